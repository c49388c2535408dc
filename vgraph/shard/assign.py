"""Overlapping assignment and sizes."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.metric import sq_l2
from ..core.ship import ship
from ..core.types import ASSIGNED
from .kmeans import _matrix, nearest


def assign_overlap(v: DataFrame, cent: np.ndarray, m: int = 2) -> DataFrame:
    """(shard, id, choice, d2): each row under its m nearest centroids; no shuffle. The centroids ride in the task: their number is
    a parameter, and with very many of them ``two_level`` keeps each level small."""
    ship(v.sparkSession)
    m = min(m, len(cent))

    def each(batches):
        for b in batches:
            for i in range(0, b.num_rows, 512):
                part = b.slice(i, 512)
                at, d = nearest(_matrix(part, 1), cent, m)
                ids = np.repeat(part.column(0).to_numpy(zero_copy_only=False), m)
                yield pa.RecordBatch.from_arrays([pa.array(at.ravel(), pa.int32()), pa.array(ids), pa.array(np.tile(np.arange(1, m + 1), len(at)), pa.int32()), pa.array(d.ravel())], names=ASSIGNED.names)

    return v.select(F.col("id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(each, ASSIGNED)


def assign_columns(v: DataFrame, cent: DataFrame, m: int = 2) -> DataFrame:
    """The same in column functions over a broadcast of the centroids, gathered in one row."""
    one = cent.agg(F.array_sort(F.collect_list(F.struct("shard", "vec"))).alias("cents"))
    d = v.crossJoin(F.broadcast(one)).select("id", F.slice(F.array_sort(F.transform("cents", lambda c: F.struct(sq_l2(F.col("vec"), c["vec"]).alias("d2"), c["shard"].alias("shard")))), 1, m).alias("near"))
    return d.select("id", F.posexplode("near").alias("p", "x")).select(F.col("x.shard").alias("shard"), "id", (F.col("p") + 1).alias("choice"), F.col("x.d2").alias("d2"))


def plan_shards(n: int, dim: int, memory_bytes: int, m: int = 2, width: int = 8, k: int = 64) -> int:
    """How many clusters so that an average one (m copies of n rows in all) fits a worker's memory with its lists."""
    per_row = dim * width + k * 24
    return max(1, math.ceil(n * m * per_row / memory_bytes))


def shard_sizes(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("shard").agg(F.count(F.lit(1)).alias("n"))


def overlap_stats(assigned: DataFrame) -> DataFrame:
    """(rows, nodes, replication, largest, smallest, mean_size)."""
    s = shard_sizes(assigned).agg(F.sum("n").alias("rows"), F.max("n").alias("largest"), F.min("n").alias("smallest"), F.round(F.avg("n"), 6).alias("mean_size"))
    n = assigned.where("choice = 1").agg(F.count(F.lit(1)).alias("nodes"))
    return s.crossJoin(n).select("rows", "nodes", F.round(F.col("rows") / F.col("nodes"), 6).alias("replication"), "largest", "smallest", "mean_size")


def split_oversize(v: DataFrame, assigned: DataFrame, limit: int, seed: int = 42, per: int = 256) -> DataFrame:
    """Assignment in which every shard of more than ``limit`` rows is cut by k-means of its own, again while one is too large; new
    shards get new numbers. All oversize shards of a round are cut together: their centres are learned in one grouped pass over at most
    ``per`` sampled rows a part, and one pass assigns their rows."""
    from ..core.iterate import step
    from ..core.mix import mix
    from .kmeans import lloyd

    ship(v.sparkSession)
    out = assigned
    for turn in range(16):
        sizes = {r.shard: r.n for r in shard_sizes(out).collect()}  # one row for each shard
        over = {s: math.ceil(n / limit) + 1 for s, n in sizes.items() if n > limit}
        if not over:
            return out
        base, first = max(sizes) + 1, {}
        for s in sorted(over):
            first[s], base = base, base + over[s]
        table = v.sparkSession.createDataFrame([(s, n, first[s]) for s, n in over.items()], "shard int, parts int, first int")
        rows = out.join(F.broadcast(table), "shard").join(v.select("id", F.col("vec").cast("array<double>").alias("vec")), "id")
        rows = step(rows.select("shard", "id", "choice", "d2", "vec", "parts", "first"))
        place = mix(seed + turn, F.col("id"))
        share = F.least(F.lit(1.0), 2.0 * per * F.col("parts") / F.col("n"))  # about twice the rows that are used
        counted = rows.join(F.broadcast(v.sparkSession.createDataFrame([(s, sizes[s]) for s in over], "shard int, n long")), "shard")
        sample = counted.where(place / 2147483647.0 <= share).select("shard", "id", "vec", "parts")

        def centres(key, t):
            x = np.asarray(t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(t.num_rows, -1)
            parts = int(t.column("parts")[0].as_py())
            ids = np.asarray(t.column("id").to_numpy())
            c = lloyd(x[np.argsort(ids, kind="stable")][: per * parts], parts, 4)
            return pa.table({"shard": pa.array([key[0].as_py()] * len(c), pa.int32()), "part": pa.array(range(len(c)), pa.int32()), "vec": pa.array(list(c), pa.list_(pa.float64()))})

        learned = sample.groupBy("shard").applyInArrow(centres, "shard int, part int, vec array<double>").collect()  # parts of oversize shards
        cent = {s: np.array([r.vec for r in sorted(learned, key=lambda r: r.part) if r.shard == s]) for s in over}

        def each(batches, cent=cent, first=first):
            for b in batches:
                shard = b.column(0).to_numpy(zero_copy_only=False)
                x = _matrix(b, 4)
                new = shard.copy()
                for s in np.unique(shard).tolist():
                    here = shard == s
                    new[here] = first[s] + nearest(x[here], cent[s])[0][:, 0]
                yield pa.RecordBatch.from_arrays([pa.array(new, pa.int32()), b.column(1), b.column(2), b.column(3)], names=["shard", "id", "choice", "d2"])

        cut = rows.select("shard", "id", "choice", "d2", "vec").mapInArrow(each, out.select("shard", "id", "choice", "d2").schema)
        out = step(out.join(F.broadcast(table.select("shard")), "shard", "left_anti").select("shard", "id", "choice", "d2").union(cut))
    return out
