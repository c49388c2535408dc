"""Lloyd's k-means on a bounded sample, and a two-level form for very many clusters."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..core.iterate import step
from ..core.mix import mix
from ..core.ship import ship
from ..core.types import DBL, INT, LONG


def seeds(v: DataFrame, c: int, seed: int = 42) -> np.ndarray:
    """The vectors of the c ids of least mix: c rows reach the driver."""
    rows = v.withColumn("m", mix(seed, F.col("id"))).orderBy("m", "id").limit(c).select("vec").collect()
    return np.array([r[0] for r in rows], np.float64)


PART = T.StructType([T.StructField("shard", INT), T.StructField("n", LONG), T.StructField("sum", T.ArrayType(DBL))])


def nearest(x: np.ndarray, cent: np.ndarray, m: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """The m nearest centroids of each row and their squared distances, ties to the smaller number."""
    rough = (x**2).sum(1)[:, None] + (cent**2).sum(1)[None, :] - 2 * x @ cent.T  # the product selects, differences report
    few = min(m + 4, len(cent))
    near = np.sort(np.argpartition(rough, few - 1, 1)[:, :few], 1) if few < len(cent) else np.tile(np.arange(len(cent)), (len(x), 1))
    d = ((x[:, None, :] - cent[near]) ** 2).sum(-1)
    at = np.argsort(d, axis=1, kind="stable")[:, :m]
    return np.take_along_axis(near, at, 1), np.take_along_axis(d, at, 1)


def lloyd(x: np.ndarray, c: int, rounds: int) -> np.ndarray:
    """K-means of resident rows from evenly placed ones; an empty cluster keeps its place."""
    cent = x[np.linspace(0, len(x) - 1, min(c, len(x))).astype(int)].copy()
    for _ in range(rounds):
        at = nearest(x, cent)[0][:, 0]
        for j in range(len(cent)):
            if (at == j).any():
                cent[j] = x[at == j].mean(0)
    return cent


def _matrix(b, i):
    n = b.num_rows
    return np.asarray(b.column(i).flatten().to_numpy(zero_copy_only=False), np.float64).reshape(n, -1)


def kmeans_step(v: DataFrame, cent: np.ndarray) -> np.ndarray:
    """One round: partial sums inside each partition, c rows to the driver. An empty cluster keeps its place."""
    ship(v.sparkSession)

    def partial(batches):
        n = np.zeros(len(cent), np.int64)
        s = np.zeros_like(cent)
        for b in batches:
            for i in range(0, b.num_rows, 512):
                x = _matrix(b.slice(i, 512), 0)
                at = nearest(x, cent)[0][:, 0]
                n += np.bincount(at, minlength=len(cent))
                np.add.at(s, at, x)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(cent)), pa.int32()), pa.array(n), pa.array(list(s), pa.list_(pa.float64()))], names=PART.names)

    p = v.select(F.col("vec").cast("array<double>").alias("vec")).mapInArrow(partial, PART)
    rows = p.select("shard", "n", F.posexplode("sum").alias("p", "x")).groupBy("shard", "p").agg(F.sum("n").alias("n"), F.sum("x").alias("x")).where("n > 0").collect()
    out = cent.copy()
    for r in rows:
        out[r.shard, r.p] = r.x / r.n
    return out


def kmeans(v: DataFrame, c: int, rounds: int = 8, seed: int = 42, per: int = 256) -> np.ndarray:
    """Centroids learned on at most ``per`` * c vectors, those of least mix: the bound is a parameter, assignment covers every row."""
    sample = v.withColumn("m", mix(seed + 1, F.col("id"))).orderBy("m", "id").limit(per * c).select("id", "vec")
    sample = step(sample.repartition(max(1, c // 64)))  # the bounded sample stays a table; only partial sums come to the driver
    cent = seeds(v, c, seed)
    for _ in range(rounds):
        cent = kmeans_step(sample, cent)
    return cent


def two_level(v: DataFrame, outer: int, inner: int, rounds: int = 6, seed: int = 42) -> tuple[np.ndarray, list[np.ndarray]]:
    """Outer centroids and each one's inner centroids: assignment costs outer + inner distances a row instead of their product."""
    top = kmeans(v, outer, rounds, seed)
    from .assign import assign_overlap

    a = assign_overlap(v, top, 1).select("shard", "id")
    return top, [kmeans(v.join(a.where(F.col("shard") == s), "id").select("id", "vec"), inner, rounds, seed) for s in range(len(top))]


def seeds_table(cent: np.ndarray, spark) -> DataFrame:
    return spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(cent)], "shard int, vec array<double>")
