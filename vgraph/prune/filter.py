"""Filters over candidate sets.

A predicate on (owner, kept, candidate) does not depend on what else is kept, so which ranks forbid which is computed for a whole
candidate set at once; what remains sequential is a fold over short integer arrays. Greedy in rank order is the
lexicographically first independent set of that conflict relation, for the serial and the wavefront order alike.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..core.metric import apex_angle, sq_l2
from ..core.ship import ship
from ..core.types import LONG
from .rules import Rule


def gathered(cand: DataFrame, v: DataFrame) -> DataFrame:
    """(src, c): the owner's candidates in rank order with their vectors; one shuffle of n * size vectors."""
    j = cand.join(v.select(F.col("id").alias("dst"), F.col("vec").alias("v")), "dst")
    return j.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("rank", "dst", "d2", "v"))).alias("c"))


def forbids(rule: Rule) -> callable:
    """Column predicate of (d2 owner-kept, d2 owner-candidate, d2 kept-candidate)."""
    if rule.conflict:
        return rule.conflict
    if rule.metric == "dist":
        return lambda pi, pj, ij: pj >= rule.thres * rule.thres * ij
    return lambda pi, pj, ij: apex_angle(pi, pj, ij) <= rule.thres


def conflicts(g: DataFrame, rule: Rule) -> DataFrame:
    """(src, c, blockers): for each candidate the ranks before it that forbid it."""
    test = forbids(rule)

    def blockers(e, j):
        return F.transform(F.filter(F.slice("c", 1, j), lambda o: test(o["d2"], e["d2"], sq_l2(o["v"], e["v"]))), lambda o: o["rank"])

    return g.select("src", "c", F.transform("c", lambda e, j: blockers(e, j)).alias("blockers"))


def fold(rank: Column, blockers: Column, degree: int) -> Column:
    """Ranks kept in order: each is kept unless a kept one forbids it, until ``degree`` are."""
    pairs = F.arrays_zip(rank.alias("r"), blockers.alias("b"))
    return F.aggregate(pairs, F.array().cast("array<int>"), lambda kept, e: F.when((F.size(kept) < degree) & ~F.arrays_overlap(kept, e["b"]), F.concat(kept, F.array(e["r"]))).otherwise(kept))


def kept_rows(g: DataFrame, kept: Column) -> DataFrame:
    """(src, dst, rank, d2) of kept ranks; ``rank`` is the place among the kept."""
    k = g.select("src", "c", F.posexplode(kept).alias("p", "r"))
    e = F.get("c", F.col("r") - 1)
    return k.select("src", e["dst"].alias("dst"), (F.col("p") + 1).alias("rank"), e["d2"].alias("d2"))


def filter_columns(cand: DataFrame, v: DataFrame, rule: Rule) -> DataFrame:
    """The rule in column functions: conflict lists and the fold, or the dispersion steps."""
    g = gathered(cand, v)
    if rule.metric == "angle" and rule.thres == 0 and not rule.conflict:
        return dispersion_columns(g, rule.degree)
    c = conflicts(g, rule)
    return kept_rows(c, fold(F.transform("c", lambda e: e["rank"]), F.col("blockers"), rule.degree))


def dispersion_columns(g: DataFrame, degree: int) -> DataFrame:
    """Greedy choice by angle sums: the nearest first, then always the candidate of greatest sum of angles to the kept, ties by rank."""
    angle = F.transform("c", lambda a: F.transform("c", lambda b: apex_angle(a["d2"], b["d2"], sq_l2(a["v"], b["v"]))))
    a = g.select("src", "c", angle.alias("ang"))
    start = F.struct(F.array(F.lit(1)).alias("kept"), F.get("ang", F.lit(0)).alias("sums"))

    def one(s, _):
        left = F.filter(F.transform(s["sums"], lambda x, i: F.struct(F.round(x, 9).alias("x"), (-i - 1).alias("neg"))), lambda e: ~F.array_contains(s["kept"], -e["neg"]))
        best = -F.array_max(left)["neg"]
        return F.when(F.size(left) > 0, F.struct(F.concat(s["kept"], F.array(best)).alias("kept"), F.zip_with(s["sums"], F.get("ang", best - 1), lambda x, y: x + y).alias("sums"))).otherwise(s)

    steps = F.when(F.lit(degree) > 1, F.sequence(F.lit(2), F.lit(max(degree, 2)))).otherwise(F.array().cast("array<int>"))
    return kept_rows(a.select("src", "c", F.aggregate(steps, start, one)["kept"].alias("kept")), F.col("kept"))


OUT = T.StructType([T.StructField("src", LONG), T.StructField("dst", LONG), T.StructField("rank", T.IntegerType()), T.StructField("d2", T.DoubleType())])


def filter_kernel(cand: DataFrame, v: DataFrame, rule: Rule, pick: str = "nearest") -> DataFrame:
    """The same by the resident kernels, one owner a row: ``rule.kernel`` 'serial' or 'wavefront'.

    A row holds the vectors of all its candidates, so an Arrow batch takes few of them unless the session has its own setting."""
    from ..kernel import prune_np

    spark, size = v.sparkSession, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if spark.conf.get(size) == "10000":
        spark.conf.set(size, "256")
    g = gathered(cand, v)
    ship(spark)

    def each(batches):
        for b in batches:
            out = ([], [], [], [])
            for at in range(b.num_rows):  # one owner's candidates as Python objects at a time
                s, c = b.column(0)[at].as_py(), b.column(1).slice(at, 1).flatten()
                ids, dp, x = c.field("dst").to_pylist(), c.field("d2").to_numpy(), c.field("v").flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1)
                if rule.metric == "angle" and rule.thres == 0:
                    kept, _ = prune_np.dispersion(x, dp, rule.degree)
                elif rule.kernel == "serial":
                    kept, _ = prune_np.serial(x, dp, rule.metric, rule.thres, rule.degree)
                else:
                    kept, _ = prune_np.wavefront(x, dp, rule.metric, rule.thres, rule.degree, pick)
                for r, j in enumerate(kept):
                    for o, val in zip(out, (s, ids[j], r + 1, float(dp[j])), strict=True):
                        o.append(val)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int32()), pa.array(out[3], pa.float64())], names=OUT.names)

    return g.mapInArrow(each, OUT)
