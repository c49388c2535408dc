"""Random start and reverse edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..core.metric import sq_l2
from ..core.mix import mix
from ..core.types import nested


def slots(n: int, k: int, seed: int):
    """Column: the k distinct ids proposed for ``id`` over dense ids 0..n-1 (2k hashed slots, then the ids that follow)."""
    if n - 1 <= k:
        return F.transform(F.sequence(F.lit(0).cast("long"), F.lit(max(n - 2, 0)).cast("long")), lambda t: F.pmod(F.col("id") + 1 + t, F.lit(n)))
    hashed = F.transform(F.sequence(F.lit(0), F.lit(2 * k - 1)), lambda t: F.pmod(F.col("id") + 1 + mix(F.col("id"), t, seed) % (n - 1), F.lit(n)))
    after = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda t: F.pmod(F.col("id") + 1 + t, F.lit(n)))
    return F.slice(F.array_distinct(F.concat(hashed, after)), 1, k)


def random_graph(v: DataFrame, k: int, seed: int = 42, n: int | None = None) -> DataFrame:
    """Random lists over dense ids 0..n-1, sorted by (d2, id); entries are fresh and unvisited. One vector fetch by shuffle join."""
    n = v.count() if n is None else n
    if n < 2:
        return nested(v.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(0.0).alias("d2")).where(F.lit(False)))
    e = v.select(F.col("id").alias("src"), F.col("vec").alias("sv"), F.explode(slots(n, k, seed)).alias("dst"))
    return nested(e.join(v.select(F.col("id").alias("dst"), F.col("vec").alias("dv")), "dst").select("src", "dst", sq_l2(F.col("sv"), F.col("dv")).alias("d2")))


def reverse(edges: DataFrame, cap: int | None = None, seed: int = 42) -> DataFrame:
    """(src, dst) of the reversed edges; at most ``cap`` a node, those of least mix. A hub is cut down before anything is collected."""
    r = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    if cap is None:
        return r
    w = Window.partitionBy("src").orderBy(mix(seed, F.col("src"), F.col("dst")), "dst")
    return r.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= cap).drop("__r")
