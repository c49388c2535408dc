"""Candidate sets: own list, two hops, or what a search for the node meets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..core.metric import sq_l2


def collect_1hop(edges: DataFrame, size: int) -> DataFrame:
    """(src, dst, hop, rank, d2): the list's nearest ``size``."""
    return edges.where(F.col("rank") <= size).select("src", "dst", F.lit(1).alias("hop"), "rank", "d2")


def collect_2hop(edges: DataFrame, v: DataFrame, size: int) -> DataFrame:
    """Own list and the lists of the listed, without the node itself, nearest ``size``; distances are computed for second hops only."""
    one = edges.select("src", "dst", "d2")
    mid = edges.select(F.col("src").alias("mid"), F.col("dst").alias("far"))
    far = edges.select("src", F.col("dst").alias("mid")).join(mid, "mid").where("far <> src").select("src", F.col("far").alias("dst")).distinct()
    far = far.join(edges.select("src", "dst"), ["src", "dst"], "left_anti")
    x, y = v.select(F.col("id").alias("src"), F.col("vec").alias("xv")), v.select(F.col("id").alias("dst"), F.col("vec").alias("yv"))
    two = far.join(x, "src").join(y, "dst").select("src", "dst", sq_l2(F.col("xv"), F.col("yv")).alias("d2"))
    both = one.withColumn("hop", F.lit(1)).union(two.withColumn("hop", F.lit(2)))
    w = Window.partitionBy("src").orderBy("d2", "dst")
    return both.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= size).select("src", "dst", "hop", "rank", "d2")


def collect_path(edges: DataFrame, v: DataFrame, size: int, pool: int, log: str = "seen") -> DataFrame:
    """Nodes that a search for each node visits from the entry point, with its own list; the graph and vectors of a shard are resident
    in one task (``shard`` column, or one shard)."""
    from ..shard.build import in_shards

    return in_shards(v, edges, "path", size=size, pool=pool, log=log)


def collect(edges: DataFrame, v: DataFrame, mode: str, size: int, pool: int = 64) -> DataFrame:
    if mode == "1-hop":
        return collect_1hop(edges, size)
    if mode == "2-hop":
        return collect_2hop(edges, v, size)
    if mode == "path":
        return collect_path(edges, v, size, pool)
    raise ValueError(f"unknown mode {mode}")
