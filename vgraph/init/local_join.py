"""The shared join: members of an anchor are compared with each other; every member uses the same batch."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.metric import sq_l2


def compare(groups: DataFrame, v: DataFrame) -> DataFrame:
    """(anchor, a, b, apos, bpos, d2): each fresh-fresh pair once and each fresh-old pair, both ends' positions kept."""
    m = groups.join(v.select(F.col("id").alias("member"), "vec"), "member")
    x = m.where("part = 0").select("anchor", F.col("member").alias("a"), F.col("pos").alias("apos"), F.col("vec").alias("av"))
    y = m.select("anchor", F.col("member").alias("b"), F.col("pos").alias("bpos"), F.col("vec").alias("bv"))
    return x.join(y, "anchor").where("apos < bpos").select("anchor", "a", "b", "apos", "bpos", sq_l2(F.col("av"), F.col("bv")).alias("d2"))


def offers(pairs: DataFrame, keep: str = "tile", tile: int = 4) -> DataFrame:
    """(target, partner, d2) after retention: 'all', 'tile' (nearest of each run of ``tile`` partners of an anchor) or 'one' a node."""
    o = pairs.select("anchor", F.col("a").alias("target"), F.col("b").alias("partner"), F.col("bpos").alias("pos"), "d2").union(pairs.select("anchor", "b", "a", "apos", "d2"))
    best = F.min(F.struct("d2", "partner")).alias("x")
    if keep == "all":
        return o.select("target", "partner", "d2").distinct()
    if keep == "tile":
        r = o.groupBy("target", "anchor", F.floor(F.col("pos") / tile).alias("run")).agg(best)
    elif keep == "one":
        r = o.groupBy("target").agg(best)
    else:
        raise ValueError(f"unknown retention {keep}")
    return r.select("target", F.col("x.partner").alias("partner"), F.col("x.d2").alias("d2")).distinct()


def local_join(groups: DataFrame, v: DataFrame, keep: str = "tile", tile: int = 4) -> DataFrame:
    return offers(compare(groups, v), keep, tile)
