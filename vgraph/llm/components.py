"""Connected components by repeated contraction, wholly as DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import is_empty, stored, unstore


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, comp) for every node of ``edges`` (columns a, b: long); comp is the least node of the component.

    Each round maps every node to the first of itself and its neighbours in that round's order
    (ids first, then a new hash order each time, so that paths shrink by a constant share) and
    contracts the edges. Stars, however large, go in one or two rounds. A hub's neighbours are aggregated
    before they are shuffled; its edges meet its map row in a sort-merge join of an exchange that AQE may split, since each
    node has one map row. An empty input gives an empty result.
    """
    e = stored(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    maps = None
    for r in range(rounds):
        if is_empty(e):
            break

        def order(c, r=r):
            return F.struct(F.lit(0).cast("long") if r == 0 else F.xxhash64(c, F.lit(r)), c)

        ends = e.select(F.col("a").alias("v"), F.col("b").alias("u")).union(e.select("b", "a"))
        best = ends.groupBy("v").agg(F.min(order(F.col("u"))).alias("m"))
        to = stored(best.select("v", F.when(order(F.col("v")) <= F.col("m"), F.col("v")).otherwise(F.col("m")["u"]).alias("p")))
        up = to.select(F.col("v").alias("p"), F.col("p").alias("pp"))
        to = stored(to.join(up, "p").select("v", F.col("pp").alias("p")))  # one more step up: halves the rounds
        joined = e.join(to.select(F.col("v").alias("a"), F.col("p").alias("pa")), "a").join(to.select(F.col("v").alias("b"), F.col("p").alias("pb")), "b")
        nxt = stored(joined.where("pa <> pb").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct())
        if maps is None:
            maps = to.select(F.col("v").alias("node"), F.col("p").alias("comp"))
        else:
            maps = stored(maps.join(to.withColumnRenamed("v", "comp"), "comp", "left").select("node", F.coalesce("p", "comp").alias("comp")))
        unstore(e)
        e = nxt
    else:
        raise RuntimeError("components did not settle")
    if maps is None:
        return e.select(F.col("a").alias("node"), F.col("b").alias("comp"))
    least = maps.groupBy("comp").agg(F.min("node").alias("least"))
    return maps.join(least, "comp").select("node", F.col("least").alias("comp"))
