"""Fresh and old sampling, and the groups that meet around an anchor."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..core.mix import mix


def _least(fresh: bool, s: int, it: int, seed: int) -> Column:
    picked = F.filter("nbrs", lambda e: e["fresh"] == F.lit(fresh))
    keyed = F.transform(picked, lambda e: F.struct(mix(seed, it, F.col("src"), e["id"]).alias("m"), e["id"].alias("id")))
    return F.transform(F.slice(F.array_sort(keyed), 1, s), lambda e: e["id"])


def sample_lists(g: DataFrame, s: int, it: int, seed: int = 42) -> DataFrame:
    """(src, fresh, old): at most s ids of each kind, those of least mix."""
    return g.select("src", _least(True, s, it, seed).alias("fresh"), _least(False, s, it, seed).alias("old"))


def _side(sampled: DataFrame, name: str, s: int, it: int, seed: int, reverse: bool) -> DataFrame:
    own = sampled.select(F.col("src").alias("anchor"), F.explode(name).alias("member"))
    if not reverse:
        return own
    w = Window.partitionBy("anchor").orderBy(mix(seed, it, F.col("anchor"), F.col("member")), "member")
    back = own.select(F.col("member").alias("anchor"), F.col("anchor").alias("member"))
    back = back.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= s).drop("__r")
    return own.union(back).distinct()


def groups(g: DataFrame, s: int, it: int, seed: int = 42, reverse: bool = True) -> DataFrame:
    """(anchor, member, part, pos): part 0 fresh, 1 old; pos counts the fresh by id, then the old by id. A member that is fresh is not old."""
    sampled = sample_lists(g, s, it, seed)
    both = _side(sampled, "fresh", s, it, seed, reverse).withColumn("part", F.lit(0)).union(_side(sampled, "old", s, it, seed, reverse).withColumn("part", F.lit(1)))
    one = both.groupBy("anchor", "member").agg(F.min("part").alias("part"))
    w = Window.partitionBy("anchor").orderBy("part", "member")
    return one.withColumn("pos", F.row_number().over(w) - 1)
