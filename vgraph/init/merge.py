"""Viability cut and list update; the rank form of merging two sorted lists."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def viable(offers: DataFrame, g: DataFrame, k: int) -> DataFrame:
    """(target, cand): per target at most k nearest offers that are nearer than its list's last and not in the list.

    The cut runs before offers are gathered, so no more than k of them meet in a row."""
    kth = g.select(F.col("src").alias("target"), F.when(F.size("nbrs") >= k, F.element_at("nbrs", -1)["d2"]).alias("kth"), F.transform("nbrs", lambda e: e["id"]).alias("own"))
    o = offers.where("target <> partner").join(kth, "target")
    o = o.where((F.col("kth").isNull() | (F.col("d2") < F.col("kth"))) & ~F.array_contains("own", F.col("partner")))
    from pyspark.sql.window import Window

    w = Window.partitionBy("target").orderBy("d2", "partner")
    top = o.dropDuplicates(["target", "partner"]).withColumn("r", F.row_number().over(w)).where(F.col("r") <= k)
    return top.groupBy("target").agg(F.array_sort(F.collect_list(F.struct("d2", F.col("partner").alias("id")))).alias("cand"))


def update(g: DataFrame, offers: DataFrame, k: int, fresh: bool = True) -> DataFrame:
    """Lists with the viable offers merged in; admitted entries get the flag ``fresh`` and, outside the shared rounds, remember visits."""
    c = viable(offers, g, k)
    j = g.join(c.withColumnRenamed("target", "src"), "src", "left")
    new = F.transform(F.coalesce("cand", F.array().cast("array<struct<d2:double,id:bigint>>")), lambda e: F.struct(e["d2"].alias("d2"), e["id"].alias("id"), F.lit(fresh).alias("fresh"), (F.array_contains("seen", e["id"]) if not fresh else F.lit(False)).alias("visited")))
    old = F.transform("nbrs", lambda e: F.struct(e["d2"].alias("d2"), e["id"].alias("id"), e["fresh"].alias("fresh"), e["visited"].alias("visited")))
    both = F.slice(F.array_sort(F.concat(old, new)), 1, k)
    back = F.transform(both, lambda e: F.struct(e["id"].alias("id"), e["d2"].alias("d2"), e["fresh"].alias("fresh"), e["visited"].alias("visited")))
    return j.select("src", back.alias("nbrs"), "seen")


def merge_lists(a: Column, b: Column, k: int) -> Column:
    """Two sorted arrays of struct(d2, id), merged without repeats to the k nearest."""
    return F.slice(F.array_sort(F.array_distinct(F.concat(a, b))), 1, k)


def rank_merge(a: Column, b: Column, k: int) -> Column:
    """The same for arrays without common entries by ranks: an element's slot is its own index plus how many of the other list come before it."""

    def placed(x, y, strict):
        # x's elements with their slots
        return F.transform(x, lambda e, i: F.struct((i + F.size(F.filter(y, lambda o: (o < e) if strict else (o <= e)))).alias("slot"), e.alias("e")))

    both = F.concat(placed(a, b, True), placed(b, a, False))
    return F.transform(F.array_sort(F.filter(both, lambda s: s["slot"] < k)), lambda s: s["e"])
