"""Fine-grained rounds: a node looks through the lists of its nearest unvisited neighbours, for itself only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.iterate import step
from ..core.metric import sq_l2
from .merge import update


def expand(g: DataFrame, m: int) -> DataFrame:
    """The lists with their m nearest unvisited entries marked and recorded, and those entries as ``now``."""
    now = F.slice(F.transform(F.filter("nbrs", lambda e: ~e["visited"]), lambda e: e["id"]), 1, m)
    h = g.withColumn("now", now)
    mark = F.transform("nbrs", lambda e: F.struct(e["id"].alias("id"), e["d2"].alias("d2"), e["fresh"].alias("fresh"), (e["visited"] | F.array_contains("now", e["id"])).alias("visited")))
    return h.select("src", mark.alias("nbrs"), F.array_union("seen", "now").alias("seen"), "now")


def refine(g: DataFrame, v: DataFrame, m: int, k: int, take: int | None = None, prefilter: str | None = None) -> DataFrame:
    """One fine round. ``prefilter='triangle'`` drops a neighbour's neighbour w where |d(v,u) - d(u,w)| shows that it cannot enter."""
    h = step(expand(g, m))
    far = F.transform("nbrs", lambda e: F.struct(e["id"].alias("id"), e["d2"].alias("d2")))
    lists = h.select(F.col("src").alias("mid"), (F.slice(far, 1, take) if take else far).alias("theirs"))
    pair = h.select("src", F.transform("nbrs", lambda e: e["id"]).alias("own"), F.when(F.size("nbrs") >= k, F.element_at("nbrs", -1)["d2"]).alias("kth"), F.explode(F.filter("nbrs", lambda e: F.array_contains("now", e["id"]))).alias("e"))
    pair = pair.select("src", "own", "kth", F.col("e.id").alias("mid"), F.col("e.d2").alias("near"))
    met = pair.join(lists, "mid").select("src", "own", "kth", "near", F.explode("theirs").alias("w")).where((F.col("w.id") != F.col("src")) & ~F.array_contains("own", F.col("w.id")))
    if prefilter == "triangle":
        met = met.where(F.col("kth").isNull() | (F.abs(F.sqrt("near") - F.sqrt("w.d2")) < F.sqrt("kth")))
    pairs = met.select("src", F.col("w.id").alias("partner")).distinct()
    x, y = v.select(F.col("id").alias("src"), F.col("vec").alias("xv")), v.select(F.col("id").alias("partner"), F.col("vec").alias("yv"))
    offers = pairs.join(x, "src").join(y, "partner").select(F.col("src").alias("target"), "partner", sq_l2(F.col("xv"), F.col("yv")).alias("d2"))
    return update(h.drop("now"), offers, k, fresh=False)
