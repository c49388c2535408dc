"""Recall of searches and of k-NN graphs, curves and their gaps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def recall(truth: DataFrame, found: DataFrame, k: int, key: str = "qid", item: str = "id") -> DataFrame:
    """(queries, recall): mean share of the k true answers that were found; a query without answers counts 0."""
    t = truth.where(F.col("rank") <= k).select(key, item)
    hit = t.join(found.where(F.col("rank") <= k).select(key, item).distinct(), [key, item], "left_semi").groupBy(key).agg(F.count(F.lit(1)).alias("hit"))
    per = t.select(key).distinct().join(hit, key, "left").select(F.coalesce("hit", F.lit(0)).alias("hit"))
    return per.agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg(F.col("hit") / k), 6).alias("recall"))


def graph_recall(edges: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """(queries, recall) with every node as a query."""
    return recall(exact, edges, k, "src", "dst")


def curve_gap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(qps, recall_a, recall_b, gap): at each point of curve a, the recall of b at the same speed, on the line between its neighbours.

    Curves are (qps, recall); the neighbours are found by as-of windows over the union of both."""
    both = a.select("qps", F.col("recall").alias("ra"), F.lit(None).cast("double").alias("rb")).union(b.select("qps", F.lit(None).cast("double"), F.col("recall")))
    w = Window.orderBy("qps")  # a curve has a row for each setting
    down, up = w.rowsBetween(Window.unboundedPreceding, -1), w.rowsBetween(1, Window.unboundedFollowing)
    at = F.when(F.col("rb").isNotNull(), F.struct("qps", "rb"))
    j = both.withColumn("lo", F.last(at, True).over(down)).withColumn("hi", F.first(at, True).over(up)).where("ra is not null")
    share = (F.col("qps") - F.col("lo.qps")) / (F.col("hi.qps") - F.col("lo.qps"))
    rb = F.when(F.col("lo").isNull(), F.col("hi.rb")).when(F.col("hi").isNull(), F.col("lo.rb")).otherwise(F.col("lo.rb") + share * (F.col("hi.rb") - F.col("lo.rb")))
    return j.select("qps", F.col("ra").alias("recall_a"), rb.alias("recall_b"), (rb - F.col("ra")).alias("gap"))
