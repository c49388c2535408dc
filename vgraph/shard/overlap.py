"""The cluster graph and the objective that a dispatch order is judged by."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def cluster_graph(assigned: DataFrame) -> DataFrame:
    """(a, b, w), a < b: how many nodes two clusters share. Pairs come from each node's own short array, without a join."""
    per = assigned.groupBy("id").agg(F.array_sort(F.collect_set("shard")).alias("s"))
    pair = per.select("s", F.posexplode("s").alias("i", "a")).select("a", F.explode(F.slice(F.col("s"), F.col("i") + 2, F.size("s"))).alias("b"))
    return pair.groupBy("a", "b").agg(F.count(F.lit(1)).alias("w"))


def window_overlap(order: DataFrame, graph: DataFrame, n: int) -> DataFrame:
    """(objective): summed weights of clusters that stand within n places of each other in a load order (step, load)."""
    o = order.select("step", "load")
    x, y = o.select(F.col("step").alias("s1"), F.col("load").alias("c1")), o.select(F.col("step").alias("s2"), F.col("load").alias("c2"))
    near = x.join(y, (F.col("s2") > F.col("s1")) & (F.col("s2") < F.col("s1") + n)).select(F.least("c1", "c2").alias("a"), F.greatest("c1", "c2").alias("b"))
    return near.join(graph, ["a", "b"]).agg(F.coalesce(F.sum("w"), F.lit(0)).alias("objective"))


def cumulative_windows(order: DataFrame, n: int) -> DataFrame:
    """(step, load, resident): clusters resident after each load, first in first out."""
    w = Window.orderBy("step").rowsBetween(-(n - 1), 0)  # one row for each cluster
    return order.withColumn("resident", F.collect_list("load").over(w))
