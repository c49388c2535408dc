"""Shape of an index: degrees, in-degrees, reach, components, edge lengths, bytes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.iterate import step


def in_degree(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(id, n_in) of every node."""
    n = edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("n"))
    return nodes.select("id").join(n, "id", "left").select("id", F.coalesce("n", F.lit(0)).alias("n_in"))


def graph_stats(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(nodes, edges, min_deg, max_deg, mean_deg, max_in, mean_d2)."""
    out = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"))
    deg = nodes.select("id").join(out, "id", "left").select(F.coalesce("deg", F.lit(0)).alias("deg"))
    a = deg.agg(F.count(F.lit(1)).alias("nodes"), F.sum("deg").alias("edges"), F.min("deg").alias("min_deg"), F.max("deg").alias("max_deg"), F.round(F.avg("deg"), 6).alias("mean_deg"))
    b = in_degree(edges, nodes).agg(F.max("n_in").alias("max_in"))
    c = edges.agg(F.round(F.avg("d2"), 6).alias("mean_d2"))
    return a.crossJoin(b).crossJoin(c)


def weak_components(edges: DataFrame, nodes: DataFrame, rounds: int = 100) -> DataFrame:
    """(id, comp): least id of each undirected component, by passing minima and jumping to the label's label."""
    und = step(edges.select("src", "dst").union(edges.select("dst", "src")).distinct())
    lab = step(nodes.select("id", F.col("id").alias("comp")))
    for _ in range(rounds):
        low = und.join(lab, und.dst == lab.id).groupBy("src").agg(F.min("comp").alias("low"))
        nxt = lab.join(low, lab.id == low.src, "left").select("id", F.least("comp", F.coalesce("low", "comp")).alias("comp"))
        jump = nxt.select(F.col("id").alias("comp"), F.col("comp").alias("up"))
        nxt = step(nxt.join(jump, "comp").select("id", F.col("up").alias("comp")))
        if not nxt.join(lab.withColumnRenamed("comp", "was"), "id").where("comp <> was").take(1):
            return nxt
        lab = nxt
    return lab


def footprint(v: DataFrame, degree: int, float_bytes: int = 4, id_bytes: int = 4) -> DataFrame:
    """(n, dim, vector_bytes, list_bytes): what vectors and fixed-width lists take."""
    a = v.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("dim"))
    return a.select("n", "dim", (F.col("n") * F.col("dim") * float_bytes).alias("vector_bytes"), (F.col("n") * degree * id_bytes).alias("list_bytes"))


def distance_stats(edges: DataFrame) -> DataFrame:
    """(rank, n, mean_d2, min_d2, max_d2) of a k-NN graph by rank."""
    return edges.groupBy("rank").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("d2"), 6).alias("mean_d2"), F.round(F.min("d2"), 6).alias("min_d2"), F.round(F.max("d2"), 6).alias("max_d2"))
