"""Rank-only pruning: edges with many detours go. No vector is read."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def detours(edges: DataFrame, hop: str = "forward", kernel: str = "paired") -> DataFrame:
    """(src, dst, rank, detours) of every edge: how many middles k of the source's list come before dst there and hold dst before that rank too.

    'forward' reads dst's place in k's list; 'backward' k's place in dst's list. ``kernel`` 'paired' groups the counts of ranks that sum to
    k + 2 in one unit of equal work before they are separated again; 'per_candidate' counts edge by edge. Counts are partial sums."""
    e = edges.select("src", "dst", "rank")
    mid = e.select("src", F.col("dst").alias("mid"), F.col("rank").alias("r1"))
    if hop == "forward":
        far = e.select(F.col("src").alias("mid"), "dst", F.col("rank").alias("r2"))
    else:
        far = e.select(F.col("dst").alias("mid"), F.col("src").alias("dst"), F.col("rank").alias("r2"))
    tri = mid.join(far, "mid").select("src", "dst", F.greatest("r1", "r2").alias("r"))
    hit = tri.join(e, ["src", "dst"]).where(F.col("r") < F.col("rank"))
    if kernel == "paired":
        k = edges.agg(F.max("rank").alias("k"))
        unit = hit.crossJoin(F.broadcast(k)).withColumn("unit", F.least("rank", F.col("k") + 2 - F.col("rank")))
        count = unit.groupBy("src", "unit", "rank", "dst").agg(F.count(F.lit(1)).alias("n")).select("src", "dst", "n")
    else:
        count = hit.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    return e.join(count, ["src", "dst"], "left").select("src", "dst", "rank", F.coalesce("n", F.lit(0)).alias("detours"))


def detour_prune(edges: DataFrame, degree: int, hop: str = "forward", kernel: str = "paired") -> DataFrame:
    """(src, dst, rank, detours): the ``degree`` edges of fewest detours, ties by rank; ``rank`` is the place among them."""
    w = Window.partitionBy("src").orderBy("detours", "rank")
    d = detours(edges, hop, kernel)
    return d.withColumn("place", F.row_number().over(w)).where(F.col("place") <= degree).select("src", "dst", F.col("place").alias("rank"), "detours")


def detour_work(edges: DataFrame, kernel: str = "per_candidate") -> DataFrame:
    """(kernel, units, max_scans, mean_scans, total_scans): work units of the detour count over all lists.

    The candidate at rank r scans r - 1 entries; pairs u + v = k + 2 scan k together."""
    size = edges.groupBy("src").agg(F.max("rank").alias("k"))
    u = edges.join(size, "src").select("src", "k", "rank")
    if kernel == "paired":
        u = u.where("rank >= 2").groupBy("src", F.least("rank", F.col("k") + 2 - F.col("rank")).alias("unit")).agg(F.sum(F.col("rank") - 1).alias("scans"))
    else:
        u = u.select("src", (F.col("rank") - 1).alias("scans"))
    return u.agg(F.lit(kernel).alias("kernel"), F.count(F.lit(1)).alias("units"), F.max("scans").cast("long").alias("max_scans"), F.round(F.avg("scans"), 6).alias("mean_scans"), F.sum("scans").alias("total_scans"))
