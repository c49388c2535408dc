"""collect -> filter -> store for any rule."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .collect import collect
from .filter import filter_columns, filter_kernel
from .rank import detour_prune
from .rules import Rule
from .store import fill


def prune(v: DataFrame, edges: DataFrame, rule: Rule, tier: str = "kernel") -> DataFrame:
    """(src, dst, rank, d2): pruned edges of a flat k-NN graph. ``tier`` 'columns' keeps everything in column functions.

    alpha = 1 makes the relaxed rule the strict one; an angle threshold of 0 asks for greatest dispersion."""
    if rule.metric == "rank":
        kept = detour_prune(edges, rule.degree, rule.hop)
        return kept.join(edges.select("src", "dst", "d2"), ["src", "dst"]).select("src", "dst", "rank", "d2")
    cand = collect(edges, v, rule.mode, rule.candidates, rule.pool)
    run = filter_columns if tier == "columns" or rule.conflict else filter_kernel
    kept = run(cand, v, rule)
    return fill(kept, cand, rule.degree) if rule.fill else kept.select("src", "dst", F.col("rank").cast("int").alias("rank"), "d2")
