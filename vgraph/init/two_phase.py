"""Drivers of the initialisers: two-phase descent, its single phases, and the two baselines of the same family."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.iterate import step
from .local_join import local_join
from .merge import update
from .refine import refine
from .sample import groups, sample_lists
from .start import random_graph


def shared_round(g: DataFrame, v: DataFrame, k: int, s: int, it: int, seed: int = 42, keep: str = "tile", tile: int = 4, reverse: bool = True) -> DataFrame:
    """One shared round: all reads see the lists of the round's start, so the result does not depend on any order."""
    offers = local_join(groups(g, s, it, seed, reverse), v, keep, tile)
    sampled = sample_lists(g, s, it, seed).select("src", F.col("fresh").alias("took"))
    aged = g.join(sampled, "src").select("src", F.transform("nbrs", lambda e: F.struct(e["id"].alias("id"), e["d2"].alias("d2"), (e["fresh"] & ~F.array_contains("took", e["id"])).alias("fresh"), e["visited"].alias("visited"))).alias("nbrs"), "seen")
    return update(aged, offers, k)


def two_phase_descent(v: DataFrame, k: int, it1: int, it2: int, sample: int, m: int = 2, tile: int = 4, keep: str = "tile", seed: int = 42, reverse: bool = True, delta: float = 0.0, take: int | None = None, prefilter: str | None = None, trace: Callable | None = None) -> DataFrame:
    """Lists after it1 shared and it2 fine rounds over dense ids; each round is one written table.

    With ``delta`` the loop ends early when fewer than that share of list entries changed (one scalar a round reaches the driver).
    It serves small sets and polishing across shards; inside a shard the resident kernel runs the same rounds."""
    n = v.count()
    g = step(random_graph(v, k, seed, n))
    if trace:
        trace(0, g)
    for it in range(1, it1 + it2 + 1):
        nxt = step(shared_round(g, v, k, sample, it, seed, keep, tile, reverse) if it <= it1 else refine(g, v, m, k, take, prefilter))
        if trace:
            trace(it, nxt)
        if delta:
            old, new = (x.select("src", F.explode("nbrs.id").alias("dst")) for x in (g, nxt))
            if new.join(old, ["src", "dst"], "left_anti").count() < delta * n * k:
                g = nxt
                break
        g = nxt
    return g


def phase1_only(v: DataFrame, k: int, it: int, sample: int, **kw) -> DataFrame:
    return two_phase_descent(v, k, it, 0, sample, **kw)


def phase2_only(v: DataFrame, k: int, it: int, m: int = 2, **kw) -> DataFrame:
    return two_phase_descent(v, k, 0, it, 1, m=m, **kw)


def descent_full(v: DataFrame, k: int, it: int, sample: int, **kw) -> DataFrame:
    """The textbook baseline: shared groups, every nearer pair kept."""
    return two_phase_descent(v, k, it, 0, sample, keep="all", **kw)


def descent_single(v: DataFrame, k: int, it: int, sample: int, **kw) -> DataFrame:
    """The baseline that keeps one result a node and round."""
    return two_phase_descent(v, k, it, 0, sample, keep="one", **kw)
