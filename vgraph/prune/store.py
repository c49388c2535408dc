"""Final lists: fill, pad, entry point, reachability, files."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..core.iterate import step
from ..core.metric import sq_l2


def fill(kept: DataFrame, cand: DataFrame, degree: int) -> DataFrame:
    """Kept edges topped up to ``degree`` with the nearest pruned candidates, which come after all kept ones."""
    k = kept.select("src", "dst", "rank", "d2", F.lit(0).alias("late"))
    rest = cand.select("src", "dst", "rank", "d2", F.lit(1).alias("late")).join(kept.select("src", "dst"), ["src", "dst"], "left_anti")
    w = Window.partitionBy("src").orderBy("late", "rank")
    both = k.union(rest.select("src", "dst", "rank", "d2", "late"))
    return both.withColumn("place", F.row_number().over(w)).where(F.col("place") <= degree).select("src", "dst", F.col("place").alias("rank"), "d2")


def finish(edges: DataFrame, nodes: DataFrame | None = None, pad: int | None = None) -> DataFrame:
    """(src, nbrs, deg): one row a node; with ``pad`` lists have that length, -1 behind."""
    g = edges.groupBy("src").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "dst"))), lambda e: e["dst"]).alias("nbrs"))
    if nodes is not None:
        g = nodes.select(F.col("id").alias("src")).join(g, "src", "left").select("src", F.coalesce("nbrs", F.array().cast("array<bigint>")).alias("nbrs"))
    deg = F.size("nbrs").alias("deg")
    if pad:
        return g.select("src", F.slice(F.concat("nbrs", F.array_repeat(F.lit(-1).cast("long"), pad)), 1, pad).alias("nbrs"), deg)
    return g.select("src", "nbrs", deg)


def entry_point(v: DataFrame) -> DataFrame:
    """(id, d2): the node nearest the mean vector, ties by id."""
    mean = v.select(F.posexplode("vec").alias("p", "x")).groupBy("p").agg(F.avg("x").alias("x")).agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "x"))), lambda e: e["x"]).alias("mean"))
    d = v.crossJoin(F.broadcast(mean)).select("id", sq_l2(F.col("vec"), F.col("mean")).alias("d2"))
    return d.agg(F.min(F.struct("d2", "id")).alias("b")).select("b.id", "b.d2")


def reached(edges: DataFrame, entry: DataFrame, rounds: int = 200) -> DataFrame:
    """(id, hop): nodes reached from the entry, by frontier joins; each round is one written table."""
    seen = step(entry.select(F.col("id").cast("long").alias("id"), F.lit(0).alias("hop")))
    front = seen
    for h in range(1, rounds):
        nxt = step(edges.join(front.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct().join(seen, "id", "left_anti").withColumn("hop", F.lit(h)))
        if not nxt.take(1):
            break
        seen, front = step(seen.union(nxt)), nxt
    return seen


def repair(edges: DataFrame, v: DataFrame, entry: DataFrame, spare: DataFrame, rounds: int = 20) -> DataFrame:
    """Edges with every unreached node hung on its nearest reached neighbour of ``spare`` (the unpruned graph), round by round."""
    add = edges.select("src", "dst", "rank", "d2")
    for _ in range(rounds):
        r = reached(add, entry)
        out = v.select("id").join(r, "id", "left_anti")
        if not out.take(1):
            break
        near = spare.join(out.withColumnRenamed("id", "src"), "src", "left_semi").join(r.select(F.col("id").alias("dst")), "dst", "left_semi")
        new = near.groupBy("src").agg(F.min(F.struct("d2", "dst")).alias("b")).select(F.col("b.dst").alias("src"), F.col("src").alias("dst"), F.lit(1 << 20).alias("rank"), F.col("b.d2").alias("d2"))
        if not new.take(1):
            break
        add = step(add.union(new))
    return add
