"""Best-first search over an index. A shard's graph and vectors are resident in one task; its queries come to it."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..core.mix import mix_np
from ..core.ship import ship
from ..core.types import DBL, INT, LONG
from ..shard.assign import assign_overlap
from ..shard.build import _frame, resident_graph

FOUND = T.StructType([T.StructField("shard", INT), T.StructField("qid", LONG), T.StructField("id", LONG), T.StructField("d2", DBL), T.StructField("expanded", INT), T.StructField("computed", INT)])
VEC = T.ArrayType(DBL)
ROW = T.StructType([T.StructField("shard", INT), T.StructField("kind", INT), T.StructField("id", LONG), T.StructField("vec", VEC), T.StructField("dst", LONG), T.StructField("rank", INT)])


def _search(v: DataFrame, edges: DataFrame, q: DataFrame, k: int, pool: int, width: int, starts: int, seed: int, allowed: bool = False) -> DataFrame:
    """v, edges and q carry a shard; (shard, qid, id, d2, expanded, computed). With ``allowed`` v has a boolean column ``ok``: the search
    walks over all nodes and answers with the nearest of those it met that are ok (``rank`` carries the flag)."""
    ship(v.sparkSession)
    none = F.lit(None)
    flag = F.col("ok").cast(INT) if allowed else none.cast(INT)
    rows = (
        v.select("shard", F.lit(0).alias("kind"), "id", F.col("vec").cast(VEC).alias("vec"), none.cast(LONG).alias("dst"), flag.alias("rank"))
        .union(edges.select("shard", F.lit(1), F.col("src"), none.cast(VEC), "dst", F.col("rank").cast(INT)))
        .union(q.select("shard", F.lit(2), F.col("qid"), F.col("vec").cast(VEC), none.cast(LONG), none.cast(INT)))
    )

    def run(key, t):
        from ..kernel import search_np as S

        import pyarrow.compute as pc

        part = lambda kind: t.filter(pc.equal(t.column("kind"), kind))
        own = part(0)
        ids, x = _frame(own)
        ok = None
        if allowed and len(ids):
            ok = np.asarray(own.column("rank").to_numpy(zero_copy_only=False))[np.argsort(np.asarray(own.column("id").to_numpy()), kind="stable")] == 1
        e = part(1)
        graph = resident_graph(ids, pa.table({"src": e.column("id"), "dst": e.column("dst"), "rank": e.column("rank")}))
        qids, qx = _frame(part(2))
        out = [[], [], [], [], []]
        if len(ids):
            first = [S.entry_point(x, ids)]
            for i, qv in zip(qids.tolist(), qx, strict=True):
                # random starts come from the portable mix; one start is the entry point
                begin = first if starts <= 1 else sorted({int(mix_np(seed, i, s) % len(ids)) for s in range(starts)})
                got, d, log, exp = S.beam(x, graph, qv, k, pool, begin, width, ids)
                if ok is not None:
                    met = np.array(log)
                    met = met[ok[met]]
                    far = ((x[met] - qv) ** 2).sum(1)
                    best = np.lexsort((ids[met], far))[:k]
                    got, d = met[best], far[best]
                for o, val in zip(out, ([i] * len(got), ids[got].tolist(), d.tolist(), [exp] * len(got), [len(log)] * len(got)), strict=True):
                    o += val
        s = key[0].as_py()
        return pa.table({"shard": pa.array([s] * len(out[0]), pa.int32()), "qid": pa.array(out[0], pa.int64()), "id": pa.array(out[1], pa.int64()), "d2": pa.array(out[2], pa.float64()), "expanded": pa.array(out[3], pa.int32()), "computed": pa.array(out[4], pa.int32())})

    return rows.groupBy("shard").applyInArrow(run, FOUND)


def _best(found: DataFrame, k: int) -> DataFrame:
    one = found.groupBy("qid", "id").agg(F.min("d2").alias("d2"))
    cost = found.groupBy("qid", "shard").agg(F.max("expanded").alias("e"), F.max("computed").alias("c")).groupBy("qid").agg(F.sum("e").alias("expanded"), F.sum("c").alias("computed"))
    w = Window.partitionBy("qid").orderBy("d2", "id")
    top = one.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return top.join(cost, "qid").select("qid", "id", F.col("rank").cast(INT).alias("rank"), "d2", "expanded", "computed")


def _placed(v: DataFrame, edges: DataFrame, q: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """All three with their shard: where vectors and edges have one, every query goes to every shard; else all is one shard."""
    if "shard" in v.columns:
        return v, edges, q.crossJoin(F.broadcast(v.select("shard").distinct()))  # a row for each shard
    zero = F.lit(0).cast(INT)
    return v.withColumn("shard", zero), edges.withColumn("shard", zero), q.withColumn("shard", zero)


def beam_search(v: DataFrame, edges: DataFrame, q: DataFrame, k: int, pool: int = 64, width: int = 1) -> DataFrame:
    """(qid, id, rank, d2, expanded, computed) from the entry point of an index that one worker holds. ``expanded`` is the number of list
    fetches (a disk-resident index would read as many), ``computed`` of distances. With a ``shard`` in ``v`` and ``edges``
    every shard is searched from its own entry point, and costs add up."""
    return _best(_search(*_placed(v, edges, q), k, pool, width, 1, 0), k)


def filtered_index_search(v: DataFrame, edges: DataFrame, q: DataFrame, k: int, where, pool: int = 128) -> DataFrame:
    """Search over an index of all rows for the nearest rows that the predicate ``where`` on the other columns of ``v`` lets through.

    The walk uses every node, so that a rare value does not cut the graph apart; among the nodes whose distance it computed, the
    nearest allowed ones are the answer. A wider pool meets more of them; ``filtered_search`` is the exact answer."""
    ok = F.expr(where) if isinstance(where, str) else where
    flagged = v.withColumn("ok", F.coalesce(ok, F.lit(False)))
    return _best(_search(*_placed(flagged, edges, q), k, pool, 1, 1, 0, True), k)


def batch_search(v: DataFrame, edges: DataFrame, q: DataFrame, k: int, pool: int = 64, width: int = 4, starts: int = 8, seed: int = 42) -> DataFrame:
    """The same from several random starts, several expansions a step."""
    return _best(_search(*_placed(v, edges, q), k, pool, width, starts, seed), k)


def sharded_search(v: DataFrame, local: DataFrame, assigned: DataFrame, cent: np.ndarray, q: DataFrame, k: int, probe: int = 2, pool: int = 64) -> DataFrame:
    """Queries go to their ``probe`` nearest shards, each searched with its own local index (shard, src, dst, rank), answers merged."""
    routed = assign_overlap(q.select(F.col("qid").alias("id"), "vec"), cent, probe).select("shard", F.col("id").alias("qid")).join(q, "qid").select("shard", "qid", "vec")
    rows = assigned.select("shard", "id").join(v.select("id", "vec"), "id").select("shard", "id", "vec")
    return _best(_search(rows, local, routed, k, pool, 1, 1, 0), k)


def merged_search(v: DataFrame, edges: DataFrame, assigned: DataFrame, cent: np.ndarray, q: DataFrame, k: int, probe: int = 2, pool: int = 64) -> DataFrame:
    """The same over a merged index: each probed shard holds the merged lists of its own nodes."""
    local = assigned.select("shard", F.col("id").alias("src")).join(edges, "src").select("shard", "src", "dst", "rank")
    return sharded_search(v, local, assigned, cent, q, k, probe, pool)


def beam_columns(v: DataFrame, edges: DataFrame, q: DataFrame, k: int, pool: int, entry: DataFrame, rounds: int = 60) -> DataFrame:
    """The search as frontier joins: every round expands each query's nearest unexpanded pool member, joins its list, drops what was seen, and
    keeps the pool's nearest. For an index that no single worker holds; each round is one written table."""
    from ..core.iterate import step
    from ..core.metric import sq_l2

    qv = q.select("qid", F.col("vec").alias("qv"))
    d = sq_l2(F.col("qv"), F.col("vec")).alias("d2")
    state = step(qv.crossJoin(F.broadcast(entry.select("id"))).join(v, "id").select("qid", "id", d, F.lit(False).alias("done")))
    seen = state.select("qid", "id")
    near = Window.partitionBy("qid").orderBy("d2", "id")
    for _ in range(rounds):
        go = state.where(~F.col("done")).withColumn("r", F.row_number().over(near)).where("r = 1").select("qid", "id")
        go = step(go)
        if not go.take(1):
            break
        new = step(go.join(edges.select(F.col("src").alias("id"), "dst"), "id").select("qid", F.col("dst").alias("id")).distinct().join(seen, ["qid", "id"], "left_anti"))
        got = new.join(v, "id").join(qv, "qid").select("qid", "id", d, F.lit(False).alias("done"))
        aged = state.join(go.withColumn("now", F.lit(True)), ["qid", "id"], "left").select("qid", "id", "d2", (F.col("done") | F.coalesce("now", F.lit(False))).alias("done"))
        state = step(aged.union(got).withColumn("r", F.row_number().over(near)).where(F.col("r") <= pool).drop("r"))
        seen = step(seen.union(new))
    return state.withColumn("rank", F.row_number().over(near)).where(F.col("rank") <= k).select("qid", "id", "rank", "d2")
