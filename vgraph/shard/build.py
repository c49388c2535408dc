"""Local builds: one shard's rows in one Arrow task, the whole build resident there."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..core.ship import ship
from ..core.types import DBL, INT, LOCAL, LONG
from ..prune.rules import RECIPES, Rule


def resident_build(x: np.ndarray, rule: Rule, k: int, init: dict, ids: np.ndarray | None = None) -> list[np.ndarray]:
    """Lists of row numbers: initialise, collect, filter. ``init``: {'method': 'two_phase' | 'exact' | 'random', ...settings}; its
    'target' ends the descent at that recall of sampled rows."""
    from ..kernel import descent_np as D
    from ..kernel import prune_np as P
    from ..kernel import search_np as S

    n = len(x)
    if n < 2:
        return [np.zeros(0, np.int64)] * n
    ids = np.arange(n) if ids is None else ids
    how = dict(init)
    method = how.pop("method", "two_phase")
    k = min(k, n - 1)
    if method == "exact":
        g = D.exact_lists(x, k)
    elif method == "random":
        g = D.random_lists(x, k, how.get("seed", 42))
    else:
        target = how.pop("target", None)
        trace = D.until_recall(x, k, target) if target else None
        g = D.two_phase(x, k, how.pop("it1", 6), how.pop("it2", 6), how.pop("sample", 8), trace=trace, **how)
    if rule.metric == "rank":
        return [r[r >= 0] for r in P.detour_prune(g.to, rule.degree, rule.hop)]
    if rule.mode == "1-hop":
        cand = [r[r >= 0][: rule.candidates] for r in g.to]
    elif rule.mode == "2-hop":
        cand = S.two_hop(x, g.to, rule.candidates)
    else:
        own = [r[r >= 0] for r in g.to]
        cand = S.path_candidates(x, own, rule.candidates, rule.pool, S.entry_point(x), own)
    return P.prune_lists(x, cand, rule.metric, rule.thres, rule.degree, rule.fill, rule.kernel)[0]


def _frame(b):
    ids = b.column("id").to_numpy(zero_copy_only=False).astype(np.int64) if hasattr(b.column("id"), "to_numpy") else np.asarray(b.column("id"))
    order = np.argsort(ids, kind="stable")
    col = b.column("vec").combine_chunks() if hasattr(b.column("vec"), "combine_chunks") else b.column("vec")
    x = np.asarray(col.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(len(ids), -1) if len(ids) else np.zeros((0, 1))
    return ids[order], x[order]


def build_local(v: DataFrame, assigned: DataFrame, recipe: str | Rule = "occlusion_relaxed", k: int = 32, init: dict | None = None, limit: int = 2_000_000) -> DataFrame:
    """(shard, src, dst, rank, d2) of every shard's local index; ids stay global. A shard above ``limit`` rows is refused: plan smaller ones."""
    return build_rows(with_vectors(v, assigned), recipe, k, init, limit)


def with_vectors(v: DataFrame, assigned: DataFrame) -> DataFrame:
    """(shard, id, vec): the one shuffle of the vectors, m copies of each."""
    return assigned.select("shard", "id").join(v.select("id", F.col("vec").cast("array<double>").alias("vec")), "id").select("shard", "id", "vec")


def build_rows(rows: DataFrame, recipe: str | Rule = "occlusion_relaxed", k: int = 32, init: dict | None = None, limit: int | None = 2_000_000) -> DataFrame:
    """The same from rows that carry their shard and vector."""
    rule = RECIPES[recipe] if isinstance(recipe, str) else recipe
    init = init or {}
    ship(rows.sparkSession)

    def one(key, table):
        from ..core.metric import sq_l2_pairs

        if limit is not None and table.num_rows > limit:
            raise ValueError(f"a shard of {table.num_rows} rows: split it first")
        ids, x = _frame(table)
        lists = resident_build(x, rule, k, init, ids)
        src = np.repeat(np.arange(len(ids)), [len(g) for g in lists])
        dst = np.concatenate(lists) if len(src) else np.zeros(0, np.int64)
        d = sq_l2_pairs(x, src, dst)
        rank = np.concatenate([np.arange(1, len(g) + 1) for g in lists]) if len(src) else src
        return pa.table({"shard": pa.array(np.full(len(src), key[0].as_py()), pa.int32()), "src": pa.array(ids[src] if len(src) else src, pa.int64()), "dst": pa.array(ids[dst] if len(src) else dst, pa.int64()), "rank": pa.array(rank, pa.int32()), "d2": pa.array(d, pa.float64())})

    return rows.groupBy("shard").applyInArrow(one, LOCAL)


GRAPH_OUT = {"path": T.StructType([T.StructField("src", LONG), T.StructField("dst", LONG), T.StructField("hop", INT), T.StructField("rank", INT), T.StructField("d2", DBL)])}


def in_shards(v: DataFrame, edges: DataFrame, what: str, **kw) -> DataFrame:
    """Run a resident search over a graph and its vectors, shard by shard (``shard`` column in both, else one shard).

    'path': candidates of every node."""
    ship(v.sparkSession)
    one_shard = "shard" not in v.columns
    vv = (v.withColumn("shard", F.lit(0)) if one_shard else v).select("shard", "id", F.col("vec").cast("array<double>").alias("vec"))
    ee = (edges.withColumn("shard", F.lit(0)) if one_shard else edges).select("shard", "src", "dst", "rank")

    def run(key, left, right):
        from ..core.metric import sq_l2_pairs
        from ..kernel import search_np as S

        ids, x = _frame(left)
        graph = resident_graph(ids, right)
        cand = S.path_candidates(x, graph, kw["size"], kw["pool"], S.entry_point(x, ids), graph, kw.get("log", "seen"), ids)
        src = np.repeat(np.arange(len(ids)), [len(c) for c in cand])
        dst = np.concatenate(cand) if len(src) else np.zeros(0, np.int64)
        hop = np.concatenate([np.where(np.isin(c, g), 1, 3) for c, g in zip(cand, graph, strict=True)]) if len(src) else src
        rank = np.concatenate([np.arange(1, len(c) + 1) for c in cand]) if len(src) else src
        return pa.table({"src": pa.array(ids[src], pa.int64()), "dst": pa.array(ids[dst], pa.int64()), "hop": pa.array(hop, pa.int32()), "rank": pa.array(rank, pa.int32()), "d2": pa.array(sq_l2_pairs(x, src, dst), pa.float64())})

    return vv.groupBy("shard").cogroup(ee.groupBy("shard")).applyInArrow(run, GRAPH_OUT[what])


def resident_graph(ids: np.ndarray, edges: pa.Table) -> list[np.ndarray]:
    """Row-number lists in rank order of edges that name global ids (``ids`` sorted)."""
    src, dst, rank = (np.asarray(edges.column(c).to_numpy()) for c in ("src", "dst", "rank"))
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    ok = (s < len(ids)) & (d < len(ids))
    ok[ok] &= (ids[s[ok]] == src[ok]) & (ids[d[ok]] == dst[ok])
    s, d, rank = s[ok], d[ok], rank[ok]
    order = np.lexsort((rank, s))
    s, d = s[order], d[order]
    cut = np.searchsorted(s, np.arange(len(ids) + 1))
    return [d[cut[i] : cut[i + 1]] for i in range(len(ids))]
