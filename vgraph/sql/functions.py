"""``register(spark)``: SQL functions for distances, angles, the portable mix and merging, and table functions for graphs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..core.mix import MULT, PRIME, ROUNDS
from ..core.ship import ship

FUNCTIONS = {
    "sq_l2(a array<double>, b array<double>) returns double": "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)",
    "l2(a array<double>, b array<double>) returns double": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
    "inner_product(a array<double>, b array<double>) returns double": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "cosine_distance(a array<double>, b array<double>) returns double": "1 - aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x) / nullif(sqrt(aggregate(a, 0D, (s, x) -> s + x * x)) * sqrt(aggregate(b, 0D, (s, x) -> s + x * x)), 0D)",
    "apex_angle(pa double, pb double, ab double) returns double": "case when pa = 0 or pb = 0 then 0D else degrees(acos(greatest(-1D, least(1D, (pa + pb - ab) / (2 * sqrt(pa) * sqrt(pb)))))) end",
    "merge_lists(a array<struct<d2: double, id: bigint>>, b array<struct<d2: double, id: bigint>>, k int) returns array<struct<d2: double, id: bigint>>": "slice(array_sort(array_distinct(concat(a, b))), 1, k)",
    "conflict_fold(rank array<int>, blockers array<array<int>>, degree int) returns array<int>": "aggregate(arrays_zip(rank, blockers), cast(array() as array<int>), (kept, e) -> case when size(kept) < degree and not arrays_overlap(kept, e.blockers) then array_append(kept, e.rank) else kept end)",
    "mix(parts array<bigint>) returns bigint": f"aggregate(sequence(1, {ROUNDS}), aggregate(parts, 1L, (h, x) -> pmod(h * {MULT} + pmod(x, {PRIME}L) + 1, {PRIME}L)), (h, i) -> pmod(h * {MULT} + 1, {PRIME}L))",
}


@udtf(returnType="step int, load int, evict int")
class DispatchSteps:
    """Greedy dispatch of a cluster graph given as JSON: {"edges": [[a, b, w], ...], "clusters": c, "cache": n}."""

    def eval(self, graph: str):
        import json

        from vgraph.shard.dispatch import overlap_dispatch

        g = json.loads(graph)
        w: dict[int, dict[int, int]] = {}
        for a, b, k in g["edges"]:
            w.setdefault(a, {})[b] = k
            w.setdefault(b, {})[a] = k
        for i, (load, evict) in enumerate(overlap_dispatch(w, g["clusters"], g["cache"], g.get("first", 0))):
            yield i, load, evict


@udtf(returnType="id bigint, rank int, d2 double")
class NearestOf:
    """Rows of one query against a packed block: ids and vectors as arrays."""

    def eval(self, query: list, ids: list, vecs: list, k: int):
        x, q = np.asarray(vecs, float), np.asarray(query, float)
        d = ((x - q) ** 2).sum(1)
        for r, i in enumerate(np.lexsort((np.asarray(ids), d))[:k]):
            yield int(ids[i]), r + 1, float(d[i])


@udtf(returnType="src bigint, dst bigint, rank int, d2 double")
class KnnGraph:
    """``select * from knn_graph(table(v) with single partition, 10)``: the exact k-NN graph of a table (id, vec) of at most LIMIT rows;
    ``partition by`` in its place gives one graph for each part, each held by one task."""

    LIMIT = 200_000

    def __init__(self):
        self.ids, self.vecs, self.k = [], [], 0

    def eval(self, row, k: int):
        self.ids.append(row["id"])
        self.vecs.append(row["vec"])
        self.k = k
        if len(self.ids) > self.LIMIT:
            raise ValueError("knn_graph: too many rows for one task; use facade.knn_graph")

    def terminate(self):
        from vgraph.kernel.descent_np import exact_lists

        if len(self.ids) > 1:
            order = np.argsort(np.asarray(self.ids), kind="stable")
            ids, x = np.asarray(self.ids)[order], np.asarray(self.vecs, float)[order]
            g = exact_lists(x, min(self.k, len(ids) - 1), ids)
            for i, (to, d2) in enumerate(zip(g.to, g.d2, strict=True)):
                for r, (j, d) in enumerate(zip(to.tolist(), d2.tolist(), strict=True)):
                    yield int(ids[i]), int(ids[j]), r + 1, float(d)


@F.arrow_udf("double")
def sq_l2_arrow(a: pa.Array, b: pa.Array) -> pa.Array:
    """Squared distance of two vector columns, a batch at a time."""
    n = len(a)
    if not n:
        return pa.array([], pa.float64())
    x, y = (np.asarray(c.flatten().to_numpy(zero_copy_only=False), float).reshape(n, -1) for c in (a, b))
    return pa.array(((x - y) ** 2).sum(1))


def register_search(spark: SparkSession, index, name: str = "search", limit: int = 200_000) -> None:
    """``select * from search(array(...), 10)``, laterally for a table of queries: best-first search over an index of at most ``limit``
    nodes, which travels with the function. Larger indexes are searched by ``Index.search``."""
    from vgraph.shard.build import resident_graph

    rows = index.vectors.select("id", "vec").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError("the index is too large to travel with a function")
    ids = np.array([r.id for r in rows], np.int64)
    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], np.array([r.vec for r in rows], float)[order]
    graph = resident_graph(ids, index.edges.select("src", "dst", "rank").toArrow())

    class Search:
        def eval(self, vec: list, k: int):
            from vgraph.kernel import search_np as S

            got, d, _, _ = S.beam(x, graph, np.asarray(vec, float), k, max(64, 2 * k), [S.entry_point(x, ids)], ids=ids)
            for r, (i, v) in enumerate(zip(got.tolist(), d.tolist(), strict=True)):
                yield int(ids[i]), r + 1, float(v)

    spark.udtf.register(name, udtf(Search, returnType="id bigint, rank int, d2 double"))


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.udf.register("v_sq_l2", sq_l2_arrow)
    spark.udtf.register("knn_graph", KnnGraph)
    for head, body in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {head} return {body}")
    spark.udtf.register("dispatch_steps", DispatchSteps)
    spark.udtf.register("nearest_of", NearestOf)


def register_graph(spark: SparkSession, edges, name: str = "neighbours") -> None:
    """A view (src, dst, rank, d2) that SQL joins laterally: ``from t, lateral (select * from neighbours where src = t.id and rank <= 5)``."""
    edges.createOrReplaceTempView(name)


def packed(v):
    """One block row of a bounded set for ``nearest_of``."""
    return v.agg(F.collect_list("id").alias("ids"), F.collect_list("vec").alias("vecs"))
