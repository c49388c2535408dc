"""Driver queries of the methods, variants, baselines and measures, on the given tables. Twins are in ``oracles``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import data
from .core import metric
from .core.iterate import step
from .core.mix import mix
from .core.types import flat, nested
from .exact import exact_knn_graph, exact_search, filtered_search, range_search
from .init import local_join as lj
from .init import merge as mg
from .init import sample as sp
from .init import start as st
from .init.refine import refine
from .init.two_phase import phase1_only, phase2_only, two_phase_descent
from .measure import graph as gm
from .measure.recall import graph_recall, recall
from .prune import collect as pc
from .prune import filter as pf
from .prune import rank as pr
from .prune import store as ps
from .prune.pipeline import prune
from .prune.rules import Rule
from .search.beam import batch_search, beam_search, filtered_index_search, sharded_search
from .shard import dispatch as dp
from .shard import kmeans as km
from .shard import replay as rp
from .shard.assign import assign_overlap, overlap_stats, shard_sizes
from .shard.build import build_local, build_rows
from .shard.cache_merge import CacheMerge
from .shard.merge import merge_locals, merge_ordered
from .shard.overlap import cluster_graph, window_overlap

K, SEED, S, TILE, M = 10, 42, 5, 4, 2
CLUSTERS, CACHE = 20, 4
QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in cols or ("d2",)})


def emb(s: SparkSession, d: str) -> DataFrame:
    return data.embeddings(s, d)


def knn(s: SparkSession, d: str, k: int = K) -> DataFrame:
    return step(exact_knn_graph(emb(s, d), k))


# -- exact answers ----------------------------------------------------------------------------------
@query
def exact_knn(s, d):
    return rounded(exact_knn_graph(emb(s, d), K))


@query
def exact_search_queries(s, d):
    v = emb(s, d)
    return rounded(exact_search(v, data.query_set(v), K, exclude_self=True))


@query
def range_search_queries(s, d):
    v = emb(s, d)
    return rounded(range_search(v, data.query_set(v), 1.2))


@query
def filtered_search_label(s, d):
    v = data.table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")
    return rounded(filtered_search(v, data.query_set(v.select("id", "vec")), K, F.col("label") == 3))


@query
def distance_matrix_stats(s, d):
    return gm.distance_stats(exact_knn_graph(emb(s, d), K))


# -- initialisation ---------------------------------------------------------------------------------
@query
def random_graph(s, d):
    return rounded(flat(st.random_graph(emb(s, d), K, SEED)))


@query
def random_graph_recall(s, d):
    v = emb(s, d)
    return graph_recall(flat(st.random_graph(v, K, SEED)), exact_knn_graph(v, K), K)


@query
def reverse_graph(s, d):
    return st.reverse(exact_knn_graph(emb(s, d), K).select("src", "dst"), 8, SEED)


@query
def merge_rank(s, d):
    """Odd and even ranks of a list merged again by counting ranks."""
    e = F.struct("d2", F.col("dst").alias("id"))
    g = exact_knn_graph(emb(s, d), K).groupBy("src").agg(F.array_sort(F.collect_list(F.when(F.col("rank") % 2 == 1, e))).alias("a"), F.array_sort(F.collect_list(F.when(F.col("rank") % 2 == 0, e))).alias("b"))
    m = g.select("src", F.posexplode(mg.rank_merge(F.col("a"), F.col("b"), K)).alias("p", "e"))
    return rounded(m.select("src", F.col("e.id").alias("dst"), (F.col("p") + 1).alias("rank"), F.col("e.d2").alias("d2")))


def _half_old(s, d):
    """A random graph in which the portable mix made some entries old."""
    g = st.random_graph(emb(s, d), K, SEED)
    old = F.transform("nbrs", lambda e: F.struct(e["id"].alias("id"), e["d2"].alias("d2"), (mix(7, F.col("src"), e["id"]) % 2 == 0).alias("fresh"), F.lit(False).alias("visited")))
    return step(g.select("src", old.alias("nbrs"), "seen"))


@query
def sample_fresh_old(s, d):
    x = sp.sample_lists(_half_old(s, d), S, 1, SEED)
    a, b = (x.select("src", F.lit(n).alias("part"), F.explode(n).alias("dst")) for n in ("fresh", "old"))
    return a.union(b)


def _offers(s, d, keep):
    g = _half_old(s, d)
    return rounded(lj.local_join(sp.groups(g, S, 1, SEED), emb(s, d), keep, TILE))


@query
def local_join_all(s, d):
    return _offers(s, d, "all")


@query
def local_join_tile(s, d):
    return _offers(s, d, "tile")


@query
def local_join_single(s, d):
    return _offers(s, d, "one")


@query
def local_join_one_iter(s, d):
    from .init.two_phase import shared_round

    return rounded(flat(shared_round(_half_old(s, d), emb(s, d), K, S, 1, SEED, "tile", TILE)))


@query
def refine_one_iter(s, d):
    return rounded(flat(refine(_half_old(s, d), emb(s, d), M, K)))


def _recall_of(lists, s, d):
    return graph_recall(flat(lists), exact_knn_graph(emb(s, d), K), K)


@query
def two_phase_final(s, d):
    return _recall_of(two_phase_descent(emb(s, d), K, 4, 4, S), s, d)


@query
def two_phase_triangle(s, d):
    return _recall_of(two_phase_descent(emb(s, d), K, 3, 3, S, prefilter="triangle"), s, d)


@query
def phase1_final(s, d):
    return _recall_of(phase1_only(emb(s, d), K, 6, S), s, d)


@query
def phase2_final(s, d):
    return _recall_of(phase2_only(emb(s, d), K, 6, M), s, d)


# -- pruning ----------------------------------------------------------------------------------------
@query
def collect_1hop(s, d):
    return rounded(pc.collect_1hop(knn(s, d), 8))


@query
def collect_2hop(s, d):
    return rounded(pc.collect_2hop(knn(s, d), emb(s, d), 20))


@query
def collect_path(s, d):
    return rounded(pc.collect_path(knn(s, d), emb(s, d), 20, 32))


def _pruned(s, d, rule, tier="columns"):
    return rounded(prune(emb(s, d), knn(s, d), rule, tier))


@query
def prune_strict(s, d):
    return _pruned(s, d, Rule.dist(1.0, degree=50))


@query
def prune_relaxed(s, d):
    return _pruned(s, d, Rule.dist(1.2, degree=6))


@query
def prune_angle(s, d):
    return _pruned(s, d, Rule.angle(60.0, degree=50, mode="2-hop", candidates=20))


@query
def prune_dispersion(s, d):
    return _pruned(s, d, Rule.angle(0.0, degree=5))


@query
def prune_detour(s, d):
    return pr.detour_prune(knn(s, d), 5)


@query
def prune_custom(s, d):
    """A user's own predicate: a kept neighbour forbids what is nearer to it than half the owner's distance."""
    return _pruned(s, d, Rule.custom(lambda pi, pj, ij: 2 * ij <= pj, degree=50))


@query
def prune_wavefront_eq(s, d):
    return _pruned(s, d, Rule.dist(1.0, degree=50, kernel="wavefront"), "kernel")


@query
def prune_serial_eq(s, d):
    return _pruned(s, d, Rule.dist(1.0, degree=50, kernel="serial"), "kernel")


@query
def prune_dispersion_kernel(s, d):
    return _pruned(s, d, Rule.angle(0.0, degree=5), "kernel")


@query
def prune_path_relaxed(s, d):
    return _pruned(s, d, Rule.dist(1.2, degree=32, mode="path", candidates=64, pool=32), "kernel")


@query
def detour_counts(s, d):
    return pr.detours(knn(s, d))


@query
def detour_counts_backward(s, d):
    return pr.detours(knn(s, d), "backward", "per_candidate")


@query
def detour_work_unbalanced(s, d):
    return pr.detour_work(knn(s, d), "per_candidate")


@query
def detour_work_paired(s, d):
    return pr.detour_work(knn(s, d), "paired")


@query
def store_filled(s, d):
    """Strict occlusion topped up to six with the nearest pruned."""
    return _pruned(s, d, Rule.dist(1.0, degree=6, fill=True))


@query
def store_padded(s, d):
    g = ps.finish(prune(emb(s, d), knn(s, d), Rule.dist(1.0, degree=8), "kernel"), emb(s, d), pad=8)
    return g.select("src", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",").alias("nbrs"), "deg")


@query
def entry_point(s, d):
    return rounded(ps.entry_point(emb(s, d)))


@query
def graph_stats(s, d):
    return gm.graph_stats(knn(s, d), emb(s, d))


@query
def in_degree(s, d):
    return gm.in_degree(knn(s, d), emb(s, d))


@query
def reachability(s, d):
    v = emb(s, d)
    return ps.reached(knn(s, d), ps.entry_point(v)).groupBy("hop").agg(F.count(F.lit(1)).alias("n"))


@query
def weak_components(s, d):
    return gm.weak_components(knn(s, d, 3), emb(s, d)).groupBy("comp").agg(F.count(F.lit(1)).alias("n"))


@query
def footprint(s, d):
    return gm.footprint(emb(s, d), 32)


# -- search -----------------------------------------------------------------------------------------
#: Rows of one resident index, on average, at most.
RESIDENT = 4096


def _sharded(v, n):
    """``v`` with a shard: as many of equal expected size, by hashed id, as ``n`` rows need. All are searched, so none needs to be a region."""
    return v.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(-(-n // RESIDENT))).cast("int"))


def _index(s, d):
    """Vectors and edges of an index of all rows; above RESIDENT rows both carry a shard, and every query is to be sent to all shards."""
    v = emb(s, d)
    n = v.count()
    if n > RESIDENT:
        v = _sharded(v, n)
        return v, step(build_rows(v, "occlusion_relaxed", 32))
    return v, step(build_local(v, v.select(F.lit(0).alias("shard"), "id"), "occlusion_relaxed", 32).drop("shard"))


@query
def search_recall(s, d):
    v, g = _index(s, d)
    q = data.query_set(v)
    return recall(exact_search(v, q, K), beam_search(v, g, q, K, 64), K)


@query
def batch_search_recall(s, d):
    v, g = _index(s, d)
    q = data.query_set(v)
    return recall(exact_search(v, q, K), batch_search(v, g, q, K, 64), K)


@query
def search_io(s, d):
    v, g = _index(s, d)
    b = beam_search(v, g, data.query_set(v), K, 64, width=4)
    return b.select("qid", "expanded", "computed").distinct()


@query
def filtered_index_recall(s, d):
    """Recall of searches over the index for rows of one label against the exact filtered answer."""
    v, g = _index(s, d)
    lab = data.table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), "label")
    if "shard" in v.columns:
        lab = _sharded(lab, lab.count())
    q = data.query_set(v)
    return recall(filtered_search(lab, q, K, "label % 2 = 0"), filtered_index_search(lab, g, q, K, "label % 2 = 0"), K)


@query
def metric_variants(s, d):
    """Euclidean, cosine and inner-product distance of each query to rows of the next id."""
    v = emb(s, d)
    q = data.query_set(v).select((F.col("qid") + 1).alias("id"), F.col("vec").alias("qv"))
    j = q.join(v, "id")
    return j.select("id", *[F.round(metric.distance(F.col("qv"), F.col("vec"), m), 6).alias(m) for m in ("l2", "cosine", "inner")])


# -- shards -----------------------------------------------------------------------------------------
def _seeded(s, d, m=M):
    v = emb(s, d)
    return v, km.seeds(v, CLUSTERS, SEED)


def _assigned(s, d, m=M):
    v, c = _seeded(s, d)
    return step(assign_overlap(v, c, m))


@query
def assign_overlapping(s, d):
    return rounded(_assigned(s, d))


@query
def kmeans_assign(s, d):
    return rounded(_assigned(s, d, 1)).select("shard", "id", "d2")


@query
def kmeans_step(s, d):
    v, c = _seeded(s, d)
    return km.seeds_table(km.kmeans_step(v, c), s).select("shard", F.posexplode("vec").alias("p", "x")).withColumn("x", F.round("x", 6))


@query
def cluster_overlap_graph(s, d):
    return cluster_graph(_assigned(s, d))


@query
def shard_size_table(s, d):
    return shard_sizes(_assigned(s, d))


@query
def shard_overlap_stats(s, d):
    return overlap_stats(_assigned(s, d))


def _order(s, d, how):
    w = dp.weights(cluster_graph(_assigned(s, d)))
    return {"greedy": lambda: dp.overlap_dispatch(w, CLUSTERS, CACHE), "sequential": lambda: dp.order_sequential(CLUSTERS, CACHE), "random": lambda: dp.order_random(CLUSTERS, CACHE), "locality": lambda: dp.order_locality_window(w, CLUSTERS, CACHE)}[how]()


@query
def dispatch_greedy(s, d):
    return dp.as_table(s, _order(s, d, "greedy"))


@query
def dispatch_sequential(s, d):
    return dp.as_table(s, _order(s, d, "sequential"))


@query
def dispatch_locality(s, d):
    return dp.as_table(s, _order(s, d, "locality"))


@query
def cache_replay_sequential(s, d):
    return rp.hit_ratio(rp.replay_cache(_assigned(s, d), dp.as_table(s, _order(s, d, "sequential"))))


@query
def cache_replay_greedy(s, d):
    return rp.hit_ratio(rp.replay_cache(_assigned(s, d), dp.as_table(s, _order(s, d, "greedy"))))


@query
def io_operations(s, d):
    return rp.io_ops(rp.replay_cache(_assigned(s, d), dp.as_table(s, _order(s, d, "sequential"))))


@query
def window_objective(s, d):
    return window_overlap(dp.as_table(s, _order(s, d, "sequential")), cluster_graph(_assigned(s, d)), CACHE)


def _exact_locals(s, d):
    """Every shard's exact graph, as its local index."""
    v = emb(s, d)
    return step(build_local(v, _assigned(s, d), Rule("1-hop", "dist", 1e9, 8, 8), 8, {"method": "exact"}))


def _local_lists(s, d):
    from .baseline.run import run

    v = emb(s, d)
    return step(run(v, "divide_conquer", _assigned(s, d), k=8, leaf=1 << 30, reps=1))


@query
def merge_of_locals(s, d):
    return rounded(merge_locals(_local_lists(s, d), 8))


@query
def merge_of_locals_ordered(s, d):
    return rounded(merge_ordered(_local_lists(s, d), dp.as_table(s, _order(s, d, "greedy")), CACHE, 8))


def _through_cache(s, d, how):
    """Exact local lists of every shard taken through the cache wave by wave."""
    a, order = _assigned(s, d), _order(s, d, how)
    flow = CacheMerge.start(a, dp.as_table(s, order), CACHE, 8)
    local = _local_lists(s, d)
    for w in range((len(order) + CACHE - 1) // CACHE):
        loads = [x for x, _ in order[w * CACHE : (w + 1) * CACHE]]
        flow.wave(w, local.where(F.col("shard").isin(loads)).select("shard", "src", "dst", "d2"))
    return flow


@query
def cache_merge_graph(s, d):
    return rounded(_through_cache(s, d, "greedy").edges(s))


@query
def cache_merge_io(s, d):
    """Lists read back and written by the executed merge, under the columns of the replay's count."""
    f = _through_cache(s, d, "sequential")
    return s.createDataFrame([(f.reads, f.writes)], "reads long, writes long")


@query
def sharded_graph_recall(s, d):
    from .shard.pipeline import sharded_build

    v = emb(s, d)
    b = sharded_build(v, Rule("1-hop", "rank", 0.0, K, hop="forward"), 8, 3, 4, K, {"method": "exact"}, rounds=3)
    return graph_recall(b.edges, exact_knn_graph(v, K), K)


@query
def sharded_search_recall(s, d):
    v = emb(s, d)
    cent = km.seeds(v, 8, SEED)
    a = step(assign_overlap(v, cent, 3))
    local = step(build_local(v, a, "occlusion_relaxed", 24))
    q = data.query_set(v)
    return recall(exact_search(v, q, K), sharded_search(v, local, a, cent, q, K, probe=6), K)


# -- derived vectors --------------------------------------------------------------------------------
@query
def doc_vectors(s, d):
    return data.doc_vec(s, d, 96).select("id", F.posexplode("vec").alias("p", "x")).where("x > 0").select("id", "p", F.round("x", 6).alias("x"))


@query
def line_vectors(s, d):
    return data.line_vec(s, d).select("id", *[F.round(F.get("vec", i), 6).alias(f"x{i}") for i in range(4)])


@query
def event_vectors(s, d):
    return data.event_vec(s, d).select("id", *[F.round(F.get("vec", i), 4).alias(f"x{i}") for i in range(6)])


def as_nested(edges: DataFrame) -> DataFrame:
    return nested(edges)
