"""The experiments re-expressed on the given tables. Each returns measurements; sizes scale with the tables.

Resident runs take a set that one worker holds (a shard) in one Arrow task each and record what the experiment compares."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import data
from .baseline import builders as B
from .core.iterate import step
from .core.ship import ship
from .exact import exact_knn_graph, exact_search
from .kernel import descent_np as D
from .kernel import prune_np as P
from .kernel import search_np as S
from .measure.recall import recall
from .measure.timing import SCHEMA
from .prune.rules import RECIPES
from .shard import dispatch as dp
from .shard import replay as rp
from .shard.assign import assign_overlap
from .shard.build import _frame
from .shard.kmeans import kmeans
from .shard.overlap import cluster_graph, window_overlap
from .shard.pipeline import sharded_build

WORKLOADS: dict = {}


def workload(f):
    WORKLOADS[f.__name__] = f
    return f


def in_tasks(s: SparkSession, named: dict[str, DataFrame], variants: list[str], body, near: int = 0) -> DataFrame:
    """``body(x, set, variant, truth)`` -> measurement rows, one Arrow task for each vector set and variant: the resident experiments, whose
    sets are shards. ``truth`` holds the row numbers of each row's ``near`` nearest others, found by the distributed search before.

    Only measurements come back. The groups are dealt into more partitions than there are groups, so that they run side by side."""
    ship(s)
    kinds = s.createDataFrame([], SCHEMA).schema
    arrow = (pa.string(), pa.string(), pa.string(), pa.int32(), pa.string(), pa.float64())

    def one(key, t):
        ids, x = _frame(t)
        name, variant = (k.as_py() for k in key)
        truth = None
        if near and len(ids) > 1:
            order = np.argsort(np.asarray(t.column("id").to_numpy()), kind="stable")
            lists = t.column("near").combine_chunks()
            truth = np.searchsorted(ids, np.asarray(lists.flatten().to_numpy(zero_copy_only=False))).reshape(len(ids), -1)[order]
        rows = body(x, name, variant, truth) if len(x) > 1 else []
        return pa.table({f.name: pa.array([r[i] for r in rows], a) for i, (f, a) in enumerate(zip(kinds, arrow, strict=True))})

    every = None
    for name, v in named.items():
        v = v.select("id", F.col("vec").cast("array<double>").alias("vec"))
        if near:
            v = step(v)
            e = exact_knn_graph(v, near).groupBy(F.col("src").alias("id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "dst"))), lambda z: z["dst"]).alias("near"))
            v = v.join(e, "id", "left")
        v = v.withColumn("set", F.lit(name))
        every = v if every is None else every.union(v)
    groups = len(named) * len(variants)
    dealt = every.withColumn("variant", F.explode(F.array(*map(F.lit, variants)))).repartition(4 * groups, "set", "variant")
    return step(dealt.groupBy("set", "variant").applyInArrow(one, kinds))


def table(s: SparkSession, rows: list) -> DataFrame:
    return s.createDataFrame([(a, b, c, int(k), m, float(x)) for a, b, c, k, m, x in rows], SCHEMA)


#: Dimensions of the hashed-text sets beside the embeddings.
DIMS = (96, 128, 282, 960)


def sets(s: SparkSession, d: str, dims: tuple[int, ...] = (96, 282)) -> dict[str, DataFrame]:
    """The mid-dimension set and hashed whole texts of several dimensions."""
    return {"embeddings": data.embeddings(s, d)} | {f"doc_vec_{n}": data.doc_vec(s, d, n) for n in dims}


def hits(x, graph, truth, k: int = 10, pool: int = 64):
    """Recall of searches for every hundredth row, itself left out, and their seconds."""
    q = range(0, len(x), data.EVERY)
    e = S.entry_point(x)
    at = time.perf_counter()
    got = [S.beam(x, graph, x[i], k + 1, pool, [e])[0] for i in q]
    t = time.perf_counter() - at
    return float(np.mean([len(set(a.tolist()) & set(truth[i, :k].tolist())) / k for a, i in zip(got, q, strict=True)])), t, len(q)


BOTH = [f"{who}:{name}" for name in RECIPES for who in ("original", "fast")]


@workload
def w_profile_breakdown(s, d):
    """Initialisation and pruning seconds of two original builders, and the greatest memory they held at once (traced in runs of their own)."""
    import tracemalloc

    def body(x, ds, variant, _):
        what, name = variant.split(":")
        if what == "time":
            _, t = B.build(x, name, False)
            return [("profile", name, ds, 32, m, t[m]) for m in ("init_s", "prune_s", "evaluations")]
        tracemalloc.start()
        B.build(x, name, False)
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        return [("profile", name, ds, 32, "peak_bytes", float(peak))]

    return in_tasks(s, {"embeddings": data.embeddings(s, d)}, [f"{w}:{n}" for n in ("detour_rank", "occlusion_strict") for w in ("time", "memory")], body)


TRACED = {"descent_single": {"it1": 8, "it2": 0, "keep": "one"}, "descent_full": {"it1": 8, "it2": 0, "keep": "all"}, "two_phase": {"it1": 4, "it2": 4}}


@workload
def w_recall_trace(s, d):
    """Graph recall and seconds after each iteration of the single-closest, the full and the two-phase initialiser, for two list lengths,
    and the seconds until recall 0.95 (missing where it is not reached)."""

    def body(x, ds, variant, truth):
        name, k = variant.split(":")
        k, rows, at = min(int(k), len(x) - 1), [], time.perf_counter()

        def seen(it, g):
            t = time.perf_counter() - at
            r = D.recall(g.to, truth[:, :k])
            rows.extend([("trace", name, ds, k, f"recall_it{it}", r), ("trace", name, ds, k, f"seconds_it{it}", t)])
            if r >= 0.95 and not any(m[4] == "seconds_to_0.95" for m in rows):
                rows.append(("trace", name, ds, k, "seconds_to_0.95", t))

        D.two_phase(x, k, sample=8 if k < 64 else 12, trace=seen, **TRACED[name])
        return rows

    return in_tasks(s, {"embeddings": data.embeddings(s, d)}, [f"{n}:{k}" for n in TRACED for k in (32, 96)], body, 96)


@workload
def w_sampling_toy(s, d):
    """(anchor, sampling, place, member): what shared and per-node sampling offer the first entry of a list, in the random graph of the
    embeddings, for every hundredth anchor: shared compares it with the rest of the anchor's list, per-node with its own list and the
    lists of those in it; the two nearest of each, ties by id."""
    from .core.metric import sq_l2
    from .core.types import flat
    from .init.start import random_graph

    v = data.embeddings(s, d)
    g = step(flat(random_graph(v, 10)).select("src", "dst", "rank"))
    one = g.where(f"rank = 1 and src % {data.EVERY} = 0").select(F.col("src").alias("anchor"), F.col("dst").alias("fresh"))
    to = g.select(F.col("src").alias("mid"), F.col("dst").alias("member"))
    shared = one.join(to.withColumnRenamed("mid", "anchor"), "anchor").select("anchor", "fresh", F.lit("shared").alias("sampling"), "member")
    own = one.join(to.withColumnRenamed("mid", "fresh"), "fresh").select("anchor", "fresh", "member")
    far = own.withColumnRenamed("member", "mid").join(to, "mid").select("anchor", "fresh", "member")
    offered = shared.union(own.union(far).distinct().select("anchor", "fresh", F.lit("per_node"), "member")).where("member <> fresh")
    x, y = v.select(F.col("id").alias("fresh"), F.col("vec").alias("x")), v.select(F.col("id").alias("member"), F.col("vec").alias("y"))
    near = offered.join(x, "fresh").join(y, "member").withColumn("d2", sq_l2(F.col("x"), F.col("y")))
    w = Window.partitionBy("anchor", "sampling").orderBy("d2", "member")
    return near.withColumn("place", F.row_number().over(w) - 1).where("place < 2").select("anchor", "sampling", "place", "member")


def compared(rows: DataFrame, metric: str, better: str) -> DataFrame:
    """``rows`` with, for each set and recipe, how many times the original's ``metric`` the fast build's is (method without its prefix)."""
    both = rows.where(F.col("metric") == metric).select("run", F.split("method", ":").alias("m"), "dataset", "k", "value")
    wide = both.groupBy("run", F.get("m", F.lit(1)).alias("method"), "dataset", "k").agg(F.max(F.when(F.get("m", F.lit(0)) == "original", F.col("value"))).alias("o"), F.max(F.when(F.get("m", F.lit(0)) == "fast", F.col("value"))).alias("f"))
    return rows.union(wide.select("run", "method", "dataset", "k", F.lit(better).alias("metric"), (F.col("o") / F.col("f")).alias("value")))


@workload
def w_build_time(s, d):
    """Seconds of original and fast builds, their ratio, and recall of a fixed search, for each recipe and set."""

    def body(x, ds, variant, truth):
        who, name = variant.split(":")
        at = time.perf_counter()
        g, _ = B.build(x, name, who == "fast")
        t = time.perf_counter() - at
        return [("build_time", variant, ds, 10, "seconds", t), ("build_time", variant, ds, 10, "recall", hits(x, g, truth)[0])]

    return compared(in_tasks(s, sets(s, d, DIMS), BOTH, body, 10), "seconds", "speedup")


@workload
def w_other_builders(s, d):
    """Seconds and recall of the incremental, iterated, two-pass relaxed and divide-and-conquer builders.

    Above RESIDENT rows each builds an index in shards of hashed ids, each resident in a task, and every query searches all of them;
    seconds are then those of the whole build, and only the queries' true neighbours are sought."""
    from .queries import RESIDENT, _sharded

    v = data.embeddings(s, d)
    n = v.count()
    if n > RESIDENT:
        return _builders_sharded(s, v, _sharded(v, n))
    own = {
        "incremental": lambda x: B.incremental(x, 12, 32), "incremental_layers": lambda x: B.incremental(x, 12, 32, layers=True), "iterated": lambda x: B.iterated_collect_prune(x, 24, 2),
        "relaxed_two_pass": lambda x: B.relaxed_two_pass(x, 24, pool=24), "divide_conquer": lambda x: B.divide_conquer(x, 12, 100, 3),
    }

    def body(x, ds, name, truth):
        at = time.perf_counter()
        g = own[name](x)
        return [("builders", name, ds, 10, "seconds", time.perf_counter() - at), ("builders", name, ds, 10, "recall", hits(x, g, truth)[0])]

    return in_tasks(s, {"embeddings": v}, list(own), body, 10)


#: name -> (builder, settings), as ``w_other_builders`` runs them over shards.
BUILDERS = {
    "incremental": ("incremental", {"m": 12, "ef": 32}), "incremental_layers": ("incremental", {"m": 12, "ef": 32, "layers": True}), "iterated": ("iterated_collect_prune", {"degree": 24, "rounds": 2}),
    "relaxed_two_pass": ("relaxed_two_pass", {"degree": 24, "pool": 24}), "divide_conquer": ("divide_conquer", {"k": 12, "leaf": 100, "reps": 3}),
}


def _builders_sharded(s: SparkSession, v: DataFrame, placed: DataFrame) -> DataFrame:
    """Rows of ``w_other_builders`` for a set in shards. A query's own row is no answer, as in ``hits``."""
    from .baseline.run import run
    from .search.beam import beam_search

    placed, q = step(placed), step(data.query_set(v))
    truth, n, rows = step(exact_search(v, q, 10, exclude_self=True).select("qid", "id")), q.count(), []
    shards = placed.select("shard").distinct().count()
    dealt = placed.select("shard", "id").repartition(shards, "shard")
    for name, (builder, settings) in BUILDERS.items():
        at = time.perf_counter()
        g = step(run(v, builder, dealt, **settings))
        t = time.perf_counter() - at
        hit = beam_search(placed, g, q, 11, 64).select("qid", "id").join(truth, ["qid", "id"], "left_semi").count()
        rows += [("builders", name, "embeddings", 10, "seconds", t), ("builders", name, "embeddings", 10, "recall", hit / (10 * n) if n else float("nan"))]
    return table(s, rows)


@workload
def w_quality_curve(s, d):
    """Recall and queries a second by pool size, original against fast, every recipe and set."""

    def body(x, ds, variant, truth):
        g, _ = B.build(x, variant.split(":")[1], variant.startswith("fast"))
        rows = []
        for pool in (16, 32, 64, 128):
            hit, t, n = hits(x, g, truth, 10, pool)
            rows += [("curve", variant, ds, 10, f"recall_pool{pool}", hit), ("curve", variant, ds, 10, f"qps_pool{pool}", n / t)]
        return rows

    return in_tasks(s, sets(s, d, DIMS), BOTH, body, 10)


#: Many small and few large shards, as the large-scale experiment compares them.
MANY, SOME = 40, 4


@workload
def w_sharded_build(s, d):
    """Phase seconds, reads and writes of the sharded build: many small shards merged through the cache in order (overlapped with local
    builds, and in turn) against few large ones, and the disk baseline (random start, two relaxed passes, everything written first)."""
    from .baseline.run import disk_baseline
    from .measure.timing import timed

    v = step(data.embeddings_copies(s, d, 2))
    rule, init = RECIPES["occlusion_relaxed"].but(candidates=64, pool=32), {"method": "two_phase", "it1": 4, "it2": 2}
    rows = []
    for c, cache, overlap in ((MANY, 16, True), (MANY, 16, False), (SOME, 4, True)):
        b = sharded_build(v, rule, c, 2, cache, 32, init, overlap=overlap, rounds=3)
        who = f"clusters_{c}_{'overlap' if overlap else 'in_turn'}"
        rows += [("sharded", who, "embeddings_x2", 32, f"{n}_s", t) for n, t in b.seconds.items()] + [("sharded", who, "embeddings_x2", 32, "reads", b.reads), ("sharded", who, "embeddings_x2", 32, "writes", b.writes)]
    return table(s, [*rows, ("sharded", f"disk_baseline_{SOME}", "embeddings_x2", 32, "all_s", timed(lambda: disk_baseline(v, SOME, rounds=3)))])


@workload
def w_sharded_quality(s, d):
    """Recall and queries a second by pool size of merged indexes from many and from few shards, and the recall gap at equal speed where the
    many-shard index reaches recall 0.95 and 0.98. Shards are whole at every size of the input."""
    from .measure.recall import curve_gap
    from .measure.timing import qps
    from .search.beam import merged_search

    v = step(data.embeddings_copies(s, d, 2))
    q = step(data.query_set(v))
    truth, n = step(exact_search(v, q, 10)), q.count()
    rows, curves = [], {}
    for c, cache in ((MANY, 16), (SOME, 4)):
        b = sharded_build(v, RECIPES["occlusion_relaxed"].but(mode="1-hop", candidates=32), c, 2, cache, 32, {"method": "two_phase", "it1": 4, "it2": 4}, rounds=3)
        probe = max(2, c // 5)
        for pool in (16, 32, 64, 128):
            found = lambda b=b, probe=probe, pool=pool: merged_search(v, b.edges, b.assigned, b.centroids, q, 10, probe=probe, pool=pool)
            hit, speed = recall(truth, found(), 10).first().recall, qps(found, n, 0, 1)
            curves.setdefault(c, []).append((float(speed), float(hit)))
            rows += [("sharded_quality", f"clusters_{c}", "embeddings_x2", 10, f"recall_pool{pool}", hit), ("sharded_quality", f"clusters_{c}", "embeddings_x2", 10, f"qps_pool{pool}", speed)]
    many, few = (s.createDataFrame(curves[c], "qps double, recall double") for c in (MANY, SOME))
    gaps = curve_gap(many, few).collect()  # one row a pool size
    for least in (0.95, 0.98):
        got = [g.gap for g in gaps if g.recall_a >= least]
        rows.append(("sharded_quality", "gap", "embeddings_x2", 10, f"gap_at_{least}", max(got, key=abs) if got else float("nan")))
    return table(s, rows)


@workload
def w_scaling(s, d):
    """Local build seconds with the shards dealt over one, two and four tasks."""
    from .measure.timing import timed
    from .shard.build import build_local

    v = step(data.embeddings(s, d))
    a = step(assign_overlap(v, kmeans(v, 8, 3), 2))
    rows = []
    for slots in (1, 2, 4):
        one = a.withColumn("shard", F.col("shard")).repartition(slots, "shard")
        t = timed(lambda one=one: build_local(v, one, "detour_rank", 24, {"it1": 4, "it2": 0}))
        rows.append(("scaling", f"slots_{slots}", "embeddings", 24, "seconds", t))
    return table(s, rows)


PHASES = {"phase1": {"it1": 8, "it2": 0}, "phase2": {"it1": 0, "it2": 8}, "single": {"it1": 8, "it2": 0, "keep": "one"}, "two_phase": {"it1": 4, "it2": 4}, "two_phase_long": {"it1": 8, "it2": 8}}


@workload
def w_phase_ablation(s, d):
    """Recall of shared rounds only, fine rounds only, the single-closest baseline and both phases."""

    def body(x, ds, name, truth):
        at = time.perf_counter()
        g = D.two_phase(x, 32, sample=8, **PHASES[name])
        t = time.perf_counter() - at
        return [("ablation", name, ds, 32, "recall", D.recall(g.to, truth)), ("ablation", name, ds, 32, "seconds", t), ("ablation", name, ds, 32, "evaluations", float(g.evaluations))]

    return in_tasks(s, sets(s, d, (282,)), list(PHASES), body, 32)


@workload
def w_split_sweep(s, d):
    """Recall and seconds of splits of 8, 12 and 16 iterations between the phases."""
    splits = [f"{it1}+{total - it1}" for total in (8, 12, 16) for it1 in range(0, total + 1, max(2, total // 4))]

    def body(x, ds, name, truth):
        it1, it2 = map(int, name.split("+"))
        at = time.perf_counter()
        g = D.two_phase(x, 32, it1, it2, 8)
        t = time.perf_counter() - at
        return [("split", name, ds, 32, "recall", D.recall(g.to, truth)), ("split", name, ds, 32, "seconds", t)]

    return in_tasks(s, sets(s, d, (282,)), splits, body, 32)


RULES = {"occlusion_strict": ("dist", 1.0, 50), "occlusion_relaxed": ("dist", 1.2, 32), "angle_threshold": ("angle", 60.0, 50)}


@workload
def w_prune_time(s, d):
    """Pruning seconds of the same input graph by the original form of each of the five rules and by the fast one, their ratio, and whether
    the outputs agree: candidates one by one against waves, all angle sums anew against running ones, per-node counting of detours against
    counting in whole matrices."""

    def body(x, ds, name, to):
        cand, rows, out = list(to), [], {}
        for who in ("original", "fast"):
            at = time.perf_counter()
            if name in RULES:
                out[who], tests = P.prune_lists(x, cand, *RULES[name], kernel="serial" if who == "original" else "wavefront")
                rows.append(("prune_time", f"{who}:{name}", ds, 32, "tests", float(tests)))
            elif name == "angle_dispersion":
                out[who] = P.dispersion_lists(x, cand, 16, running=who == "fast")
            else:
                out[who] = list(P.detour_prune(to, 16) if who == "fast" else P.detour_prune_rows(to, 16))
            rows.append(("prune_time", f"{who}:{name}", ds, 32, "seconds", time.perf_counter() - at))
        same = all(np.array_equal(a, b) for a, b in zip(out["original"], out["fast"], strict=True))
        return [*rows, ("prune_time", name, ds, 32, "same", float(same))]

    return compared(in_tasks(s, sets(s, d, DIMS), list(RECIPES), body, 32), "seconds", "speedup")


@workload
def w_kernel_compare(s, d):
    """Work of the two detour kernels over the lists of the embeddings' random graph: greatest and mean scans of a unit, and the units
    of all lists, by the length that lists are cut to."""
    from .core.types import flat
    from .init.start import random_graph
    from .prune.rank import detour_work

    g = step(flat(random_graph(data.embeddings(s, d), 64)).select("src", "dst", "rank"))
    rows = []
    for k in (8, 16, 32, 64):
        for kernel in ("per_candidate", "paired"):
            w = detour_work(g.where(F.col("rank") <= k), kernel).first()
            rows += [("kernels", kernel, "embeddings", k, m, w[m] or 0) for m in ("max_scans", "mean_scans", "units")]
    return table(s, rows)


def _orders(w, c, n):
    return {"sequential": dp.order_sequential(c, n), "random": dp.order_random(c, n), "locality": dp.order_locality_window(w, c, n), "greedy": dp.overlap_dispatch(w, c, n)}


@workload
def w_cache_hit(s, d):
    """Cache hit ratio, I/O and window objective of four dispatch orders on the clusterable and on the isotropic set."""
    rows = []
    for ds, v in (("line_vec", data.line_vec(s, d)), ("embeddings", data.embeddings(s, d))):
        v = step(v)
        a = step(assign_overlap(v, kmeans(v, 20, 4), 2))
        g = step(cluster_graph(a))
        w = dp.weights(g)
        for name, order in _orders(w, 20, 4).items():
            o = dp.as_table(s, order)
            log = step(rp.replay_cache(a, o))
            h, io = rp.hit_ratio(log).first(), rp.io_ops(log).first()
            rows += [("cache", name, ds, 4, "ratio_revisits", h.ratio_revisits or 0.0), ("cache", name, ds, 4, "ratio_all", h.ratio_all or 0.0), ("cache", name, ds, 4, "cached_io", io.cached_io), ("cache", name, ds, 4, "baseline_io", io.baseline_exact), ("cache", name, ds, 4, "objective", window_overlap(o, g, 4).first().objective)]
    return table(s, rows)


@workload
def w_merge_compare(s, d):
    """Seconds of ordered merging and of writing everything first, and whether the merged graphs are the same."""
    from .measure.timing import timed
    from .shard.build import build_local
    from .shard.merge import merge_ordered, merge_via_disk

    v = step(data.embeddings(s, d))
    a = step(assign_overlap(v, kmeans(v, 12, 3), 2))
    local = step(build_local(v, a, RECIPES["detour_rank"].but(degree=16), 24, {"method": "exact"}))
    o = dp.as_table(s, dp.overlap_dispatch(dp.weights(cluster_graph(a)), 12, 4))
    x, y = merge_ordered(local, o, 4, 16), merge_via_disk(local, 16)
    same = x.select("src", "dst").exceptAll(y.select("src", "dst")).count() + y.select("src", "dst").exceptAll(x.select("src", "dst")).count() == 0
    return table(s, [("merge", "ordered", "embeddings", 16, "seconds", timed(lambda: merge_ordered(local, o, 4, 16))), ("merge", "via_disk", "embeddings", 16, "seconds", timed(lambda: merge_via_disk(local, 16))), ("merge", "both", "embeddings", 16, "same", float(same))])


@workload
def w_dispatch_time(s, d):
    """Seconds to plan the order of 400 clusters of the clusterable set."""
    v = step(data.line_vec(s, d))
    rows_ = v.orderBy(F.xxhash64("id"), "id").limit(400).select("vec").collect()
    a = assign_overlap(v, np.array([r[0] for r in rows_]), 2)
    w = dp.weights(cluster_graph(a))
    at = time.perf_counter()
    dp.overlap_dispatch(w, len(rows_), 16)
    return table(s, [("dispatch", "greedy", "line_vec", 16, "plan_s", time.perf_counter() - at), ("dispatch", "greedy", "line_vec", 16, "edges", sum(map(len, w.values())) / 2)])


@workload
def w_dim_sweep(s, d):
    """Serial and wavefront pruning seconds of the strict and the angle rule by dimension."""

    def body(x, ds, variant, truth):
        kernel, name = variant.split(":")
        at = time.perf_counter()
        P.prune_lists(x, list(truth), *RULES[name], kernel=kernel)
        return [("dims", variant, ds, x.shape[1], "prune_s", time.perf_counter() - at)]

    return in_tasks(s, sets(s, d, DIMS), [f"{k}:{n}" for n in ("occlusion_strict", "angle_threshold") for k in ("serial", "wavefront")], body, 24)


@workload
def w_rebuild_trigger(s, d):
    """(day, user_shard, changed, rebuild): share of vectors changed per shard and day of the event feed; a shard over the bound is rebuilt."""
    e = data.table(s, d, "events")
    day = e.groupBy(F.to_date("ts").alias("day"), (F.col("user_id") % 8).alias("user_shard")).agg(F.countDistinct("user_id").alias("changed"))
    size = e.groupBy((F.col("user_id") % 8).alias("user_shard")).agg(F.countDistinct("user_id").alias("n"))
    return day.join(size, "user_shard").select("day", "user_shard", "changed", (F.col("changed") > 0.8 * F.col("n")).alias("rebuild"))


@workload
def churn_daily(s, d):
    """(day, upserts, deletes) of the feed: errors delete, everything else upserts."""
    e = data.table(s, d, "events")
    return e.groupBy(F.to_date("ts").alias("day")).agg(F.count_if(F.col("event_type") != "error").alias("upserts"), F.count_if(F.col("event_type") == "error").alias("deletes"))
