"""Invariants of the resident kernels, worked examples, and the trends that the methods claim."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from vgraph.baseline import builders as B
from vgraph.kernel import descent_np as D
from vgraph.kernel import prune_np as P
from vgraph.kernel import search_np as S
from vgraph.shard import dispatch as dp


@pytest.fixture(scope="module")
def x():
    r = np.random.default_rng(5)
    return r.normal(size=(300, 16))


def lists_ok(g, k):
    for v, (row, d) in enumerate(zip(g.to, g.d2, strict=True)):
        own = row[row >= 0]
        assert v not in own and len(set(own.tolist())) == len(own) <= k
        assert (np.diff(d[row >= 0]) >= 0).all()


def test_descent_invariants(x):
    seen, kth = [], []

    def look(it, g):
        lists_ok(g, 12)
        seen.append(D.recall(g.to, truth))
        kth.append(g.d2[:, -1].copy())

    truth = D.exact_lists(x, 12).to
    D.two_phase(x, 12, 4, 4, 6, trace=look)
    assert all(b >= a - 1e-12 for a, b in zip(seen, seen[1:], strict=False)) and seen[-1] > 0.9
    assert all((b <= a + 1e-12).all() for a, b in zip(kth, kth[1:], strict=False))


def test_retention_order(x):
    g = D.random_lists(x, 12)
    fresh, old, _ = D.groups(g, 6, 1, 42, True, np.arange(len(x)))
    offers = {}
    for keep in ("all", "tile", "one"):
        t, p, _, _ = D.local_join(x, fresh, old, keep, 4, np.arange(len(x)))
        offers[keep] = set(zip(t.tolist(), p.tolist(), strict=True))
    assert offers["one"] <= offers["tile"] <= offers["all"]


def test_trends():
    """Phase 1 beats the single-closest baseline and phase 2 alone at eight rounds; both phases do not lose to phase 1 at sixteen, over five seeds."""
    r = np.random.default_rng(1)
    y = r.normal(size=(300, 32))
    truth = D.exact_lists(y, 16).to

    def got(**kw):
        return np.mean([D.recall(D.two_phase(y, 16, sample=6, seed=s, **kw).to, truth) for s in range(5)])

    one, two, single = got(it1=8, it2=0), got(it1=0, it2=8), got(it1=8, it2=0, keep="one")
    assert one > single and one > two
    assert got(it1=8, it2=8) >= got(it1=16, it2=0) - 0.005


def test_no_revisit(x):
    g = D.random_lists(x, 8)
    seen = [set() for _ in x]
    for _ in range(4):
        before = [set(s) for s in g.seen]
        g, _ = D.fine_round(x, g, 2)
        for v, s in enumerate(g.seen):
            new = s - before[v]
            assert not new & seen[v]
            seen[v] |= new


def test_triangle_bound_changes_nothing(x):
    a = D.two_phase(x, 10, 2, 3, 5)
    b = D.two_phase(x, 10, 2, 3, 5, prefilter="triangle")
    assert np.array_equal(a.to, b.to) and b.evaluations <= a.evaluations


@given(st.integers(0, 10_000))
@settings(max_examples=25, deadline=None)
def test_wavefront_is_serial(seed):
    r = np.random.default_rng(seed)
    v = r.integers(-3, 4, size=(12, 2)).astype(float)
    p = r.integers(-3, 4, size=2).astype(float)
    d = ((v - p) ** 2).sum(1)
    o = np.lexsort((np.arange(12), d))
    for metric, thres in (("dist", 1.0), ("dist", 1.2), ("angle", 60.5)):
        a, _ = P.serial(v[o], d[o], metric, thres, 6)
        b, _ = P.wavefront(v[o], d[o], metric, thres, 6)
        assert a == b


def test_kept_set_is_valid_and_maximal(x):
    to = D.exact_lists(x, 24).to
    for pick in ("nearest", "any"):
        kept, _ = P.prune_lists(x, list(to), "dist", 1.0, 100, pick=pick)
        for p, (k, c) in enumerate(zip(kept, to, strict=True)):
            d = {j: ((x[p] - x[j]) ** 2).sum() for j in c}
            near = sorted(k.tolist(), key=lambda j: d[j])
            for i, a in enumerate(near):
                for b in near[i + 1 :]:
                    assert pick == "any" or d[b] < ((x[a] - x[b]) ** 2).sum()
            for j in set(c.tolist()) - set(near):
                assert any(d[j] >= ((x[a] - x[j]) ** 2).sum() for a in near)


def test_line_keeps_one_neighbour_a_side():
    pts = np.array([[0.0], [1.0], [2.1], [3.3], [4.6]])
    to = D.exact_lists(pts, 4).to
    kept, _ = P.prune_lists(pts, list(to), "dist", 1.0, 9)
    assert [sorted(k.tolist()) for k in kept] == [[1], [0, 2], [1, 3], [2, 4], [3]]


def test_hexagon_angles():
    a = np.radians(np.arange(6) * 60.0)
    pts = np.vstack([[[0.0, 0.0]], np.c_[np.cos(a), np.sin(a)] * (1 + 0.001 * np.arange(6))[:, None]])
    to = D.exact_lists(pts, 6).to
    assert len(P.prune_lists(pts, [to[0]], "angle", 59.0, 9)[0][0]) == 6
    assert len(P.prune_lists(pts, [to[0]], "angle", 61.0, 9)[0][0]) == 3
    order, _ = P.dispersion(pts[to[0]], ((pts[to[0]]) ** 2).sum(1), 2)
    assert to[0][order[1]] == 4  # the opposite of the nearest, which is 1


def test_slack_and_duplicates():
    pts = np.array([[0.0, 0.0], [1.0, 0.0], [1.0, 0.95]])
    c = [np.array([1, 2])]
    assert P.prune_lists(pts, c, "dist", 1.0, 9)[0][0].tolist() == [1]
    two = np.array([[0.0, 0.0], [1.0, 0.0], [0.55, 1.05]])  # between the distances and 1.2 times them
    assert P.prune_lists(two, c, "dist", 1.0, 9)[0][0].tolist() == [1]
    assert P.prune_lists(two, c, "dist", 1.2, 9)[0][0].tolist() == [1, 2]
    dup = np.array([[0.0, 0.0], [0.0, 0.0], [1.0, 0.0]])
    assert P.prune_lists(dup, [np.array([1, 2])], "dist", 1.0, 9)[0][0].tolist() == [1]


def test_detour_example_and_work():
    # list of node 0: 1 2 3 4 5; node 3 holds 5 in place 4, before rank 5, and 4 in place 3, before rank 4: a forward detour of each
    to = np.full((6, 5), -1)
    to[0] = [1, 2, 3, 4, 5]
    to[3] = [1, 2, 4, 5, 0]
    c = P.detours(to)
    assert c[0].tolist() == [0, 0, 0, 1, 1]
    assert P.work(5, "paired") == [5, 5] and P.work(6, "paired") == [6, 6, 3]
    assert P.work(5, "per_candidate") == [0, 1, 2, 3, 4]
    for k in range(2, 40):
        assert sum(P.work(k, "paired")) == sum(P.work(k, "per_candidate"))


def test_beam_with_full_pool_is_exact(x):
    g = [r for r in D.exact_lists(x, 16).to]
    e = S.entry_point(x)
    truth = D.exact_lists(x, 5).to
    for i in range(0, 300, 37):
        got, _, _, _ = S.beam(x, g, x[i], 6, len(x), [e])
        assert set(got.tolist()) == {i, *truth[i].tolist()}


def brute_dispatch(w, c, n):
    """Every choice tried afresh at each step."""
    order, res, left = [(0, None)], [0], set(range(1, c))
    gain = lambda x: sum(w.get(x, {}).get(r, 0) for r in res)
    while left:
        if len(res) < n:
            x = min(left, key=lambda x: (-gain(x), x))
            order.append((x, None))
        else:
            _, x, e = min((-(gain(x) - w.get(x, {}).get(e, 0)), x, e) for x in left for e in res)
            order.append((x, e))
            res.remove(e)
        res.append(x)
        left.discard(x)
    return order


def test_dispatch_against_brute_force():
    r = random.Random(3)
    for _ in range(30):
        c, n = r.randint(2, 12), r.randint(1, 5)
        w = {}
        for a in range(c):
            for b in range(a):
                if r.random() < 0.6:
                    w.setdefault(a, {})[b] = w.setdefault(b, {})[a] = r.randint(1, 9)
        assert dp.overlap_dispatch(w, c, n) == brute_dispatch(w, c, n)


def test_dispatch_worked_example():
    """Own weights for cache 3 of six clusters: loads 0, 2, 3, then 5 in place of 0."""
    w = {}
    for a, b, k in ((0, 2, 9), (0, 3, 5), (2, 3, 6), (3, 5, 8), (2, 5, 7), (1, 4, 2), (0, 1, 1)):
        w.setdefault(a, {})[b] = w.setdefault(b, {})[a] = k
    assert dp.overlap_dispatch(w, 6, 3)[:4] == [(0, None), (2, None), (3, None), (5, 0)]


def test_orders_are_permutations():
    w = {0: {1: 3}, 1: {0: 3, 2: 1}, 2: {1: 1}}
    for o in (dp.order_sequential(5, 2), dp.order_random(5, 2), dp.order_locality_window(w, 5, 2), dp.overlap_dispatch(w, 5, 2)):
        assert sorted(a for a, _ in o) == list(range(5))
        res = []
        for a, e in o:
            if e is not None:
                assert e in res
                res.remove(e)
            res.append(a)
            assert len(res) <= 2


@pytest.mark.parametrize("f", [lambda x: B.incremental(x, 10, 24), lambda x: B.incremental(x, 10, 24, layers=True), lambda x: B.iterated_collect_prune(x, 16, 2), lambda x: B.relaxed_two_pass(x, 16, pool=20), lambda x: B.divide_conquer(x, 10, 60, 3), lambda x: B.build(x, "detour_rank", True, 16, 16)[0], lambda x: B.build(x, "occlusion_strict", False, 16)[0]])
def test_builders_search_well(x, f):
    g = f(x)
    truth = D.exact_lists(x, 5).to
    e = S.entry_point(x)
    hit = np.mean([len(set(S.beam(x, g, x[i], 6, 60, [e])[0].tolist()) & set(truth[i].tolist())) / 5 for i in range(0, 300, 10)])
    assert hit > 0.85


@pytest.mark.parametrize("n", [1, 2, 5])
def test_tiny_sets(n):
    from vgraph.prune.rules import RECIPES
    from vgraph.shard.build import resident_build

    y = np.arange(n, dtype=float)[:, None]
    for rule in RECIPES.values():
        g = resident_build(y, rule, 8, {"it1": 1, "it2": 1, "sample": 2})
        assert len(g) == n and all(v not in r for v, r in enumerate(g))


def test_original_prune_forms_agree_with_the_fast_ones():
    x = np.random.default_rng(8).normal(size=(70, 5))
    to = D.exact_lists(x, 16).to
    assert all(np.array_equal(a, b) for a, b in zip(P.detour_prune_rows(to, 8), P.detour_prune(to, 8), strict=True))
    assert all(np.array_equal(a, b) for a, b in zip(P.dispersion_lists(x, list(to), 8, False), P.dispersion_lists(x, list(to), 8), strict=True))


def test_descent_ends_at_its_recall_target():
    x = np.random.default_rng(9).normal(size=(300, 8))
    truth, seen = D.exact_lists(x, 12).to, []
    stop = D.until_recall(x, 12, 0.9)

    def trace(it, g):
        seen.append(it)
        return stop(it, g)

    g = D.two_phase(x, 12, 10, 10, 6, trace=trace)
    assert len(seen) < 21 and D.recall(g.to, truth) > 0.85
    settled = D.two_phase(x, 12, 10, 6, 6, delta=0.5)  # shared rounds that settle at once still hand over to the fine ones
    assert settled.visited.any()


def test_every_set_and_variant_is_its_own_task(spark, sf):
    from vgraph import workloads as w

    def body(x, name, variant, truth):
        return [("r", variant, name, truth.shape[1], "rows", float(len(x)))]

    named = w.sets(spark, sf, (96,))
    got = w.in_tasks(spark, named, ["a", "b"], body, 5).collect()
    assert {(r.dataset, r.method) for r in got} == {(n, v) for n in named for v in "ab"} and all(r.k == 5 for r in got)


def test_two_phase_reaches_what_neither_shared_nor_single_rounds_reach(spark, sf):
    from vgraph.workloads import WORKLOADS

    r = {(x.method, x.dataset): x.value for x in WORKLOADS["w_phase_ablation"](spark, sf).where("metric = 'recall'").collect()}
    for ds in {d for _, d in r}:
        assert r["two_phase_long", ds] >= max(r["two_phase", ds], r["single", ds]) - 0.01 and r["single", ds] < r["two_phase", ds]


def test_descent_memory_grows_with_lists_not_with_compared_rows():
    import tracemalloc

    x = np.random.default_rng(5).normal(size=(3000, 64))
    tracemalloc.start()
    D.two_phase(x, 32, 1, 1, 8)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 200e6


def test_index_above_one_residents_rows_is_sharded_and_searched_whole(spark, sf, monkeypatch):
    from vgraph import queries as Q

    monkeypatch.setattr(Q, "RESIDENT", 200)
    v, g = Q._index(spark, sf)
    sizes = [r["count"] for r in v.groupBy("shard").count().collect()]
    assert len(sizes) == 3 and sum(sizes) == v.count() and g.select("src").distinct().count() == v.count()
    assert g.join(v.select(F.col("id").alias("dst"), F.col("shard").alias("other")), "dst").where("shard <> other").count() == 0
    monkeypatch.setattr(Q, "_index", lambda s, d: (v, g))
    for name in ("search_recall", "batch_search_recall", "filtered_index_recall"):
        assert Q.QUERIES[name](spark, sf).first().recall >= 0.9
    assert Q.search_io(spark, sf).count() == Q.data.query_set(v).count()


def test_path_candidates_search_side_by_side(monkeypatch):
    """What single searches visit, equal distances and repeated list entries included, without one search a row."""
    from vgraph.core.metric import sq_l2_rows

    r = np.random.default_rng(8)
    x = np.vstack([np.round(r.normal(size=(150, 6)), 1)] * 2)
    graph = [np.append(w, [w[0], -1]) for w in r.integers(0, 300, (300, 9))]
    ids = r.permutation(300)
    want = []
    for v in range(300):
        c = np.array([w for w in {*S.beam(x, graph, x[v], 1, 20, [3], ids=ids)[2], *graph[v].tolist()} if w not in (v, -1)])
        want.append(c[np.lexsort((ids[c], sq_l2_rows(x[c], x[v])))[:40]])
    monkeypatch.setattr(S, "beam", None)
    got = S.path_candidates(x, graph, 40, 20, 3, graph, ids=ids)
    assert all(np.array_equal(a, b) for a, b in zip(got, want, strict=True))


@pytest.mark.parametrize(("metric", "thres"), [("dist", 1.0), ("dist", 1.2), ("angle", 60.0)])
def test_serial_meets_the_kept_list_at_once(monkeypatch, metric, thres):
    from vgraph.core.metric import apex_angle_np, sq_l2_rows

    r = np.random.default_rng(9)
    calls = []
    monkeypatch.setattr(P, "sq_l2_rows", lambda a, b: calls.append(1) or sq_l2_rows(a, b))
    for _ in range(20):
        v = r.normal(size=(60, 8))
        dp = np.sort((v**2).sum(1))
        v = v[np.argsort((v**2).sum(1), kind="stable")]
        kept, tests = [], 0
        for j in range(60):
            for i in kept:
                tests += 1
                dij = ((v[i] - v[j]) ** 2).sum()
                if dp[j] >= thres * thres * dij if metric == "dist" else apex_angle_np(dp[i], dp[j], dij) <= thres:
                    break
            else:
                kept.append(j)
        calls.clear()
        assert P.serial(v, dp, metric, thres, 60) == (kept, tests) and len(calls) < 60
        assert P.wavefront(v, dp, metric, thres, 60)[0] == kept


@pytest.mark.parametrize("name", ["detour_rank", "angle_dispersion"])
@pytest.mark.parametrize("fast", [False, True])
def test_pruning_chooses_among_more_than_it_keeps(monkeypatch, name, fast):
    """The pruned lists of a build are not just what the descent gave: without the detour counts or angles they would be others."""
    x = np.random.default_rng(12).standard_normal((150, 8))
    seen, descent = [], D.two_phase
    monkeypatch.setattr(D, "two_phase", lambda *a, **kw: seen.append(descent(*a, **kw)) or seen[-1])
    got, _ = B.build(x, name, fast)
    nearest = [set(r[: len(g)].tolist()) for r, g in zip(seen[0].to, got, strict=True)]
    assert all(len(g) == 32 and set(g.tolist()) <= set(r.tolist()) for g, r in zip(got, seen[0].to, strict=True))
    assert sum(set(g.tolist()) != near for g, near in zip(got, nearest, strict=True)) > 100


def test_sharded_quality_has_whole_shards_at_every_size(spark, sf, monkeypatch):
    from vgraph import workloads as w

    monkeypatch.setattr(w, "SHARD_ROWS", 10, raising=False)  # the bound that it had
    monkeypatch.setattr(w, "MANY", 3)
    monkeypatch.setattr(w, "SOME", 2)
    built, build = [], w.sharded_build
    monkeypatch.setattr(w, "sharded_build", lambda v, *a, **kw: built.append(build(v.where("id < 200"), *a, **kw)) or built[-1])
    w.w_sharded_quality(spark, sf)
    assert [(len(b.centroids), b.assigned.select("shard").distinct().count()) for b in built] == [(3, 3), (2, 2)]
