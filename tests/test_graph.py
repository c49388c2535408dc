"""DataFrame forms against the resident kernels, and the library's surfaces."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from vgraph import build_index, compare
from vgraph.core.mix import mix, mix_np, mix_sql
from vgraph.core.types import as_vectors, densify, flat
from vgraph.exact import exact_search, exact_search_columns
from vgraph.init.start import random_graph
from vgraph.init.two_phase import shared_round
from vgraph.kernel import descent_np as D
from vgraph.measure.recall import curve_gap, recall


@pytest.fixture(scope="module")
def small(spark):
    x = np.random.default_rng(3).normal(size=(80, 6))
    return x, spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").cache()


def test_tiers_agree(small):
    from vgraph.init.refine import refine

    x, v = small
    g, n = random_graph(v, 8, 42, len(x)), D.random_lists(x, 8)

    def same(df, lists):
        got = {r.src: [(e.id) for e in r.nbrs] for r in df.collect()}
        assert got == {i: row[row >= 0].tolist() for i, row in enumerate(lists.to)}

    same(g, n)
    from vgraph.core.iterate import step

    for keep in ("tile", "one", "all"):
        h = step(shared_round(g, v, 8, 3, 1, 42, keep, 2))
        m, _ = D.shared_round(x, n, 3, 1, 42, keep, 2)
        same(h, m)
    h2 = step(refine(h, v, 2, 8))
    m2, _ = D.fine_round(x, m, 2)
    same(h2, m2)
    same(refine(h2, v, 2, 8), D.fine_round(x, m2, 2)[0])


def test_mix_is_portable(spark, duck):
    a = [r[0] for r in spark.range(50).select(mix(42, F.col("id"), F.col("id") * 7)).collect()]
    b = mix_np(42, np.arange(50), np.arange(50) * 7).tolist()
    c = [r[0] for r in duck.sql(f"select {mix_sql('42', 'i', 'i * 7')} from range(50) t(i) order by i").fetchall()]
    assert a == b == c


def test_validation(spark):
    ok = spark.createDataFrame([(1, [1.0, 2.0]), (2, [0.0, 1.0])], "id long, vec array<double>")
    assert as_vectors(ok).count() == 2
    for bad in ([(1, None), (2, [1.0])], [(1, [float("nan")]), (2, [1.0])], [(1, [1.0, 2.0]), (2, [1.0])], [(1, [1.0]), (1, [2.0])]):
        with pytest.raises(ValueError):
            as_vectors(spark.createDataFrame(bad, "id long, vec array<double>"))


def test_densify(spark):
    d = densify(spark.range(100).select((F.col("id") * 37 % 101).alias("k")).repartition(5), "k").orderBy("k").collect()
    assert [r.id for r in d] == list(range(100))


def test_exact_forms_agree(small):
    _, v = small
    q = v.where("id < 5").select(F.col("id").alias("qid"), "vec")
    a = exact_search(v, q, 4, True).orderBy("qid", "rank").select("qid", "id").collect()
    assert a == exact_search_columns(v, q, 4, True).orderBy("qid", "rank").select("qid", "id").collect()


def test_plans(small, spark, sf):
    from vgraph.prune.rank import detours

    _, v = small
    plan = exact_search_columns(v, v.select(F.col("id").alias("qid"), "vec"), 3)._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in plan
    e = spark.read.parquet(f"{sf}/embeddings.parquet").select(F.col("vec_id").alias("src"), F.col("label").cast("long").alias("dst"), F.lit(1).alias("rank"))
    assert "embedding:" not in detours(e)._jdf.queryExecution().executedPlan().toString()


def test_index_round_trip(small, spark, tmp_path):
    from vgraph import Index

    _, v = small
    q = v.where("id % 10 = 0").select(F.col("id").alias("qid"), "vec")
    truth = exact_search(v, q, 5)
    for memory in (None, 9000):
        index = build_index(v, "occlusion_relaxed", 16, 12, memory, init={"method": "exact"})
        assert index.meta["mode"] == ("memory" if memory is None else "sharded")
        assert recall(truth, index.search(q, 5, 40, probe=50), 5).first().recall >= 0.9
    index.save(str(tmp_path / "ix"))
    back = Index.load(spark, str(tmp_path / "ix"), v)
    assert back.edges.count() == index.edges.count() and back.meta["recipe"] == "occlusion_relaxed"


def test_one_shard_is_the_memory_build(small):
    from vgraph.prune.rules import RECIPES
    from vgraph.shard.pipeline import sharded_build

    _, v = small
    rule = RECIPES["detour_rank"].but(degree=6)
    a = build_index(v, rule, 10, init={"method": "exact"}).edges
    b = sharded_build(v, rule, 1, 1, 1, 10, {"method": "exact"}, rounds=1).edges
    assert {(r.src, r.dst) for r in a.collect()} == {(r.src, r.dst) for r in b.collect()}


def test_compare_and_columns_search(small):
    from vgraph.prune.store import entry_point
    from vgraph.search.beam import beam_columns

    _, v = small
    q = v.where("id in (3, 40)").select(F.col("id").alias("qid"), "vec")
    m = compare(v, q, ["detour_rank"], 4, (80,), 16).collect()
    assert any(r.metric == "recall_pool_80" and r.value >= 0.9 for r in m)
    g = build_index(v, "detour_rank", 16).edges
    got = beam_columns(v, g, q, 4, 12, entry_point(v))
    assert recall(exact_search(v, q, 4), got, 4).first().recall >= 0.75


def test_curve_gap(spark):
    a = spark.createDataFrame([(10.0, 0.9), (20.0, 0.8)], "qps double, recall double")
    b = spark.createDataFrame([(5.0, 1.0), (15.0, 0.9), (25.0, 0.7)], "qps double, recall double")
    r = {x.qps: round(x.recall_b, 6) for x in curve_gap(a, b).collect()}
    assert r == {10.0: 0.95, 20.0: 0.8}


def test_split_build_is_searched(small):
    from vgraph.search.beam import merged_search
    from vgraph.shard.assign import shard_sizes
    from vgraph.shard.pipeline import sharded_build

    x, v = small
    b = sharded_build(v, "occlusion_relaxed", 2, 2, 2, 16, {"method": "exact"}, rounds=2, limit=30)
    sizes = {r.shard: r.n for r in shard_sizes(b.assigned).collect()}
    assert sum(sizes.values()) == 2 * len(x) and max(sizes.values()) <= 30 and sorted(sizes) == list(range(len(b.centroids)))
    q = v.where("id % 4 = 0").withColumnRenamed("id", "qid")
    found = merged_search(v, b.edges, b.assigned, b.centroids, q, 5, probe=len(sizes) - 1, pool=30)
    assert recall(exact_search(v, q, 5), found, 5).first().recall >= 0.9


def test_split_oversize_and_repair(small):
    from vgraph.core.iterate import step
    from vgraph.prune.store import entry_point, reached, repair
    from vgraph.shard.assign import assign_overlap, shard_sizes, split_oversize
    from vgraph.shard.kmeans import kmeans

    x, v = small
    a = assign_overlap(v, kmeans(v, 2, 2), 1)
    s = shard_sizes(split_oversize(v, a, 30)).collect()
    assert sum(r.n for r in s) == len(x) and max(r.n for r in s) <= 30
    full = step(flat(random_graph(v, 20, 1, len(x))))
    thin = step(full.where("rank = 1"))
    e = entry_point(v)
    assert reached(repair(thin, v, e, full), e).count() == len(x)


def test_vecs_source_and_sql(spark, tmp_path):
    from vgraph.io.vecs_source import VecsSource, write_vecs
    from vgraph.sql.functions import register

    x = np.random.default_rng(0).normal(size=(7, 3)).astype("float32")
    write_vecs(x, str(tmp_path / "a.fvecs"))
    spark.dataSource.register(VecsSource)
    got = spark.read.format("vecs").option("rows", "3").load(str(tmp_path / "a.fvecs")).orderBy("id").collect()
    assert np.allclose([r.vec for r in got], x)
    register(spark)
    assert spark.sql("select l2(array(0D, 0D), array(3D, 4D)) as d").first().d == 5.0
    assert spark.sql("select mix(array(42L, 7L)) as m").first().m == int(mix_np(42, 7))
    assert spark.sql("""select count(*) as n from dispatch_steps('{"edges": [[0, 1, 2]], "clusters": 3, "cache": 2}')""").first().n == 3


def test_streams(spark, sf, tmp_path):
    import datetime as dt

    from vgraph.stream import changes as ch

    t0 = dt.datetime(2024, 1, 1)
    rows = [(i, t0 + dt.timedelta(minutes=20 * i), i % 3, ["view", "purchase", "error"][i % 3], float(i)) for i in range(30)]
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double"
    spark.createDataFrame(rows + rows[:3], schema).coalesce(1).write.parquet(str(tmp_path / "e"))

    def run(df, mode, name):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination(120)
        return spark.table(name).collect()

    s = spark.readStream.schema(schema).parquet(str(tmp_path / "e"))
    churn = run(ch.churn(ch.changes(s), 1, "1 hour"), "complete", "churn")
    assert sum(r.n for r in churn) == 30  # repeated ids count once
    pairs = run(ch.follow_ups(s, "30 minutes"), "append", "pairs")
    assert all(r.purchase_id == r.view_id + 1 for r in pairs)
    built = []
    q = ch.rebuild_on(ch.changes(s), {0: 3}, 0.5, built.append, 1).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert built == [0]


def test_cache_merge_follows_any_order(spark, sf):
    """Merged through the cache by each order, the graph is that of all lists united, and input and output are as replayed."""
    from vgraph.shard import dispatch as dp
    from vgraph.shard import replay as rp
    from vgraph.shard.cache_merge import CacheMerge

    r = random.Random(3)
    held = [(s, i, k + 1, 0.0) for i in range(40) for k, s in enumerate(r.sample(range(9), 3))]
    a = spark.createDataFrame(held, "shard int, id long, choice int, d2 double")
    lists = [(s, i, j, float(r.randrange(1000))) for s, i, _, _ in held for j in r.sample([x for x in range(40) if x != i], 4)]
    nearest = {}
    for _, i, j, x in lists:
        nearest[i, j] = min(x, nearest.get((i, j), 1e9))
    want = {i: sorted((x, j) for (s, j), x in nearest.items() if s == i)[:5] for i in range(40)}
    local = spark.createDataFrame(lists, "shard int, src long, dst long, d2 double")
    for n, order in ((3, dp.order_random(9, 3)), (2, dp.order_sequential(9, 2))):
        o = dp.as_table(spark, order)
        flow = CacheMerge.start(a, o, n, 5)
        for w in range((9 + n - 1) // n):
            loads = [x for x, _ in order[w * n : (w + 1) * n]]
            flow.wave(w, local.where(F.col("shard").isin(loads)))
        got = {}
        for x in flow.edges(spark).orderBy("src", "rank").collect():
            got.setdefault(x.src, []).append((x.d2, x.dst))
        assert got == want
        log = rp.replay_cache(a, o).groupBy("outcome").count().collect()
        seen = {x.outcome: x["count"] for x in log}
        assert (flow.reads, flow.writes) == (seen.get("miss", 0), seen["first"] + seen.get("miss", 0))


def test_oversize_shards_are_split_together(spark):
    from vgraph.shard.assign import assign_overlap, shard_sizes, split_oversize
    from vgraph.shard.pipeline import sharded_build

    r = np.random.default_rng(2)
    x = np.concatenate([r.normal(0, 0.1, (300, 4)), r.normal(5, 0.1, (30, 4))])
    v = spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(x)], "id long, vec array<double>")
    a = assign_overlap(v, np.array([[0.0] * 4, [5.0] * 4]), 1)
    cut = split_oversize(v, a, 80)
    sizes = {row.shard: row.n for row in shard_sizes(cut).collect()}
    assert max(sizes.values()) <= 80 and sum(sizes.values()) == 330 and cut.select("id").distinct().count() == 330
    b = sharded_build(v, "detour_rank", 2, 1, 2, 8, {"method": "exact"}, rounds=2, limit=100)
    assert b.edges.select("src").distinct().count() == 330 and b.writes == 330 + b.reads


def test_filtered_index_search_meets_the_exact_answer(spark, small):
    from vgraph.exact import filtered_search
    from vgraph.search.beam import filtered_index_search

    x, v = small
    index = build_index(v, "detour_rank", k=12, degree=10, init={"method": "exact"})
    lab = v.withColumn("label", (F.col("id") % 5).cast("int"))
    q = v.where("id % 9 = 0").select(F.col("id").alias("qid"), "vec")
    got = filtered_index_search(lab, index.edges, q, 4, "label = 2", pool=40)
    assert got.join(lab, "id").where("label <> 2").count() == 0
    assert recall(filtered_search(lab, q, 4, "label = 2"), got, 4).first().recall > 0.9
    assert filtered_index_search(lab, index.edges, q, 4, "label = 99").count() == 0


def test_sql_table_functions_over_graphs(spark, small):
    from vgraph.sql.functions import register, register_search

    x, v = small
    register(spark)
    v.createOrReplaceTempView("small_v")
    g = spark.sql("select * from knn_graph(table(select id, vec from small_v) with single partition, 3)").collect()
    want = {(r.src, r.rank): r.dst for r in exact_search(v, v.select(F.col("id").alias("qid"), "vec"), 3, True).withColumnRenamed("qid", "src").withColumnRenamed("id", "dst").collect()}
    assert {(r.src, r.rank): r.dst for r in g} == want
    d = spark.sql("select v_sq_l2(a.vec, b.vec) as d from small_v a join small_v b on a.id = 0 and b.id = 1").first().d
    assert abs(d - ((x[0] - x[1]) ** 2).sum()) < 1e-9
    register_search(spark, build_index(v, "detour_rank", k=12, degree=10, init={"method": "exact"}), "search_small")
    near = spark.sql("select q.id as q, s.id, s.rank from small_v q, lateral search_small(q.vec, 1) s where q.id < 20").collect()
    assert len(near) == 20 and sum(r.q == r.id for r in near) >= 19
