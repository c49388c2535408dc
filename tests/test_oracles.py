"""Every relational operator and the quicker method queries against their DuckDB twins."""

import pytest
from same import rows, twin

from vgraph.ops.relational import OPS
from vgraph.ops.twins import TWINS
from vgraph.oracles import ORACLES
from vgraph.queries import QUERIES

METHODS = [
    "metric_variants", "exact_knn", "exact_search_queries", "range_search_queries", "random_graph", "merge_rank", "sample_fresh_old", "local_join_tile", "refine_one_iter",
    "collect_2hop", "prune_strict", "prune_wavefront_eq", "prune_serial_eq", "prune_angle", "prune_dispersion", "prune_dispersion_kernel", "prune_custom", "store_filled", "detour_counts", "detour_work_paired",
    "assign_overlapping", "kmeans_step", "cluster_overlap_graph", "dispatch_greedy", "cache_replay_greedy", "io_operations", "merge_of_locals", "merge_of_locals_ordered", "cache_merge_graph", "cache_merge_io", "doc_vectors", "event_vectors",
]


@pytest.mark.parametrize("name", METHODS)
def test_method(spark, sf, duck, name):
    assert rows(QUERIES[name](spark, sf)) == twin(duck, ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(OPS) & set(TWINS)))
def test_operator(spark, sf, duck, name):
    assert rows(OPS[name](spark, sf)) == twin(duck, TWINS[name])


def test_every_twin_has_its_query():
    from vgraph.workloads import WORKLOADS

    assert set(ORACLES) <= set(QUERIES) | set(WORKLOADS)
    assert set(TWINS) <= set(OPS)


def test_sampling_workload_reads_the_embeddings(spark, sf, duck):
    from vgraph.workloads import WORKLOADS

    got = WORKLOADS["w_sampling_toy"](spark, sf)
    assert rows(got) == twin(duck, ORACLES["w_sampling_toy"])
    assert got.count() == 2 * 2 * 5  # anchors 0, 100, ... 400


def test_kernel_workload_reads_the_embeddings(spark, sf):
    from vgraph.kernel.prune_np import work
    from vgraph.workloads import WORKLOADS

    got = {(r.method, r.k, r.metric): r.value for r in WORKLOADS["w_kernel_compare"](spark, sf).collect()}
    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    for k in (8, 16, 32, 64):
        for kernel in ("per_candidate", "paired"):
            w = work(k, kernel)
            assert got[kernel, k, "units"] == n * len(w) and got[kernel, k, "max_scans"] == max(w)
            assert got[kernel, k, "mean_scans"] == pytest.approx(sum(w) / len(w), abs=1e-6)


def test_theta_join_compares_near_prices_only(spark, duck, tmp_path):
    """4,000 parts of one brand, 10 apart but for pairs on a cell's edges: the join gives near pairs, not all 8 million."""
    price = [10.0 * (i // 4) + (0.0, 0.4999, 0.5, 0.9998)[i % 4] for i in range(4000)]
    spark.createDataFrame([("b", i, x) for i, x in enumerate(price)], "p_brand string, p_partkey long, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    duck.sql(f"create or replace temp view near_part as select * from '{tmp_path}/part.parquet/*.parquet'")
    got = OPS["op_join_theta"](spark, str(tmp_path))
    assert rows(got) == twin(duck, TWINS["op_join_theta"].replace("part a join part b", "near_part a join near_part b"))
    assert "cell" in got._jdf.queryExecution().optimizedPlan().toString().split("Join Inner", 1)[1].splitlines()[0]


def test_other_builders_in_shards(spark, monkeypatch):
    """Above RESIDENT rows no builder takes the whole set in one task, and every row of the result is there."""
    from vgraph import queries, workloads
    from vgraph.baseline import run as br

    seen, run = [], br.run
    monkeypatch.setattr(queries, "RESIDENT", 200)
    monkeypatch.setattr(br, "run", lambda v, name, assigned=None, **kw: seen.append(assigned.select("shard").distinct().count()) or run(v, name, assigned, **kw))
    got = {(r.method, r.metric): r.value for r in workloads.WORKLOADS["w_other_builders"](spark, "/root/testdata/sf0.001").collect()}
    assert seen == [3] * 5 and len(got) == 10 and {m for m, _ in got} == set(workloads.BUILDERS)
    assert all(got[m, "recall"] >= 0.9 for m in ("incremental", "iterated", "relaxed_two_pass"))
