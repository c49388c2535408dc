"""The builders as a user calls them."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .core.iterate import step
from .core.types import flat
from .exact import exact_knn_graph
from .init.two_phase import descent_full, descent_single, two_phase_descent
from .measure.graph import graph_stats
from .prune.pipeline import prune
from .prune.rules import RECIPES, Rule
from .search.beam import beam_search, merged_search
from .shard.assign import plan_shards
from .shard.build import build_local
from .shard.pipeline import sharded_build


@dataclass
class Index:
    """Vectors and pruned edges; a sharded index also routes by centroids."""

    vectors: DataFrame
    edges: DataFrame
    meta: dict = field(default_factory=dict)
    assigned: DataFrame | None = None
    centroids: object = None

    def search(self, q: DataFrame, k: int, pool: int = 64, probe: int = 2) -> DataFrame:
        if self.assigned is None:
            return beam_search(self.vectors, self.edges, q, k, pool)
        return merged_search(self.vectors, self.edges, self.assigned, self.centroids, q, k, probe, pool)

    def stats(self) -> DataFrame:
        return graph_stats(self.edges, self.vectors)

    def save(self, path: str) -> None:
        """Edges as Parquet sorted by node inside files, and one row of settings beside them; the settings are written last."""
        self.edges.repartitionByRange("src").sortWithinPartitions("src", "rank").write.mode("overwrite").parquet(f"{path}/edges")
        self.edges.sparkSession.createDataFrame([(json.dumps(self.meta),)], "meta string").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str, vectors: DataFrame) -> Index:
        return Index(vectors, spark.read.parquet(f"{path}/edges"), json.loads(spark.read.parquet(f"{path}/meta").first()[0]))


def knn_graph(v: DataFrame, k: int, method: str = "two_phase", **kw) -> DataFrame:
    """(src, dst, rank, d2) by 'two_phase', 'exact', 'full' or 'single'."""
    if method == "exact":
        return exact_knn_graph(v, k)
    kw = {"sample": 8} | kw
    if method == "two_phase":
        return flat(two_phase_descent(v, k, kw.pop("it1", 6), kw.pop("it2", 6), **kw))
    return flat({"full": descent_full, "single": descent_single}[method](v, k, kw.pop("it", 8), **kw))


def build_index(v: DataFrame, recipe: str | Rule = "occlusion_relaxed", k: int = 64, degree: int | None = None, memory: int | None = None, m: int = 2, cache: int = 4, init: dict | None = None) -> Index:
    """In memory of one worker when vectors and lists fit ``memory`` bytes (default 1 GB), else sharded."""
    rule = RECIPES[recipe] if isinstance(recipe, str) else recipe
    if degree:
        rule = rule.but(degree=degree)
    memory = memory or 1 << 30
    r = v.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("dim")).first()
    shards = plan_shards(r.n, r.dim or 1, memory, 1, k=k)
    meta = {"recipe": recipe if isinstance(recipe, str) else "own", "k": k, "degree": rule.degree, "n": r.n, "dim": r.dim}
    at = time.perf_counter()
    if shards <= 1:
        one = v.select(F.lit(0).alias("shard"), "id")
        edges = step(build_local(v, one, rule, k, init).drop("shard"))
        return Index(v, edges, meta | {"mode": "memory", "seconds": time.perf_counter() - at})
    b = sharded_build(v, rule, plan_shards(r.n, r.dim, memory, m, k=k), m, cache, k, init, limit=2_000_000)
    return Index(v, b.edges, meta | {"mode": "sharded", "clusters": len(b.centroids), "seconds": time.perf_counter() - at, **{f"{a}_s": s for a, s in b.seconds.items()}}, b.assigned, b.centroids)


def compare(v: DataFrame, q: DataFrame, recipes: list[str], k: int = 10, pools: tuple[int, ...] = (16, 64), init_k: int = 32) -> DataFrame:
    """(run, method, dataset, k, metric, value): build seconds, degree, and recall by pool of each recipe."""
    from .exact import exact_search
    from .measure.recall import recall
    from .measure.timing import SCHEMA

    truth = step(exact_search(v, q, k))
    rows = []
    for name in recipes:
        index = build_index(v, name, init_k)
        rows.append(("compare", name, "", k, "build_s", index.meta["seconds"]))
        rows.append(("compare", name, "", k, "mean_degree", index.stats().first().mean_deg))
        for p in pools:
            rows.append(("compare", name, "", k, f"recall_pool_{p}", recall(truth, index.search(q, k, p), k).first().recall))
    return v.sparkSession.createDataFrame(rows, SCHEMA)


__all__ = ["Index", "build_index", "compare", "knn_graph", "prune"]
