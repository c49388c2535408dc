"""Orders in which clusters enter and leave a bounded cache. Driver work over cluster-graph edges only."""

from __future__ import annotations

import random
from collections import deque

from pyspark.sql import DataFrame, SparkSession

Order = list[tuple[int, int | None]]


def weights(graph: DataFrame) -> dict[int, dict[int, int]]:
    """Adjacency of the cluster graph: at most c^2 / 2 edges, c being a parameter of the build."""
    out: dict[int, dict[int, int]] = {}
    for r in graph.collect():
        out.setdefault(r.a, {})[r.b] = r.w
        out.setdefault(r.b, {})[r.a] = r.w
    return out


def overlap_dispatch(w: dict[int, dict[int, int]], c: int, n: int, first: int = 0) -> Order:
    """Greedy order for a cache of n clusters. While it fills, the cluster of greatest weight to the residents comes; then the pair
    (load, evict) that gains most: weight of the load to the residents less its weight to the evicted. Ties to the smaller load, then evict.

    ``gain`` keeps each cluster's summed weight to the residents and changes only along the edges of what enters or leaves."""
    gain = dict.fromkeys(range(c), 0)
    resident: list[int] = []
    left = set(range(c))
    order: Order = []

    def enter(x: int, out: int | None) -> None:
        order.append((x, out))
        left.discard(x)
        if out is not None:
            resident.remove(out)
            for y, k in w.get(out, {}).items():
                gain[y] -= k
        resident.append(x)
        for y, k in w.get(x, {}).items():
            gain[y] += k

    enter(first, None)
    while left:
        if len(resident) < n:
            enter(min(left, key=lambda x: (-gain[x], x)), None)
            continue
        best = None
        for x in left:
            near = w.get(x, {})
            low, e = min((near.get(e, 0), e) for e in resident)
            key = (-(gain[x] - low), x, e)
            if best is None or key < best:
                best = key
        enter(best[1], best[2])
    return order


def with_fifo(loads: list[int], n: int) -> Order:
    """Evictions oldest first, for orders that do not choose them."""
    q: deque[int] = deque()
    out: Order = []
    for x in loads:
        gone = q.popleft() if len(q) == n else None
        q.append(x)
        out.append((x, gone))
    return out


def order_sequential(c: int, n: int) -> Order:
    return with_fifo(list(range(c)), n)


def order_random(c: int, n: int, seed: int = 42) -> Order:
    loads = list(range(c))
    random.Random(seed).shuffle(loads)
    return with_fifo(loads, n)


def order_locality_window(w: dict[int, dict[int, int]], c: int, n: int, window: int | None = None, weighted: bool = False) -> Order:
    """Next comes the cluster with most adjacency plus common neighbours within the last ``window`` placed; weights only on request."""
    window = window or n
    loads, left = [0], set(range(1, c))
    nbr = {x: set(w.get(x, {})) for x in range(c)}

    def score(x: int, y: int) -> float:
        tie = w.get(x, {}).get(y, 0)
        return (tie if weighted else float(tie > 0)) + len(nbr[x] & nbr[y])

    while left:
        last = loads[-window:]
        x = min(left, key=lambda x: (-sum(score(x, y) for y in last), x))
        loads.append(x)
        left.remove(x)
    return with_fifo(loads, n)


def as_table(spark: SparkSession, order: Order) -> DataFrame:
    return spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(order)], "step int, load int, evict int")
