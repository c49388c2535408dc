"""Exact answers by brute force: blocks of vectors against blocks of vectors, best k merged.

A block pair is a unit of work whatever the table's size; a task merges what its query blocks find before the shuffle."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .core.metric import sq_l2
from .core.ship import ship
from .core.types import DBL, INT, LONG, fields

BLOCK = 1024


def blocks(v: DataFrame, name: str, id_col: str = "id", block: int = BLOCK) -> DataFrame:
    """(name, ids, vecs): rows packed by ``block`` inside each partition; vecs is one flat array."""
    ship(v.sparkSession)
    out = T.StructType([T.StructField(name, LONG), T.StructField("ids", T.ArrayType(LONG)), T.StructField("vecs", T.ArrayType(DBL))])

    def pack(batches):
        from pyspark import TaskContext

        at, ids, vecs = TaskContext.get().partitionId() << 32, [], []
        for b in batches:
            ids += b.column(0).to_pylist()
            vecs.append(b.column(1).flatten().to_numpy(zero_copy_only=False))
            while len(ids) >= block:
                dim = sum(map(len, vecs)) // len(ids)
                flat = np.concatenate(vecs)
                yield pa.RecordBatch.from_arrays([pa.array([at]), pa.array([ids[:block]], pa.list_(pa.int64())), pa.array([flat[: block * dim]], pa.list_(pa.float64()))], names=[name, "ids", "vecs"])
                at, ids, vecs = at + 1, ids[block:], [flat[block * dim :]]
        if ids:
            yield pa.RecordBatch.from_arrays([pa.array([at]), pa.array([ids], pa.list_(pa.int64())), pa.array([np.concatenate(vecs)], pa.list_(pa.float64()))], names=[name, "ids", "vecs"])

    return v.select(F.col(id_col).cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec")).mapInArrow(pack, out)


def _topk(qx: np.ndarray, x: np.ndarray, ids: np.ndarray, k: int, own: np.ndarray | None):
    """Row, id and squared distance of the k best of each query row; the product selects, differences report."""
    d = (qx**2).sum(1)[:, None] + (x**2).sum(1)[None, :] - 2 * qx @ x.T
    if own is not None:
        d[own[:, None] == ids[None, :]] = np.inf
    near = np.argpartition(d, min(k + 8, d.shape[1]) - 1, 1)[:, : k + 8] if d.shape[1] > k + 8 else np.tile(np.arange(d.shape[1]), (len(qx), 1))
    real = ((qx[:, None, :] - x[near]) ** 2).sum(-1)
    if own is not None:
        real[own[:, None] == ids[near]] = np.inf
    order = np.lexsort((ids[near], real), axis=1)[:, :k]
    rows = np.repeat(np.arange(len(qx)), order.shape[1])
    sel = np.take_along_axis(near, order, 1).ravel()
    dd = np.take_along_axis(real, order, 1).ravel()
    ok = np.isfinite(dd)
    return rows[ok], ids[sel][ok], dd[ok]


def exact_search(v: DataFrame, q: DataFrame, k: int, exclude_self: bool = False, block: int = BLOCK) -> DataFrame:
    """(qid, id, rank, d2): the k nearest of ``v`` for every row of the query set (qid, vec), ties by id."""
    qb = blocks(q.select(F.col("qid").alias("id"), "vec"), "qb", block=block).select("qb", F.col("ids").alias("qids"), F.col("vecs").alias("qvecs"))
    pairs = qb.crossJoin(blocks(v, "vb", block=block))  # block rows: n / block of them a side

    out = fields(qid=LONG, id=LONG, d2=DBL)

    def each(batches):
        best: dict[int, tuple] = {}  # of the query blocks of this task: their k best so far, over all vector blocks that meet them here
        for b in batches:
            for r in range(b.num_rows):
                key = b.column(0)[r].as_py()
                qids, ids = (np.asarray(b.column(i)[r].as_py(), np.int64) for i in (1, 4))
                qx, x = (np.asarray(b.column(i)[r].values.to_numpy(zero_copy_only=False)).reshape(len(n), -1) for i, n in ((2, qids), (5, ids)))
                rows, got, d = _topk(qx, x, ids, k, qids if exclude_self else None)
                at = np.arange(len(rows)) - np.searchsorted(rows, rows)
                near, far = np.full((len(qids), k), np.iinfo(np.int64).max), np.full((len(qids), k), np.inf)
                near[rows, at], far[rows, at] = got, d
                if key in best:
                    near, far = np.hstack([best[key][1], near]), np.hstack([best[key][2], far])
                    order = np.lexsort((near, far), axis=1)[:, :k]
                    near, far = np.take_along_axis(near, order, 1), np.take_along_axis(far, order, 1)
                best[key] = qids, near, far
        for qids, near, far in best.values():
            i, j = np.nonzero(np.isfinite(far))
            yield pa.RecordBatch.from_arrays([pa.array(qids[i]), pa.array(near[i, j]), pa.array(far[i, j])], names=["qid", "id", "d2"])

    near = pairs.mapInArrow(each, out)
    w = Window.partitionBy("qid").orderBy("d2", "id")
    return near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "id", F.col("rank").cast(INT).alias("rank"), "d2")


def exact_knn_graph(v: DataFrame, k: int, block: int = BLOCK) -> DataFrame:
    """(src, dst, rank, d2): every node's k nearest others. The ground truth and the brute-force baseline: n^2 distances."""
    q = v.select(F.col("id").alias("qid"), "vec")
    return exact_search(v, q, k, True, block).select(F.col("qid").alias("src"), F.col("id").alias("dst"), "rank", "d2")


def exact_search_columns(v: DataFrame, q: DataFrame, k: int, exclude_self: bool = False) -> DataFrame:
    """The same in column functions alone, for small tables and plan study: top-k by a window that Spark turns into a group limit."""
    p = F.broadcast(q.select("qid", F.col("vec").alias("qv"))).crossJoin(v)
    if exclude_self:
        p = p.where("qid <> id")
    w = Window.partitionBy("qid").orderBy("d2", "id")
    return p.select("qid", "id", sq_l2(F.col("qv"), F.col("vec")).alias("d2")).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "id", "rank", "d2")


def filtered_search(v: DataFrame, q: DataFrame, k: int, where) -> DataFrame:
    """Search among the rows of ``v`` that a predicate on its other columns lets through; the filter runs below the search."""
    return exact_search(v.where(where).select("id", "vec"), q, k)


def range_search(v: DataFrame, q: DataFrame, radius: float, block: int = BLOCK) -> DataFrame:
    """(qid, id, d2) of everything within the radius."""
    qb = blocks(q.select(F.col("qid").alias("id"), "vec"), "qb", block=block).select("qb", F.col("ids").alias("qids"), F.col("vecs").alias("qvecs"))
    pairs = qb.crossJoin(blocks(v, "vb", block=block))

    def each(batches):
        for b in batches:
            for r in range(b.num_rows):
                qids, ids = (np.asarray(b.column(i)[r].as_py(), np.int64) for i in (1, 4))
                qx, x = (np.asarray(b.column(i)[r].values.to_numpy(zero_copy_only=False)).reshape(len(n), -1) for i, n in ((2, qids), (5, ids)))
                d = (qx**2).sum(1)[:, None] + (x**2).sum(1)[None, :] - 2 * qx @ x.T
                i, j = np.nonzero(d <= radius * radius + 1e-9)
                real = ((qx[i] - x[j]) ** 2).sum(1)
                ok = real <= radius * radius
                yield pa.RecordBatch.from_arrays([pa.array(qids[i][ok]), pa.array(ids[j][ok]), pa.array(real[ok])], names=["qid", "id", "d2"])

    return pairs.mapInArrow(each, fields(qid=LONG, id=LONG, d2=DBL))
