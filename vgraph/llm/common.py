"""Shared pieces of the text operators: scratch tables, word hashing and Arrow row passes.

Executors may be lost at any time, so intermediate tables are written as Parquet under the
folder that ``spark.checkpoint.dir`` names (shared by driver and executors) and read back.
Only on a local master without that setting, as in tests, a temporary folder is made.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vgraph.core.ship import ship

#: A word is a run of anything but space, tab, line feed, vertical tab, form feed, carriage return.
WORD = re.compile(r"[^\x20\x09-\x0D]+")
#: Rows of an Arrow batch between the JVM and Python.
BATCH = "2500"
#: Documents per slice inside an Arrow batch: bounds the Python objects alive at once.
SLICE = 256
_M = np.uint64(0xFFFFFFFFFFFFFFFF)


def scratch(spark: SparkSession) -> str:
    """A fresh folder under the shared checkpoint folder."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = getattr(spark, "_vgraph_scratch", None)
        if base is None:
            base = spark._vgraph_scratch = tempfile.mkdtemp(prefix="vgraph-")
            import shutil

            atexit.register(shutil.rmtree, base, True)
    return f"{base.rstrip('/')}/vgraph-{uuid.uuid4().hex}"


#: Tables that the operators running now have written, one list for each ``cleared`` block.
_OPEN: list[list[DataFrame]] = []


def stored(df: DataFrame, **options) -> DataFrame:
    """Write ``df`` once and read it back: cuts lineage and survives lost executors."""
    path = scratch(df.sparkSession)
    df.write.options(compression="zstd", **options).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._vgraph_path = path
    if _OPEN:
        _OPEN[-1].append(out)
    return out


def unstore(df: DataFrame) -> None:
    """Delete a table made by ``stored`` that no later plan reads."""
    path = getattr(df, "_vgraph_path", None)
    if path:
        jvm = df.sparkSession._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(where, True)


def cleared(operator: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """An operator whose result is written, after which the tables that it wrote on its way are deleted."""

    @wraps(operator)
    def run(*args, **settings) -> DataFrame:
        _OPEN.append([])
        try:
            out = stored(operator(*args, **settings))
            _OPEN[-1] = [x for x in _OPEN[-1] if x is not out]
        finally:
            for x in _OPEN.pop():
                unstore(x)
        if _OPEN:
            _OPEN[-1].append(out)
        return out

    return run


def is_empty(df: DataFrame) -> bool:
    return not df.take(1)


def texts(docs: DataFrame) -> DataFrame:
    """The two columns the operators read: doc_id long, text (null becomes empty)."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))


def unused(names, *wanted: str) -> list[str]:
    """Column names like ``wanted`` that no column of ``names`` has, in any case of letters."""
    taken, out = {n.lower() for n in names}, []
    for w in wanted:
        while w.lower() in taken:
            w += "_"
        taken.add(w.lower())
        out.append(w)
    return out


def release() -> None:
    """Give freed memory back to the system: idle Python workers stay alive beside other stages' tasks."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only where the C library has it
        ctypes.CDLL(None).malloc_trim(0)


def light(spark: SparkSession) -> None:
    """Arrow batches of whole texts hold fewer rows than the default, unless the session has its own setting."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if spark.conf.get(key) == "10000":
        spark.conf.set(key, BATCH)
    ship(spark)


def rows_of(batch: pa.RecordBatch, size: int = SLICE) -> Iterator[dict[str, list]]:
    for at in range(0, batch.num_rows, size):
        part = batch.slice(at, size)
        yield {n: c.to_pylist() for n, c in zip(part.schema.names, part.columns, strict=True)}


def map_rows(df: DataFrame, fn: Callable[[], Callable[[dict[str, list]], dict[str, list]]], schema: T.StructType, size: int = SLICE) -> DataFrame:
    """``fn()`` is called once a task and gives a function from columns (lists) to columns (lists or arrays)."""
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(schema)

    def run(batches):
        each = fn()
        for b in batches:
            for cols in rows_of(b, size):
                out = each(cols)
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)
        del each
        release()

    light(df.sparkSession)
    return df.mapInArrow(run, schema)


def slices(batches, name: str, most: int) -> Iterator[pa.RecordBatch]:
    """The batches cut so that a slice's column ``name`` (strings) holds about ``most`` bytes, one row at least."""
    for b in batches:
        if not b.num_rows:
            continue
        size = pc.binary_length(b.column(b.schema.get_field_index(name))).fill_null(0).to_numpy(zero_copy_only=False)
        part = np.cumsum(size, dtype=np.int64) // most
        at = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), b.num_rows]
        for s, e in zip(at, at[1:], strict=False):
            yield b.slice(s, e - s)


class Recent:
    """A memo of two generations: when the young one holds ``most`` entries it becomes the old one, whose entries come back as they are met."""

    def __init__(self, most: int, longest: int = 48):
        self.most, self.longest = most, longest
        self.young: dict = {}
        self.old: dict = {}
        self.long: list = []

    def turn(self) -> None:
        if len(self.young) > self.most:
            self.old, self.young = self.young, {}

    def absent(self, keys) -> list:
        """Those of ``keys`` that neither generation holds, for the caller to put into ``young``, which holds the others after this."""
        young, old = self.young, self.old
        out = [k for k in keys if k not in young]
        if old:
            known = {k: old[k] for k in out if k in old}
            young.update(known)
            out = [k for k in out if k not in known]
        self.long += [k for k in out if len(k) > self.longest]
        return out

    def forget(self) -> None:
        """Drop the long keys met since the last call: they seldom come again and would take most of the room."""
        for k in self.long:
            self.young.pop(k, None)
        self.long = []


class Memo(dict):
    """``make(key)`` remembered for keys of at most ``longest`` characters, in two generations of ``most`` entries each."""

    def __init__(self, make: Callable, most: int, longest: int = 48):
        super().__init__()
        self.make, self.most, self.longest, self.old = make, most, longest, {}

    def __missing__(self, key):
        out = self.old.get(key)
        if out is None:
            out = self.make(key)
        if self.most and len(key) <= self.longest:
            if len(self) >= self.most:
                self.old = dict(self)
                self.clear()
            self[key] = out
        return out


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit values (multiply and xor-shift rounds)."""
    x = np.asarray(x, np.uint64)
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def keyed(x: np.ndarray, salt) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix64(np.asarray(x, np.uint64) + np.uint64(0x9E3779B97F4A7C15) * np.asarray(salt, np.uint64) + np.uint64(1))


#: Bytes of words that are hashed at once (a longer word alone), and the random word of each byte value.
HASH_BYTES = 1 << 20
_BYTE = mix64(np.arange(256, dtype=np.uint64) + np.uint64(0xA5A5))
_STEP = np.uint64(0x9E3779B97F4A7C15)


def _powers(n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(max(n, 1) - 1, _STEP)]))


def word_hashes(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hashes of all words (WORD) of all texts, where each text's begin and the end of the last). Null texts have none.

    Arrow splits the texts; a word's hash is a polynomial over random words of its bytes, so no word becomes a Python string."""
    split = pc.ascii_split_whitespace(text.fill_null("") if text.null_count else text)
    flat, bounds = split.flatten(), split.offsets.to_numpy()
    bounds = (bounds - bounds[0]).astype(np.int64)
    if not len(flat):
        return np.zeros(0, np.uint64), bounds
    _, places, raw = flat.buffers()
    at = np.frombuffer(places, np.int32)[flat.offset : flat.offset + len(flat) + 1].astype(np.int64)
    raw = np.frombuffer(raw, np.uint8) if raw is not None else np.zeros(0, np.uint8)
    size = np.diff(at)
    real = size > 0  # white space at an edge leaves empty words
    count = np.concatenate([np.zeros(1, np.int64), np.cumsum(real)])
    start, size = at[:-1][real], size[real]
    out = np.zeros(len(start), np.uint64)
    ends = np.cumsum(size)
    block = np.concatenate([np.zeros(1, np.int64), np.flatnonzero(np.diff(ends // HASH_BYTES)) + 1, np.array([len(start)])]) if len(start) else np.zeros(1, np.int64)
    with np.errstate(over="ignore"):
        for s, e in zip(block[:-1].tolist(), block[1:].tolist(), strict=True):
            if s == e:
                continue
            n = size[s:e]
            first = np.cumsum(n) - n
            inner = np.arange(int(n.sum())) - np.repeat(first, n)
            value = _BYTE[raw[np.repeat(start[s:e], n) + inner]] * _powers(int(n.max()))[inner]
            out[s:e] = mix64(np.add.reduceat(value, first) + n.astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D))
    return out, count[bounds]


def hashed_words(texts: list[str]) -> list[np.ndarray]:
    """The same as one array for each text."""
    h, at = word_hashes(pa.array(texts, pa.string()))
    return [h[s:e] for s, e in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]


def windows(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of k words; one hash of all words when there are fewer than k; none for none."""
    if len(h) == 0:
        return np.zeros(0, np.uint64)
    k = min(k, len(h))
    n = len(h) - k + 1
    with np.errstate(over="ignore"):
        out = np.full(n, k, np.uint64)
        for j in range(k):
            out = out * np.uint64(0x9FB21C651E98DF25) + h[j : j + n]
            out ^= out >> np.uint64(29)
    return mix64(out)


def unit(x: np.ndarray) -> np.ndarray:
    """Uniform in (0, 1) from 64-bit hashes."""
    return ((np.asarray(x, np.uint64) >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53


def held_out(mod: int, rest: int, id_col: str = "doc_id") -> Column:
    """True for rows whose crc32(id as text) leaves ``rest`` modulo ``mod``."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % mod == rest, F.lit(False))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


LONG, STR, DBL, BIN = T.LongType(), T.StringType(), T.DoubleType(), T.BinaryType()


def struct(**kinds) -> T.StructType:
    return T.StructType([T.StructField(n, t, True) for n, t in kinds.items()])
