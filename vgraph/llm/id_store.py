"""Content-addressed store of token ids.

Every document's id stream (its ids and one end id) is cut into chunks where a rolling hash of the last
ids says so, so that shared passages give shared chunks wherever they stand. A chunk is stored
once, with the first document (in ascending doc_id order) that holds it; other documents name it
by digest in their recipe. Recipes and payloads lie in packs in doc_id order, each pack under the
Merkle root of its documents' roots.

File format: a Parquet table of packs. A pack's ``recipes`` are records of RECIPE (one a chunk) under
records of DOC (one a document); ``payload`` holds the pack's own chunks one after another as
little-endian unsigned integers of ``width`` bytes (2 while the vocabulary fits, else 4).
"""

from __future__ import annotations

import hashlib
import os
import re
import zlib
from functools import lru_cache
from itertools import chain
from struct import Struct

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from vgraph.core.ship import ship

from .common import BIN, LONG, Recent, light, map_rows, mix64, release, rows_of, scratch, slices, stored, struct, texts, unstore

END = 1
#: Words of these alone are split by PARTS; lower-casing and composition act on each of their characters by itself.
PLAIN = re.compile(r"[A-Za-zÀ-ÖØ-öø-ÿ0-9!-/:-@\[-`{-~]+")
#: The tokenizer's own split of a lower-case word (between ASCII white space, across which none of its rules look).
PARTS = re.compile(r"'(?:s|t|re|ve|m|ll|d)|[a-zß-öø-ÿ]+|[0-9]|[^a-zß-öø-ÿ0-9]+")
#: Byte-level letters: bytes that print stand for themselves, the others for the code points from 256 on.
BYTE_LETTERS = {b: 256 + n for n, b in enumerate(b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or 174 <= b))}
#: Text bytes that are encoded at once (a longer text alone).
SLICE_BYTES = 8 << 20
DOC = np.dtype([("doc", "<i8"), ("offset", "<i8"), ("ids", "<u4"), ("chunks", "<u4"), ("root", "V16")])
RECIPE = np.dtype([("digest", "V16"), ("ids", "<u4"), ("flag", "<u4")])
_DOC, _RECIPE = Struct("<qqII16s").pack, Struct("<16sII").pack
OWN, LENT, BORROWED = 0, 1, 2
PACK_IDS = 1 << 20


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordIds:
    """Ids of whole texts: Arrow splits a slice of texts into words and lists the distinct ones, of which the tokenizer gets
    only those that the memo lacks.

    Words of plain letters, digits and ASCII marks are split as the tokenizer's own rules do; their parts go to its byte-pair model
    together, where the last token of each part is known by the vocabulary's word-end mark. Any other word goes through
    the whole tokenizer. A vocabulary without a word-end mark encodes whole texts."""

    def __init__(self, path: str, most: int = 300_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.tok = Tokenizer.from_file(path)
        self.width = 2 if self.tok.get_vocab_size() <= 1 << 16 else 4
        self.kind = f"<u{self.width}"
        self.suffix = getattr(self.tok.model, "end_of_word_suffix", None)
        if self.suffix:
            self.model = Tokenizer(self.tok.model)
            self.model.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
            self.last = np.zeros(1 << 8 * self.width if self.width == 2 else self.tok.get_vocab_size(), bool)
            self.last[[i for t, i in self.tok.get_vocab().items() if t.endswith(self.suffix)]] = True
        self.memo = Recent(most)

    def _each(self, words: list[str]) -> list[bytes]:
        """Ids of every word, from one call over all of them with a space between; tokens' places in that text tell whose they are."""
        e = self.tok.encode(" ".join(words), add_special_tokens=False)
        w = self.width
        ids = np.array(e.ids, self.kind).tobytes()
        starts = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        at = np.fromiter(chain.from_iterable(e.offsets), np.int64, 2 * len(e.ids))[::2]
        cut = (np.searchsorted(at, starts) * w).tolist()
        return [ids[s:t] for s, t in zip([0, *cut], cut, strict=False)]

    def _parts(self, parts: list[str], spelt: list[str]) -> None:
        """Ids of lower-case parts into the memo: each ends with the first token that bears the word-end mark."""
        for i in range(0, len(parts), 1024):
            ids = np.array(self.model.encode(" ".join(spelt[i : i + 1024]), add_special_tokens=False).ids, self.kind)
            cut = ((np.flatnonzero(self.last[ids]) + 1) * self.width).tolist()
            raw = ids.tobytes()
            self.memo.young.update(zip(parts[i : i + 1024], [raw[s:t] for s, t in zip([0, *cut], cut, strict=False)], strict=True))

    def _learn(self, words: list[str]) -> None:
        """Ids of unseen words into the memo, by way of their parts, which are words too."""
        ready, mixed, other = [], [], []
        for x in words:
            if x.isalpha() and (x.isascii() or PLAIN.fullmatch(x)):
                y = x.lower()
                if y == x:
                    ready.append(x)
                else:
                    mixed.append((x, [y]))
            elif PLAIN.fullmatch(x) and "<|" not in x:
                mixed.append((x, PARTS.findall(x.lower())))
            else:
                other.append(x)
        more = {y for _, p in mixed for y in p}
        more.difference_update(ready)
        ready += self.memo.absent(more)
        ascii_ = [x for x in ready if x.isascii()]
        self._parts(ascii_, ascii_)
        if len(ascii_) < len(ready):
            rest = [x for x in ready if not x.isascii()]
            self._parts(rest, [x.encode().decode("latin-1").translate(BYTE_LETTERS) for x in rest])
        young = self.memo.young
        for x, p in mixed:
            young[x] = young[p[0]] if len(p) == 1 else b"".join([young[y] for y in p])
        for i in range(0, len(other), 4096):
            young.update(zip(other[i : i + 4096], self._each(other[i : i + 4096]), strict=True))

    def ids(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(all ids one text after another, where each text's begin and the end of the last)."""
        if not self.suffix:
            each = [np.array(e.ids, self.kind) for e in self.tok.encode_batch(texts.to_pylist(), add_special_tokens=False)]
            return np.concatenate([np.zeros(0, self.kind), *each]), np.cumsum([0, *map(len, each)])
        split = pc.ascii_split_whitespace(texts)
        coded = split.flatten().dictionary_encode()
        words = coded.dictionary.to_pylist()
        self.memo.turn()
        self._learn(self.memo.absent(words))
        found = list(map(self.memo.young.__getitem__, words))
        self.memo.forget()
        pool = np.frombuffer(b"".join(found), self.kind)
        size = np.fromiter(map(len, found), np.int32, len(found)) // self.width
        at = coded.indices.to_numpy()
        n = size[at]
        ends = np.concatenate([np.zeros(1, np.int32), np.cumsum(n, dtype=np.int32)])  # a slice's bytes bound its ids
        where = np.repeat((np.cumsum(size, dtype=np.int32) - size)[at] - ends[:-1], n)
        where += np.arange(int(ends[-1]), dtype=np.int32)
        bounds = split.offsets.to_numpy()
        return pool[where], ends[bounds - bounds[0]]

    def encode(self, batch: list[str]) -> list[bytes]:
        flat, at = self.ids(pa.array(batch, pa.string()))
        return [flat[s:e].tobytes() for s, e in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]


@lru_cache(2)
def word_ids(path: str) -> WordIds:
    return WordIds(path)


@lru_cache(1)
def _gear() -> np.ndarray:
    return mix64(np.arange(1 << 16, dtype=np.uint64) + np.uint64(77))


def marks(ids: np.ndarray, mean: int = 256, window: int = 8) -> np.ndarray:
    """Places after which the rolling hash of the last ``window`` ids has its low bits zero."""
    n = len(ids)
    g = _gear()[ids & 0xFFFF]
    h = np.zeros(n, np.uint64)
    with np.errstate(over="ignore"):
        for j in range(min(window, n)):
            h[j:] += g[: n - j] << np.uint64(7 * j)
    return np.flatnonzero((mix64(h) & np.uint64(mean - 1)) == 0) + 1


def cuts(n: int, marked: list[int], least: int = 64, most: int = 1024) -> list[int]:
    """Ends of the chunks of a stream of n ids: at marked places, at least ``least`` and at most ``most`` ids apart.

    ``least`` exceeds the hash's window, so what stands before a stream never moves its cuts."""
    ends, last = [], 0
    for e in marked:
        while e - last > most:
            last += most
            ends.append(last)
        if e - last >= least:
            ends.append(e)
            last = e
    while n - last > most:
        last += most
        ends.append(last)
    if last < n:
        ends.append(n)
    return ends


def merkle(leaves: list[bytes]) -> bytes:
    """Root of a binary hash tree; an odd node moves up as it is; a fixed root for no leaves."""
    level = list(leaves) or [b""]
    if len(level) == 1:
        return hashlib.blake2b(b"\1" + level[0], digest_size=16).digest()
    while len(level) > 1:
        up = [hashlib.blake2b(b"\2" + level[i] + level[i + 1], digest_size=16).digest() for i in range(0, len(level) - 1, 2)]
        level = up + level[len(level) // 2 * 2 :]
    return level[0]


def digest(payload: bytes) -> bytes:
    return hashlib.blake2b(b"\0" + payload, digest_size=16).digest()


STREAM = struct(doc_id=LONG, ids=BIN, width=T.IntegerType(), sizes=T.ArrayType(T.IntegerType()), digests=T.ArrayType(BIN))


def streams(docs: DataFrame, path: str, end: int = END, mean: int = 256) -> DataFrame:
    """(doc_id, ids, width, sizes, digests): each document's stream and its chunks."""
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = to_arrow_schema(STREAM)

    def run(batches):
        coder = word_ids(path)
        w = coder.width
        tail = np.array([end], coder.kind).tobytes()
        for part in slices(batches, "text", SLICE_BYTES):
            flat, at = coder.ids(part.column("text"))
            raw, marked = flat.tobytes(), marks(flat, mean)
            near = np.searchsorted(marked, at, "right")
            ids, sizes, digests = [], [], []
            for k, (s, e) in enumerate(zip(at[:-1].tolist(), at[1:].tolist(), strict=True)):
                b = raw[s * w : e * w] + tail
                cut = cuts(e - s + 1, (marked[near[k] : near[k + 1]] - s).tolist())
                ids.append(b)
                sizes.append([y - x for x, y in zip([0, *cut], cut, strict=False)])
                digests.append([digest(b[x * w : y * w]) for x, y in zip([0, *cut], cut, strict=False)])
            yield pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, f.type) for x, f in zip((part.column("doc_id"), ids, [w] * len(ids), sizes, digests), schema, strict=True)], schema=schema)
        release()

    light(docs.sparkSession)
    return texts(docs).mapInArrow(run, STREAM)


PACK = struct(part=T.IntegerType(), pack=T.IntegerType(), width=T.IntegerType(), docs=T.IntegerType(), ids=LONG, first_doc=LONG, last_doc=LONG, index=BIN, recipes=BIN, payload=BIN, root=BIN)


def _pack(batches):
    """Rows sorted by (doc_id, uid, kind): kind 0 rows tell which chunks are shared, kind 1 rows bring the stream."""
    from pyspark import TaskContext
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = to_arrow_schema(PACK)
    part, pack, offset = TaskContext.get().partitionId(), 0, 0
    index, recipes, payload, roots, ends, total, width, shared = [], [], [], [], [], 0, 2, {}

    def flush():
        nonlocal pack, index, recipes, payload, roots, ends, total
        row = {"part": part, "pack": pack, "width": width, "docs": len(index), "ids": total, "first_doc": ends[0], "last_doc": ends[-1], "index": b"".join(index), "recipes": b"".join(recipes), "payload": b"".join(payload), "root": merkle(roots)}
        pack += 1
        index, recipes, payload, roots, ends, total = [], [], [], [], [], 0
        return pa.RecordBatch.from_pylist([row], schema=schema)

    names = ("doc_id", "kind", "shared", "ids", "width", "sizes", "digests")
    for cols in chain.from_iterable(map(rows_of, batches)):
        for doc, kind, told, ids, width, sizes, digests in zip(*(cols[n] for n in names), strict=True):  # noqa: B007
            if kind == 0:
                shared = {s["seq"]: LENT if s["own"] else BORROWED for s in told}
                continue
            at = 0
            for k, (n, d) in enumerate(zip(sizes, digests, strict=True)):
                flag = shared.get(k, OWN) if shared else OWN
                recipes.append(_RECIPE(d, n, flag))
                if flag != BORROWED:
                    payload.append(ids[at * width : (at + n) * width])
                at += n
            roots.append(merkle(digests))
            index.append(_DOC(doc, offset, at, len(sizes), roots[-1]))
            ends.append(doc)
            offset += at
            total += at
            shared = {}
            if total >= PACK_IDS:
                yield flush()
                shared = {}
    if index:
        yield flush()


def write(docs: DataFrame, path: str, tokenizer: str | None = None, end: int = END, mean: int = 256) -> None:
    """Write the store of all rows of ``docs`` under ``path``.

    Null and empty texts are streams of the end id alone. Rows with a null doc_id are left out; rows that repeat an
    id are separate documents one after another. An empty table gives a store without packs."""
    spark = docs.sparkSession
    s = streams(docs.where("doc_id is not null"), tokenizer or tokenizer_path(), end, mean)
    s = stored(s.withColumn("uid", F.monotonically_increasing_id()))
    chunks = s.select("doc_id", "uid", F.posexplode("digests").alias("seq", "digest"))
    who = F.struct("doc_id", "uid", "seq")
    first = chunks.groupBy("digest").agg(F.min(who).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("digest", "first")
    told = chunks.join(first, "digest").groupBy("doc_id", "uid").agg(F.collect_list(F.struct("seq", (who == F.col("first")).alias("own"))).alias("shared"))
    names = ["doc_id", "uid", "kind", "shared", "ids", "width", "sizes", "digests"]
    nothing = {"ids": "binary", "width": "int", "sizes": "array<int>", "digests": "array<binary>"}
    a = stored(told).withColumn("kind", F.lit(0)).withColumns({k: F.lit(None).cast(v) for k, v in nothing.items()}).select(names)
    b = s.withColumn("kind", F.lit(1)).withColumn("shared", F.lit(None).cast("array<struct<seq: int, own: boolean>>")).select(names)
    laid = a.union(b).repartitionByRange("doc_id", "uid").sortWithinPartitions("doc_id", "uid", "kind")
    ship(spark)
    laid.mapInArrow(_pack, PACK).write.options(compression="zstd").parquet(path)
    unstore(s)


def verify(row: dict) -> list[tuple[tuple, list[tuple], list[bytes | None]]]:
    """A pack's documents as (index record, recipe records, payloads or None where borrowed); raises where a digest or root differs."""
    index, recipes, payload, w = np.frombuffer(row["index"], DOC), np.frombuffer(row["recipes"], RECIPE), row["payload"], row["width"]
    at, k, out, roots = 0, 0, [], []
    for d in index.tolist():
        own, mine = recipes[k : k + d[3]].tolist(), []
        for dig, n, flag in own:
            if flag == BORROWED:
                mine.append(None)
                continue
            mine.append(payload[at : at + n * w])
            at += n * w
            if digest(mine[-1]) != bytes(dig):
                raise ValueError("a chunk differs from its digest")
        root = merkle([bytes(x[0]) for x in own])
        if root != bytes(d[4]):
            raise ValueError("a document's root differs from its chunks")
        roots.append(root)
        out.append((d, own, mine))
        k += d[3]
    if merkle(roots) != row["root"]:
        raise ValueError("a pack's root differs from its documents")
    return out


def _summed(parts: list[bytes], w: int) -> tuple[int, int]:
    raw = np.frombuffer(b"".join(parts), f"<u{w}").astype("<u4")
    return len(raw), zlib.crc32(raw.tobytes())


FOUND = struct(part=T.IntegerType(), offset=LONG, doc_id=LONG, n_tokens=LONG, ids_crc32=LONG, width=T.IntegerType(), n_chunks=T.IntegerType(), seq=T.IntegerType(), digest=BIN, payload=BIN, ids=BIN)


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of every document, rebuilt from its recipe and verified against the manifest.

    One pass over the packs rebuilds the documents whose chunks all lie in their own pack; only chunks that others borrow, and the
    documents that borrow them, are shuffled. A chunk that very many documents borrow is joined by a plan that may split it (a
    sort-merge join of rows that each name one place)."""
    packs = spark.read.schema(PACK).parquet(path)
    ship(spark)

    def rebuild(cols):
        out = []  # in the order of FOUND
        for i in range(len(cols["part"])):
            row = {n: v[i] for n, v in cols.items()}
            docs, w, part = verify(row), row["width"], row["part"]
            here = {}
            for _, rs, ps in docs:
                for (d, _, flag), p in zip(rs, ps, strict=True):
                    if flag != BORROWED:
                        here[d] = p
                        if flag == LENT:
                            out.append((None, None, None, None, None, None, None, None, d, p, None))
            for (doc, offset, _, n_chunks, _), rs, ps in docs:
                if None in ps:
                    ps = [here.get(r[0]) if p is None else p for r, p in zip(rs, ps, strict=True)]
                if None in ps:
                    out += [(part, offset, doc, None, None, w, n_chunks, k, r[0], p, None) for k, (r, p) in enumerate(zip(rs, ps, strict=True))]
                else:
                    n, crc = _summed(ps, w)
                    out.append((part, offset, doc, n, crc, w, n_chunks, None, None, None, b"".join(ps) if with_ids else None))
        return dict(zip(FOUND.names, zip(*out, strict=True) if out else [()] * len(FOUND), strict=True))

    found = stored(map_rows(packs, lambda: rebuild, FOUND, size=4))
    whole = found.where("n_tokens is not null").select("part", "offset", "doc_id", "n_tokens", "ids_crc32", "ids")
    open_ = found.where("n_tokens is null and part is not null")
    lent = found.where("part is null").select("digest", F.col("payload").alias("lent"))
    wanted = open_.where("payload is null").select("part", "offset", "doc_id", "width", "n_chunks", "seq", "digest")
    got = wanted.join(lent, "digest", "left").select("part", "offset", "doc_id", "width", "n_chunks", "seq", F.col("lent").alias("payload"))
    mine = open_.where("payload is not null").select("part", "offset", "doc_id", "width", "n_chunks", "seq", "payload")
    joined = mine.union(got).groupBy("part", "offset", "doc_id", "width", "n_chunks").agg(F.array_sort(F.collect_list(F.struct("seq", "payload"))).alias("chunks"))

    def finish(cols):
        sums, ids = [], []
        for w, n, c in zip(cols["width"], cols["n_chunks"], cols["chunks"], strict=True):
            parts = [x["payload"] for x in c]
            if len(parts) != n or None in parts:
                raise ValueError("a borrowed chunk is missing")
            sums.append(_summed(parts, w))
            ids.append(b"".join(parts) if with_ids else None)
        return {"part": cols["part"], "offset": cols["offset"], "doc_id": cols["doc_id"], "n_tokens": [x[0] for x in sums], "ids_crc32": [x[1] for x in sums], "ids": ids}

    rest = map_rows(joined, lambda: finish, struct(part=T.IntegerType(), offset=LONG, doc_id=LONG, n_tokens=LONG, ids_crc32=LONG, ids=BIN))
    parts = packs.groupBy("part").agg(F.sum("ids").alias("n"))  # one row for each file: as many as the store has parts
    before = parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    out = whole.union(rest).join(before, "part")
    return out.select("doc_id", (F.col("before") + F.col("offset")).alias("start"), "n_tokens", "ids_crc32", *(["ids"] if with_ids else []))


def round_trip(docs: DataFrame, **settings) -> DataFrame:
    path = scratch(docs.sparkSession)
    write(docs, path, **settings)
    return read(docs.sparkSession, path)
