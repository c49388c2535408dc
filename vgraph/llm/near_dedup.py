"""Weighted near-duplicate detection with bag min-hash signatures.

Signatures: each (shingle, copy) cell of a document's multiset of five-word shingles carries a
Poisson process of points in time; every point belongs to one of the m components, and a
component's value is the identity of the earliest point. Cells are reached through dyadic
shells of the copy axis ([0,1), [1,2), [2,4), [4,8), ...): a shell's first arrival is drawn at
the shell's whole rate and split downwards (one half inherits it, the other waits on from there),
so a shingle that occurs w times costs O(log w) and only halves that arrive in time are
opened. Two documents agree in a component with probability equal to their weighted Jaccard
similarity.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import BIN, LONG, cleared, hashed_words, keyed, map_rows, mix64, stored, struct, texts, unit, windows
from .components import components

WORDS, SIMILARITY = 5, 0.8
#: 28 bands of 5 rows: a pair of similarity 0.8 shares a band with probability 0.99998.
BANDS, ROWS = 28, 5
#: Further heads of a bucket that members outside its first head's group are compared with.
HEADS = 3
#: Parts that a bucket's members are dealt into where they meet those heads.
PARTS = 16


def shells(keys: np.ndarray, weight: np.ndarray, doc: np.ndarray, limit: np.ndarray):
    """First arrivals (leaf key, time, document) of all unit cells below each weight that arrive within the limit."""
    out = []
    live = np.arange(len(keys))
    s = 0
    while len(live):
        width = 1 if s == 0 else 1 << (s - 1)
        low = 0 if s == 0 else width
        live = live[weight[live] > low]
        if not len(live):
            break
        k = keyed(keys[live], 2 * s + 3)
        t = -np.log(unit(keyed(k, 1))) / width
        d, w, lo = doc[live], weight[live], np.full(len(live), low)
        while True:
            ok = (t <= limit[d]) & (lo < w)
            k, t, d, w, lo = k[ok], t[ok], d[ok], w[ok], lo[ok]
            if width == 1 or not len(k):
                break
            width //= 2
            right = (keyed(k, 5) & np.uint64(1)).astype(bool)
            wait = t - np.log(unit(keyed(k, 7))) / width
            kl, kr = keyed(k, 11), keyed(k, 13)
            k = np.concatenate([kl, kr])
            t = np.concatenate([np.where(right, wait, t), np.where(right, t, wait)])
            d, w, lo = np.concatenate([d, d]), np.concatenate([w, w]), np.concatenate([lo, lo + width])
        if len(k):
            out.append((k, t, d))
        s += 1
    if not out:
        return np.zeros(0, np.uint64), np.zeros(0), np.zeros(0, np.int64)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def signatures(bags: list[np.ndarray], m: int) -> list[np.ndarray | None]:
    """The m component identities of each bag (an array of shingle hashes, repeats allowed); None for an empty bag."""
    sig = np.zeros((len(bags), m), np.uint64)
    todo = [i for i, b in enumerate(bags) if len(b)]
    spare = 6.0
    while todo:
        keys, weight, doc, limit = [], [], [], np.zeros(len(bags))
        for i in todo:
            u, c = np.unique(bags[i], return_counts=True)
            keys.append(u)
            weight.append(c)
            doc.append(np.full(len(u), i))
            limit[i] = m * (math.log(m) + spare) / len(bags[i])
        k, t, d = shells(np.concatenate(keys), np.concatenate(weight), np.concatenate(doc), limit)
        ids, times, where, part = [], [], [], []
        n = 0
        while len(k):
            p = keyed(k, 17 + 4 * n)
            ids.append(p)
            times.append(t)
            where.append(d)
            part.append((mix64(p ^ np.uint64(0x5851F42D4C957F2D)) % np.uint64(m)).astype(np.int64))
            t = t - np.log(unit(keyed(k, 18 + 4 * n)))
            ok = t <= limit[d]
            k, t, d = k[ok], t[ok], d[ok]
            n += 1
        if ids:
            ids, times, where, part = (np.concatenate(x) for x in (ids, times, where, part))
            at = where * m + part
            last = np.lexsort((-times, at))  # within a component the earliest comes last
            at = at[last]
            end = np.append(at[1:] != at[:-1], True)
            sig.reshape(-1)[at[end]] = ids[last][end]
            full = np.bincount(at[end] // m, minlength=len(bags))
        else:
            full = np.zeros(len(bags), np.int64)
        todo = [i for i in todo if full[i] < m]
        for i in todo:
            sig[i] = 0
        spare *= 3
    return [sig[i] if len(b) else None for i, b in enumerate(bags)]


def bags(texts: list[str], k: int = WORDS) -> list[np.ndarray]:
    """Shingle hashes of each text, repeats kept."""
    return [windows(h, k) for h in hashed_words(texts)]


def weighted_jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Sum of minima over sum of maxima of the two multisets; 1 for two empty ones."""
    if not len(a) and not len(b):
        return 1.0
    ua, ca = np.unique(a, return_counts=True)
    ub, cb = np.unique(b, return_counts=True)
    _, ia, ib = np.intersect1d(ua, ub, assume_unique=True, return_indices=True)
    low = int(np.minimum(ca[ia], cb[ib]).sum())
    return low / (len(a) + len(b) - low)


def sketch(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, k: int = WORDS) -> DataFrame:
    """(doc_id, key, bands): digest of the whole text and the band hashes (none for a text without words)."""

    def begin():
        def each(cols):
            sigs = signatures(bags(cols["text"], k), bands * rows)
            out = []
            for s in sigs:
                if s is None:
                    out.append([])
                    continue
                g = s.reshape(bands, rows)
                h = np.arange(bands, dtype=np.uint64)
                for j in range(rows):
                    h = keyed(h ^ g[:, j], j + 1)
                out.append(h.view(np.int64).tolist())
            return {"doc_id": cols["doc_id"], "key": [hashlib.md5(t.encode("utf-8", "surrogatepass")).digest() for t in cols["text"]], "bands": out}

        return each

    return map_rows(texts(docs), begin, struct(doc_id=LONG, key=BIN, bands=T.ArrayType(LONG)), size=128)


def fetched(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """(doc_id, text) of the given ids, stored: the one time that texts are shuffled, by the same plan at every size."""
    return stored(texts(docs).hint("merge").join(ids, "doc_id", "left_semi").groupBy("doc_id").agg(F.first("text").alias("text")))


def verified(pairs: DataFrame, found: DataFrame, least: float, k: int) -> DataFrame:
    """The pairs (a, b) whose whole texts, in ``found``, reach the similarity."""
    both = pairs.join(found.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a").join(found.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b")

    def begin():
        def each(cols):
            twice = {}  # heads of large buckets stand in many pairs of a slice
            for side, t in (("a", "ta"), ("b", "tb")):
                twice |= dict(zip(cols[side], cols[t], strict=True))
            held = dict(zip(twice, bags(list(twice.values()), k), strict=True))
            sims = [weighted_jaccard(held[a], held[b]) for a, b in zip(cols["a"], cols["b"], strict=True)]
            return {"a": cols["a"], "b": cols["b"], "sim": sims}

        return each

    sims = map_rows(both, begin, struct(a=LONG, b=LONG, sim=T.DoubleType()))
    return sims.where(F.col("sim") >= least)


def elements(shingles: np.ndarray) -> list[int]:
    """A multiset of shingles as a set: (shingle, copy) cells hashed to 64 bits."""
    u, c = np.unique(shingles, return_counts=True)
    copy = np.arange(int(c.sum())) - np.repeat(np.cumsum(c) - c, c) if len(c) else np.zeros(0, np.int64)
    return keyed(np.repeat(u, c), copy.astype(np.uint64)).view(np.int64).tolist()


def crossing(members: DataFrame, found: DataFrame, t: float, k: int) -> DataFrame:
    """(a, b), a > b: every pair of ``members`` (rep, comp) of different groups that may reach the similarity, none left out.

    Cells are ordered by how few members hold them. Two sets of sizes x <= y reach Jaccard t only if they share o = t / (1 + t) * (x + y)
    cells, hence one among the first x - o + 1 of the one and y - o + 1 of the other: members meet on such cells only. A
    member with many cells of its own, as far edited copies have, meets nobody."""
    t_ = found.join(members.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi")

    def begin():
        return lambda cols: {"rep": cols["doc_id"], "e": list(map(elements, bags(cols["text"], k)))}

    sets = stored(map_rows(t_, begin, struct(rep=LONG, e=T.ArrayType(LONG)))).select("rep", F.size("e").alias("n"), F.explode("e").alias("e"))
    held = sets.groupBy("e").agg(F.count(F.lit(1)).alias("f")).where("f > 1")
    shared = sets.join(held, "e")
    own = Window.partitionBy("rep")
    place = F.col("n") - F.count(F.lit(1)).over(own) + F.row_number().over(own.orderBy("f", "e"))
    first = shared.withColumn("pos", place).where(F.col("pos") <= F.col("n") - F.ceil(t * F.col("n") - 1e-9) + 1)
    first = stored(first.select("rep", "n", "e", "pos").join(members, "rep"))
    x, y = (first.select("e", *[F.col(c).alias(f"{c}_{s}") for c in ("rep", "n", "pos", "comp")]) for s in "xy")
    need = F.ceil(t / (1 + t) * (F.col("n_x") + F.col("n_y")) - 1e-9)
    smaller = (F.col("n_x") < F.col("n_y")) | ((F.col("n_x") == F.col("n_y")) & (F.col("rep_x") < F.col("rep_y")))
    near = smaller & (F.col("comp_x") != F.col("comp_y")) & (F.col("n_x") >= t * F.col("n_y") - 1e-9) & (F.col("pos_x") <= F.col("n_x") - need + 1) & (F.col("pos_y") <= F.col("n_y") - need + 1)
    met = x.join(y, (x.e == y.e) & near)
    return met.select(F.greatest("rep_x", "rep_y").alias("a"), F.least("rep_x", "rep_y").alias("b")).distinct()


@cleared
def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY, words: int = WORDS, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, class_id, exact_id) for every document.

    exact_id is the least id with the same whole text, class_id the least id of the group linked by
    pairs of weighted Jaccard similarity >= ``similarity``. Exact copies meet through a digest
    and are represented by one of them from then on. In each band bucket all members are compared
    with the least one (a star, linear in the bucket). Buckets whose members are then in several groups are settled by an exact
    prefix join of their members (``crossing``), so no link between groups is left out and a group of n copies never makes n^2 rows.

    Null texts count as empty; texts without words match only equal texts; rows with a null doc_id are
    left out; repeated ids count as one document, whose class is the least that its texts have. An
    empty table gives no rows. Other columns are ignored.
    """
    sig = stored(sketch(docs.where("doc_id is not null"), bands, rows, words))
    reps = stored(sig.groupBy("key").agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands")))
    member = sig.join(reps.select("key", "rep"), "key").select("doc_id", "rep")
    rows_ = reps.select("rep", F.explode("bands").alias("band"))
    heads = rows_.groupBy("band").agg(F.min("rep").alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1").select("band", "head")
    stars = stored(rows_.join(heads, "band").where("rep <> head").select("band", F.col("rep").alias("a"), F.col("head").alias("b")))
    tried = stored(stars.select("a", "b").distinct())
    found = fetched(docs, tried.select(F.col("a").alias("doc_id")).union(tried.select("b")).distinct())
    links = stored(verified(tried, found, similarity, words).select("a", "b"))
    comp = stored(components(links))

    def open_buckets() -> DataFrame:
        """Stars of the buckets whose members are in several groups: (band, a, b, ga, gb)."""
        ca, cb = comp.select(F.col("node").alias("a"), F.col("comp").alias("ga")), comp.select(F.col("node").alias("b"), F.col("comp").alias("gb"))
        g = stored(stars.join(ca, "a", "left").join(cb, "b", "left").select("band", "a", "b", F.coalesce("ga", "a").alias("ga"), F.coalesce("gb", "b").alias("gb")))
        return g.join(g.where("ga <> gb").select("band").distinct(), "band", "left_semi")

    g = stored(open_buckets())
    if g.take(1):
        # more heads for the members outside the head's group: again a few comparisons a member
        other = g.where("ga = gb").groupBy("band").agg(*[F.min(F.struct(F.xxhash64("a", F.lit(j)), F.col("a").alias("h"))).alias(f"h{j}") for j in range(HEADS)])
        # a bucket's heads stand in each of its parts, so that the members of a large bucket meet them in many tasks
        spread = other.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(PARTS - 1))))
        dealt = g.where("ga <> gb").select("band", "a", F.pmod(F.xxhash64("a"), F.lit(PARTS)).cast("int").alias("part"))
        again = dealt.join(spread, ["band", "part"]).select("a", F.explode(F.array(*[F.col(f"h{j}.h") for j in range(HEADS)])).alias("b"))
        again = stored(again.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct().join(tried, ["a", "b"], "left_anti"))
        links = stored(links.union(verified(again, found, similarity, words).select("a", "b")))
        tried = tried.union(again)
        comp = stored(components(links))
        g = stored(open_buckets())
        open_ = stored(g.select(F.col("a").alias("rep"), F.col("ga").alias("comp")).union(g.select("b", "gb")).distinct())
        rest = stored(crossing(open_, found, similarity, words).join(tried, ["a", "b"], "left_anti"))
        if rest.take(1):
            more = stored(verified(rest, found, similarity, words).select("a", "b"))
            comp = stored(components(links.union(more)))
    out = member.join(comp.withColumnRenamed("node", "rep"), "rep", "left").select("doc_id", F.coalesce("comp", "rep").alias("class_id"), F.col("rep").alias("exact_id"))
    return out.groupBy("doc_id").agg(F.min("class_id").alias("class_id"), F.min("exact_id").alias("exact_id"))


def keep_one(docs: DataFrame, **settings) -> DataFrame:
    """The rows of ``docs`` whose document leads its group, repeated rows once; rows with a null doc_id stay as they are."""
    lead = near_duplicates(docs, **settings).where("doc_id = class_id").select("doc_id")
    names = docs.columns
    own = docs.where("doc_id is not null").join(lead, "doc_id", "left_semi").select(names)
    return own.dropDuplicates(["doc_id"]).select(names).union(docs.where("doc_id is null").select(names))
