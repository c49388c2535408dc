"""Language identification with bit-sliced Bloom filters of character n-grams.

Each language has one bit in every slot of a shared table, so one probe (the AND of a few slots) returns the mask of all
languages that may contain an n-gram. A language's filter holds the n-grams that make up at least a given share of its
training text, which bounds its size. A text's probes are counted by language, the counts are
corrected by each filter's false-positive rate, and the largest corrected share decides.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import DBL, LONG, STR, held_out, map_rows, mix64, struct, texts

LETTERS = re.compile(r"[^\W\d_]+")
SIZES = (2, 3, 4)
HASHES = 4
LONGEST = 40
#: Characters of distinct words whose n-grams are laid out at once.
CHARACTERS = 1 << 18


def grams(word: str) -> list[str]:
    """n-grams of a word with its edges marked; a long run of letters is read in full."""
    w = f"^{word}$"
    return [w[i : i + n] for n in SIZES for i in range(len(w) - n + 1)]


def laid(words: list[str]) -> tuple[np.ndarray, list[tuple[int, np.ndarray, np.ndarray]]]:
    """(code points of all words with their edges, one after another; for each n: n, where its n-grams begin, how many each word has)."""
    c = np.frombuffer(f"^{'$^'.join(words)}$".encode("utf-32-le", "surrogatepass"), "<u4") if words else np.zeros(0, np.uint32)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 2
    left = np.repeat(np.cumsum(size), size) - np.arange(len(c))
    return c, [(n, np.flatnonzero(left >= n), np.maximum(size - n + 1, 0)) for n in SIZES]


def portions(words: list[str], most: int = CHARACTERS) -> Iterator[list[str]]:
    """The words in runs of about ``most`` characters, one word at least."""
    part = np.cumsum(np.fromiter(map(len, words), np.int64, len(words))) // most
    at = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(words)]
    yield from (words[s:e] for s, e in zip(at, at[1:], strict=False) if e > s)


def counted(words: dict[str, int]) -> tuple[list[str], list[int]]:
    """The n-grams of all words, and how many there are when each word counts as often as it says."""
    c, each = laid(list(words))
    letters, code = np.unique(c, return_inverse=True)
    if len(letters) > 0xFFFF:  # four numbers of letters do not fit one key
        g: Counter = Counter()
        for w, k in words.items():
            for x in grams(w):
                g[x] += k
        return list(g), list(g.values())
    code, times = code.astype(np.uint64) + np.uint64(1), np.fromiter(words.values(), np.int64, len(words))
    keys, weights = [], []
    for n, at, many in each:
        key = code[at]
        for j in range(1, n):
            key |= code[at + j] << np.uint64(16 * j)
        keys.append(key)
        weights.append(np.repeat(times, many))
    key, place = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.bincount(place, np.concatenate(weights), len(key)).astype(np.int64)
    digit = (key[:, None] >> (np.uint64(16) * np.arange(max(SIZES), dtype=np.uint64))) & np.uint64(0xFFFF)
    points = np.append(np.uint32(0), letters)[digit.astype(np.int64)].astype("<u4")  # zeros behind a shorter n-gram are no part of a string
    return points.view(f"<U{max(SIZES)}")[:, 0].tolist(), total.tolist()


def gram_counts(rows: DataFrame) -> DataFrame:
    """(lang, gram, n) over every training text, summed inside a slice first."""

    def begin():
        def each(cols):
            words: dict[str, Counter] = {}
            for t, lang in zip(cols["text"], cols["lang"], strict=True):
                words.setdefault(lang, Counter()).update(LETTERS.findall(t.lower()))
            out = {"lang": [], "gram": [], "n": []}
            for lang, c in words.items():
                for some in portions(list(c)):
                    g, n = counted({w: c[w] for w in some})
                    out["lang"] += [lang] * len(g)
                    out["gram"] += g
                    out["n"] += n
            return out

        return each

    return map_rows(rows, begin, struct(lang=STR, gram=STR, n=LONG), size=4096).groupBy("lang", "gram").agg(F.sum("n").alias("n"))


@dataclass
class Filters:
    """The bit-sliced table: ``slots[i]`` has bit l set when some n-gram of language l hashes there."""

    langs: list[str]
    slots: np.ndarray
    false: np.ndarray

    def masks(self, hashes: np.ndarray) -> np.ndarray:
        m = len(self.slots)
        out = np.full(len(hashes), np.uint64(0xFFFFFFFFFFFFFFFF))
        for j in range(HASHES):
            out &= self.slots[mix64(hashes + np.uint64(j * 0x51ED27)) % np.uint64(m)]
        return out


def hashed_points(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Hashes of n-grams from their first two and next two code points, each pair in one integer."""
    return mix64(first + mix64(second + np.uint64(0x9E3779B9)))


def hashed(gs: list[str]) -> np.ndarray:
    c = np.array(gs, f"<U{max(SIZES)}").view("<u4").reshape(len(gs), max(SIZES)).astype(np.uint64)
    return hashed_points(c[:, 0] | c[:, 1] << np.uint64(32), c[:, 2] | c[:, 3] << np.uint64(32))


def fit(docs: DataFrame, share: float = 3e-5, bits: int = 16) -> Filters:
    """Learn from all held-in rows with a language. At most ``1/share`` n-grams of a language can reach its share, so
    what is collected is bounded by the number of languages (64 at most), whatever the corpus holds."""
    rows = docs.where("lang is not null and text is not null").where(~held_out(4, 2)).select("text", "lang")
    n = gram_counts(rows)
    total = n.groupBy("lang").agg(F.sum("n").alias("total"))
    kept = n.join(F.broadcast(total), "lang").where(F.col("n") >= F.greatest(F.lit(2.0), share * F.col("total"))).select("lang", "gram").collect()
    langs = sorted({r[0] for r in kept})
    if len(langs) > 64:
        raise ValueError("a mask holds at most 64 languages")
    by: dict[str, list[str]] = {x: [] for x in langs}
    for lang, g in kept:
        by[lang].append(g)
    m = max(1 << 12, bits * max((len(g) for g in by.values()), default=1))
    slots = np.zeros(m, np.uint64)
    for k, lang in enumerate(langs):
        h = hashed(by[lang])
        for j in range(HASHES):
            np.bitwise_or.at(slots, (mix64(h + np.uint64(j * 0x51ED27)) % np.uint64(m)).astype(np.int64), np.uint64(1 << k))
    fill = np.array([float(((slots >> np.uint64(k)) & np.uint64(1)).mean()) for k in range(len(langs))])
    return Filters(langs, slots, fill**HASHES)


class WordCounts(dict):
    """Word -> for each language how many of its n-grams the filter returns, and their number, in 32-bit lanes of one integer."""

    def __init__(self, f: Filters, most: int = 300_000):
        super().__init__()
        self.f, self.most = f, most

    def meet(self, words: set[str]) -> None:
        """Hold every one of ``words``; a memo past its bound is emptied before it is asked what it lacks."""
        if len(self) > self.most:
            self.clear()
        self.learn(list(words.difference(self)))

    def learn(self, words: list[str]) -> None:
        for some in portions(words):
            c, each = laid(some)
            c = c.astype(np.uint64)
            lanes = np.zeros((len(self.f.langs) + 1, len(some)), np.int64)
            for n, at, many in each:
                second = np.zeros(len(at), np.uint64)
                for j in range(2, n):
                    second |= c[at + j] << np.uint64(32 * (j - 2))
                mask = self.f.masks(hashed_points(c[at] | c[at + 1] << np.uint64(32), second))
                end = np.cumsum(many)
                lanes[0] += many
                for k in range(len(self.f.langs)):
                    upto = np.append(0, np.cumsum((mask >> np.uint64(k)) & np.uint64(1), dtype=np.int64))
                    lanes[k + 1] += upto[end] - upto[end - many]
            held = lanes[0].tolist()
            for k, lane in enumerate(lanes[1:].tolist(), 1):
                held = [v + (x << 32 * k) for v, x in zip(held, lane, strict=True)]
            self.update(zip(some, held, strict=True))


def predict(docs: DataFrame, f: Filters, most: int = 300_000) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row: ``und`` and 0 where the text is null or has no letter, or nothing was learned.

    score is the winner's corrected count over the sum of all corrected counts; ties go to the first name. ``most`` bounds the words
    remembered between slices and changes no result."""

    def begin():
        memo = WordCounts(f, most)
        n = len(f.langs)

        def each(cols):
            sets = [set(LETTERS.findall(t.lower())) for t in cols["text"]]
            memo.meet(set().union(*sets))
            langs, scores = [], []
            for s in sets:
                if not s or not n:
                    langs.append("und")
                    scores.append(0.0)
                    continue
                v = sum(map(memo.__getitem__, s))
                total = v & 0xFFFFFFFF
                hit = np.array([(v >> (32 * (k + 1))) & 0xFFFFFFFF for k in range(n)], float)
                real = np.maximum((hit - f.false * total) / (1 - np.minimum(f.false, 0.99)), 0)
                k = int(real.argmax())
                langs.append(f.langs[k])
                scores.append(float(real[k] / real.sum()) if real.sum() > 0 else 0.0)
            for w in [w for s in sets for w in s if len(w) > LONGEST]:
                memo.pop(w, None)
            return {"doc_id": cols["doc_id"], "lang_pred": langs, "score": scores}

        return each

    out = map_rows(texts(docs), begin, struct(doc_id=LONG, lang_pred=STR, score=DBL))
    return out.select("doc_id", held_out(4, 2).alias("held_out"), "lang_pred", "score")
