"""Bag min-hash near-duplicates against brute force over all pairs."""

import random
from collections import Counter

import numpy as np

from vgraph.llm import near_dedup as nd
from vgraph.llm.common import WORD
from vgraph.llm.components import components


def similarity(a: str, b: str) -> float:
    def grams(t):
        w = WORD.findall(t)
        k = min(5, len(w))
        return Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if w else Counter()

    x, y = grams(a), grams(b)
    low = sum((x & y).values())
    return low / (sum(x.values()) + sum(y.values()) - low) if x and y else 0.0


def brute(docs: list[tuple[int, str]]) -> dict[int, int]:
    up = {i: i for i, _ in docs}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for n, (i, a) in enumerate(docs):
        for j, b in docs[:n]:
            if a == b or similarity(a, b) >= 0.8:
                x, y = sorted((root(i), root(j)))
                up[y] = x
    return {i: root(i) for i in up}


def corpus():
    r = random.Random(4)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(4))
    docs, base = [], [word() for _ in range(120)]
    for _ in range(90):  # copies edited so far that many reach 0.8 with few others or with none
        t = list(base)
        for _ in range(r.randint(0, 7)):
            t[r.randrange(len(t))] = word()
        docs.append(" ".join(t))
    docs += [docs[3]] * 5 + ["", "", None, "one", "one", "two words", "a a a a a a a a a a a a", "a a a a a a a a a a a", "a " * 40, " ".join(base * 30)]
    docs += [" ".join(word() for _ in range(60)) for _ in range(20)]
    return [(i * 3 + 1, t) for i, t in enumerate(docs)]


def test_classes_are_those_of_brute_force(spark):
    rows = corpus()
    got = {r.doc_id: r.class_id for r in nd.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute([(i, t or "") for i, t in rows])


def test_one_of_each_stays_and_columns_too(spark):
    rows = [(5, "x y z", 1, "k"), (2, "x y z", 2, None), (9, "other text here", 3, "k"), (9, "other text here", 3, "k"), (None, "x y z", 4, "n")]
    d = spark.createDataFrame(rows, "doc_id long, text string, class_id int, rep string")
    kept = nd.keep_one(d)
    assert kept.columns == d.columns
    assert sorted((r.doc_id or -1, r.class_id) for r in kept.collect()) == [(-1, 4), (2, 2), (9, 3)]
    assert nd.near_duplicates(d.where("false")).count() == 0


def test_signature_estimates_weighted_jaccard():
    r = np.random.default_rng(0)
    a = np.repeat(r.integers(0, 1 << 62, 80).astype(np.uint64), r.integers(1, 30, 80))
    b = np.concatenate([a[: len(a) * 3 // 4], r.integers(0, 1 << 62, 100).astype(np.uint64)])
    m = 4000
    x, y = nd.signatures([a, b], m)
    assert abs((x == y).mean() - nd.weighted_jaccard(a, b)) < 0.03
    assert (nd.signatures([a], m)[0] == x).all()  # no dependence on what stands beside it


def test_shells_equal_cells():
    """A shingle that occurs w times has the first w cells of one that occurs more often."""
    k = np.array([7], np.uint64)
    far = np.array([1e9])
    few, many = (set(nd.shells(k, np.array([w]), np.array([0]), far)[0].tolist()) for w in (5, 12))
    assert len(few) == 5 and len(many) == 12 and few < many


def test_components(spark):
    e = [(i, i + 1) for i in range(0, 60)] + [(100, 200 + i) for i in range(50)] + [(7, 7)]
    got = {r.node: r.comp for r in components(spark.createDataFrame(e, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(61)} | {i: 100 for i in [100, *range(200, 250)]}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
