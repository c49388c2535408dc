"""Toxicity by weak supervision.

Voters: a fixed lexicon, words and word beginnings whose presence differs most between the labelled classes
(mined from held-in labels), and patterns of writing. Each voter speaks or is silent, and both say something. A
generative label model estimates by expectation maximisation, over labelled and unlabelled held-in rows, how often each
voter speaks in either class. Voters that go together are modelled twice: a class has several components, on which other voters
speak, and a voter may depend on a parent voter (the forest of the strongest dependences left). Labels serve the rates;
they are no voters, and a row's posterior is that of its votes. A linear classifier is then trained on the posteriors of all
these rows, over the voters' (capped) counts, and scores every text.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import DBL, LONG, STR, held_out, map_rows, stored, struct, texts

TOKEN = re.compile(r"\w+")
#: Common English insults that vote from the start, before any label is seen.
LEXICON = (
    "arse", "bastard", "bigot", "bitch", "bollocks", "bullshit", "clown", "coward", "cretin", "crap", "damn", "degenerate", "dickhead", "dimwit", "disgusting",
    "douchebag", "dumb", "dumbass", "filth", "fool", "freak", "fuck", "garbage", "halfwit", "hypocrite", "idiot", "imbecile", "jackass", "jerk", "liar", "loser", "lowlife",
    "lunatic", "maggot", "moron", "nitwit", "parasite", "pathetic", "pig", "prick", "retard", "scum", "scumbag", "shit", "slut", "stupid", "thug", "trash", "twat",
    "vermin", "wanker", "whore", "wimp", "worthless",
)
PATTERNS = {"shout": re.compile(r"[A-Z]{4,}!!"), "masked": re.compile(r"\b\w+\*{2,}\w*"), "you_are": re.compile(r"\byou(?:'re| are) (?:an? |such )", re.I)}
BEGINNINGS = (4, 5, 6)
CAP = 6


def word_features(word: str) -> list[str]:
    return [word, *(f"{word[:n]}*" for n in BEGINNINGS if len(word) > n)]


def counted(words: set[str]) -> Counter:
    """How many distinct words of a text carry each feature."""
    return Counter(f for w in words for f in word_features(w))


def tally(rows: DataFrame) -> DataFrame:
    """(feature, once, twice, thrice, toxic): labelled texts in which so many distinct words or more carry the feature."""

    def begin():
        def each(cols):
            c: dict[tuple[str, int], list[int]] = {}
            for t, y in zip(cols["text"], cols["toxic"], strict=True):
                for f, n in counted(set(TOKEN.findall(t.lower()))).items():
                    x = c.get((f, y))
                    if x is None:
                        x = c[f, y] = [0, 0, 0]
                    x[0] += 1
                    if n > 1:
                        x[1] += 1
                        if n > 2:
                            x[2] += 1
            return {"feature": [k[0] for k in c], "toxic": [k[1] for k in c], **{n: [v[i] for v in c.values()] for i, n in enumerate(("once", "twice", "thrice"))}}

        return each

    return map_rows(rows, begin, struct(feature=STR, toxic=LONG, once=LONG, twice=LONG, thrice=LONG)).groupBy("feature", "toxic").agg(*[F.sum(c).alias(c) for c in ("once", "twice", "thrice")])


@dataclass
class Model:
    """Voters with their thresholds, what the label model found, and the classifier's weights."""

    voters: list[str]
    least: list[int]
    labels: LabelModel | None
    weights: np.ndarray
    bias: float

    def lookup(self) -> dict[str, int]:
        return {v: i for i, v in enumerate(self.voters)}


def votes_of(text: str, memo: dict[str, tuple[int, ...]]) -> tuple[Counter, int]:
    """Voter number -> distinct words of the text that speak for it; and the number of distinct words."""
    c: Counter = Counter()
    words = set(TOKEN.findall(text.lower()))
    for hit in filter(None, map(memo.__getitem__, words)):
        c.update(hit)
    return c, len(words)


class VoteMemo(dict):
    def __init__(self, voters: dict[str, int], most: int = 400_000):
        super().__init__()
        self.voters, self.most = voters, most

    def __missing__(self, word: str) -> tuple[int, ...]:
        if len(self) >= self.most:
            self.clear()
        out = self[word] = tuple(i for f in word_features(word) if (i := self.voters.get(f)) is not None)
        return out


def pattern_votes(text: str) -> list[int]:
    if "!!" not in text and "**" not in text and "ou" not in text.lower():
        return [0] * len(PATTERNS)
    return [min(CAP, sum(1 for _ in zip(range(CAP), p.finditer(text), strict=False))) for p in PATTERNS.values()]


def votes(rows: DataFrame, voters: list[str]) -> DataFrame:
    """(doc_id, at, n, words): the voters that speak on each text, by number, with their capped counts; its distinct words."""
    table = {v: i for i, v in enumerate(voters)}
    words = len(voters) - len(PATTERNS)

    def begin():
        memo = VoteMemo(table)

        def each(cols):
            at, n, words_ = [], [], []
            for t in cols["text"]:
                c, size = votes_of(t, memo)
                words_.append(size)
                for j, k in enumerate(pattern_votes(t)):
                    if k:
                        c[words + j] = k
                at.append(list(c))
                n.append([min(CAP, v) for v in c.values()])
            return {"doc_id": cols["doc_id"], "at": at, "n": n, "words": words_}

        return each

    return map_rows(texts(rows), begin, struct(doc_id=LONG, at=T.ArrayType(T.IntegerType()), n=T.ArrayType(T.IntegerType()), words=LONG))


@dataclass
class LabelModel:
    """How votes arise: a class, a component of that class (kinds of texts on which other voters speak), and each voter given
    the component and whether its parent voter speaks.

    ``parent[j]`` is the voter that j depends on (-1: none); ``rate[c, v, j]`` the chance that j speaks in component c where its
    parent is silent (v = 0, also without a parent) or speaks (v = 1); ``share[c]`` how frequent the component is; ``kind[c]`` its class."""

    kind: np.ndarray
    share: np.ndarray
    parent: np.ndarray
    rate: np.ndarray

    def components(self, fired: np.ndarray) -> np.ndarray:
        """Chance of each component given all votes, silence included."""
        out = np.empty((len(fired), len(self.kind)))
        has = self.parent >= 0
        for at in range(0, len(fired), 4096):  # bounds the tables alive at once
            f = fired[at : at + 4096].astype(bool)
            led = f[:, np.maximum(self.parent, 0)] & has
            for c in range(len(self.kind)):
                p = np.where(led, self.rate[c, 1], self.rate[c, 0])
                out[at : at + 4096, c] = math.log(self.share[c]) + np.log(np.where(f, p, 1 - p)).sum(1)
        out = np.exp(out - out.max(1, keepdims=True))
        return out / out.sum(1, keepdims=True)

    def posterior(self, fired: np.ndarray) -> np.ndarray:
        return self.components(fired)[:, self.kind == 1].sum(1)

    def accuracy(self) -> np.ndarray:
        """Of each voter: how often its vote would be right if both classes were equally frequent."""
        r = [(self.share[self.kind == y, None] * self.rate[self.kind == y, 0]).sum(0) / self.share[self.kind == y].sum() for y in (0, 1)]
        return r[1] / (r[0] + r[1])


def dependence(f: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Mutual information of each pair of voters within the components (in nats a row); w: each row's share in each component."""
    n, out = len(f), 0.0
    for c in range(w.shape[1]):
        total = w[:, c].sum() + 1e-9
        both = (f.T @ (f * w[:, c, None].astype(np.float32))).astype(np.float64) / total
        one = np.clip(np.diag(both).copy(), 1e-9, 1 - 1e-9)
        for a, b, p in ((one, one, both), (one, 1 - one, one[:, None] - both), (1 - one, one, one[None] - both), (1 - one, 1 - one, 1 - one[:, None] - one[None] + both)):
            p = np.maximum(p, 1e-12)
            out = out + total / n * p * np.log(p / np.outer(a, b))
    return out


def parents(f: np.ndarray, w: np.ndarray) -> np.ndarray:
    """The forest of the strongest dependences: greedy from the strongest pair on, as long as it is beyond chance for so many pairs."""
    k = f.shape[1]
    info = np.triu(dependence(f, w), 1)
    least = (2 * math.log(max(k, 2)) + 4 * w.shape[1]) / len(f)
    i, j = np.nonzero(info > least)
    group, near = list(range(k)), [[] for _ in range(k)]

    def top(x):
        while group[x] != x:
            group[x] = x = group[group[x]]
        return x

    for e in np.argsort(-info[i, j], kind="stable").tolist():
        a, b = int(i[e]), int(j[e])
        if top(a) != top(b):
            group[top(a)] = top(b)
            near[a].append(b)
            near[b].append(a)
    parent, seen = np.full(k, -1), [False] * k
    for root in range(k):
        if seen[root]:
            continue
        seen[root], todo = True, [root]
        while todo:
            x = todo.pop()
            for y in near[x]:
                if not seen[y]:
                    seen[y], parent[y] = True, x
                    todo.append(y)
    return parent


def clusters(f: np.ndarray, weight: np.ndarray, k: int, rounds: int = 8) -> np.ndarray:
    """A first guess of components: each row's part (one of k) by a few rounds of k-means on vote directions, seeded far apart."""
    x = f / np.maximum(np.linalg.norm(f, axis=1, keepdims=True), 1e-9)
    r = np.random.default_rng(0)
    centers, far = [], weight * (f.any(1) + 1e-3)
    for _ in range(k):
        if far.sum() <= 0:
            break
        centers.append(x[r.choice(len(x), p=far / far.sum())])
        far = np.minimum(far, weight * np.maximum(1 - x @ centers[-1], 0))
    centers = np.array(centers or [np.zeros(f.shape[1])])
    for _ in range(rounds):
        part = (x @ centers.T).argmax(1)
        for c in range(len(centers)):
            m = (part == c) * weight
            if m.sum() > 0:
                v = m @ x
                centers[c] = v / max(np.linalg.norm(v), 1e-9)
    return part


def label_model(fired: np.ndarray, prior: float, start: np.ndarray, known: np.ndarray | None = None, kinds: int = 6, rounds: int = 24) -> tuple[np.ndarray, LabelModel]:
    """Posterior of each row by expectation maximisation, and the model; ``kinds`` components a class.

    ``start`` is a first guess of the posterior. Rows where ``known`` (0 or 1, nan: unknown) names the class count as that
    class when rates are estimated, but their own posterior, as returned, comes from their votes alone."""
    f = fired.astype(np.float32)
    known = np.full(len(f), np.nan) if known is None else known
    kind = np.repeat([0, 1], kinds)
    first = np.clip(np.where(np.isnan(known), start, known).astype(np.float64), 0, 1)
    w = np.zeros((len(f), 2 * kinds))
    for y, v in ((0, 1 - first), (1, first)):
        w[np.arange(len(f)), y * kinds + clusters(f, v, kinds)] = 0.9 * v
        w[:, kind == y] += 0.1 * v[:, None] / kinds
    q = start
    for it in range(rounds):
        if it % 6 == 0:
            parent = parents(f, w)
        led = np.where(parent >= 0, f[:, np.maximum(parent, 0)], 0)
        rate, share = np.empty((2 * kinds, 2, f.shape[1])), np.empty(2 * kinds)
        for c in range(2 * kinds):
            x, all_ = w[:, c, None].astype(np.float32), w[:, kind == kind[c]].sum(1).astype(np.float32)
            whole = (all_ @ f + 0.5) / (all_.sum() + 1)
            mean = ((x * f).sum(0) + whole) / (x.sum() + 1)
            for v, mine in ((0, x * (1 - led)), (1, x * led)):
                rate[c, v] = ((mine * f).sum(0) + mean) / (mine.sum(0) + 1)
            share[c] = (prior if kind[c] else 1 - prior) * (x.sum() + 1) / (all_.sum() + kinds)
        model = LabelModel(kind, share, parent, np.clip(rate, 1e-5, 1 - 1e-5))
        part = model.components(fired)
        new = part[:, kind == 1].sum(1)
        step, q = float(np.abs(new - q).max()), new
        for y in (0, 1):  # a known class leaves only the choice of its component
            mine = part[:, kind == y]
            sure = mine / np.maximum(mine.sum(1, keepdims=True), 1e-300)
            w[:, kind == y] = np.where(np.isnan(known)[:, None], mine, sure * (known == y)[:, None])
        if step < 1e-4:
            break
    return q, model


def linear(x: np.ndarray, y: np.ndarray, l2: float = 1.0, rounds: int = 40) -> np.ndarray:
    """Weights (last: bias) of a logistic fit to soft labels, by Newton steps."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1])
    ridge = np.full(x.shape[1], l2)
    ridge[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + ridge * w
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(ridge + 1e-6)
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


def shaped(count: np.ndarray, least: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Classifier inputs: whether a voter reaches its threshold, its count over that, and the log of the text's distinct words."""
    over = np.maximum(count.astype(np.int64) - least + 1, 0)
    return np.hstack([(over > 0).astype(np.float64), np.minimum(over, 4) / 4.0, np.log1p(words)[:, None] / 4.0])


def unlabelled(docs: DataFrame, labels: DataFrame, bound: int) -> DataFrame:
    """(doc_id): of the held-in rows without a label the ``bound`` of least hashed id. Ids alone are dealt and sorted, and only those that
    lie in the least part of the hashes where about twice as many are expected; all of them where too few lie there."""
    free = docs.where("doc_id is not null").where(~held_out(3, 1)).select("doc_id").join(labels.where("toxic is not null").select("doc_id"), "doc_id", "left_anti")
    rows = max(docs.count(), 1)
    low = free.where(F.xxhash64("doc_id") <= min((1 << 63) - 1, -(1 << 63) + (1 << 64) * 2 * bound // rows))
    for some in (low, free):
        got = stored(some.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound))
        if got.count() == bound:
            break
    return got.distinct()


def fit(docs: DataFrame, labels: DataFrame, bound: int = 20_000, most: int = 240, apart: float = 7.0) -> Model:
    """Learn from at most ``bound`` held-in labelled rows and as many without a label (those of the smallest hashed ids).

    What reaches the driver: at most ``most`` mined voters and the votes of the bounded sample. Without any held-in
    label of both kinds the fixed lexicon alone votes."""
    known = labels.where("doc_id is not null and toxic is not null").where(~held_out(3, 1)).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("long").alias("toxic"))
    some = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    sample = texts(docs.join(F.broadcast(some.select("doc_id")), "doc_id", "left_semi")).join(F.broadcast(some), "doc_id")
    classes = {int(r[0]): int(r[1]) for r in some.groupBy("toxic").count().collect()}
    n1, n0 = classes.get(1, 0), sum(v for k, v in classes.items() if k != 1)
    extra = list(PATTERNS)
    if not n1 or not n0:
        voters = [*LEXICON, *extra]
        w = np.concatenate([np.full(len(LEXICON), 2.2), np.zeros(len(extra) + len(voters) + 1)])
        return Model(voters, [1] * len(voters), None, w, -3.0)
    t = tally(sample)
    wide = t.groupBy("feature").agg(*[F.sum(F.when(F.col("toxic") == y, F.col(c)).otherwise(0)).alias(f"{c}{int(y == 1)}") for y in (1, 0) for c in ("once", "twice", "thrice")])

    def z(c):
        p1, p0 = F.col(f"{c}1") / n1, F.col(f"{c}0") / n0
        p = (F.col(f"{c}1") + F.col(f"{c}0") + 1) / (n1 + n0)
        return F.when(p1 >= 2 * p0, (p1 - p0) / F.sqrt(p * (1 - F.least(p, F.lit(0.999))) * (1 / n1 + 1 / n0))).otherwise(0.0)

    score = wide.withColumn("best", F.greatest(*[F.struct(z(c).alias("z"), F.lit(k).alias("least")) for k, c in enumerate(("once", "twice", "thrice"), 1)]))
    seen = F.when(F.col("best.least") == 1, F.col("once1")).when(F.col("best.least") == 2, F.col("twice1")).otherwise(F.col("thrice1"))
    good = score.where((F.col("best.z") >= apart) & (seen >= F.greatest(F.lit(3.0), F.lit(0.03 * n1))))
    # a word and its beginnings often speak on the same texts: the shortest stands for those that count alike
    alike = good.groupBy("once1", "once0", "twice1", "twice0", "thrice1", "thrice0").agg(F.min(F.struct(F.length("feature").alias("n"), "feature", "best")).alias("x"))
    mined = alike.select("x.feature", "x.best").orderBy(F.desc("best.z"), "feature").limit(most).select("feature", "best.least").collect()
    picked = {r[0]: r[1] for r in mined}
    for w in LEXICON:
        picked.setdefault(w, 1)
    voters, least = [*picked, *extra], [*picked.values(), *([1] * len(extra))]
    free = docs.join(F.broadcast(unlabelled(docs, labels, bound)), "doc_id", "left_semi").select("doc_id", "text")
    got = votes(sample.select("doc_id", "text").union(free), voters).join(F.broadcast(some), "doc_id", "left").toPandas().drop_duplicates("doc_id").sort_values("doc_id")
    count = np.zeros((len(got), len(voters)), np.uint8)
    for i, (at, n) in enumerate(zip(got["at"], got["n"], strict=True)):
        count[i, np.asarray(at, int)] = n
    y, words = got["toxic"].to_numpy(float), got["words"].to_numpy(float)
    prior = float(np.clip(np.nanmean(y), 0.01, 0.5))
    fired, given = count >= np.asarray(least), ~np.isnan(y)
    _, first = label_model(fired[given], prior, y[given], y[given])
    q, model = label_model(fired, prior, first.posterior(fired), y)
    w = linear(shaped(count, np.asarray(least), words), q, 0.3)
    return Model(voters, least, model, w[:-1], float(w[-1]))


def score(docs: DataFrame, model: Model, cut: float = 0.7) -> DataFrame:
    """(doc_id, held_out, score, predicted, n_votes) for every row. Null and empty texts get the score of a text without votes."""
    voters, least = model.lookup(), model.least
    k = len(model.voters)
    gain = [[0.0] + [(model.weights[j] + model.weights[k + j] * min(n - least[j] + 1, 4) / 4.0) if n >= least[j] else 0.0 for n in range(1, CAP + 1)] for j in range(k)]
    words, bias, by_size = k - len(PATTERNS), model.bias, float(model.weights[2 * k])

    def begin():
        memo = VoteMemo(voters)

        def each(cols):
            out, n = [], []
            for t in cols["text"]:
                c, size = votes_of(t, memo)
                zz = bias + by_size * math.log1p(size) / 4.0 + sum(gain[j][min(CAP, m)] for j, m in c.items()) + sum(gain[words + j][m] for j, m in enumerate(pattern_votes(t)))
                out.append(1 / (1 + math.exp(-max(-30.0, min(30.0, zz)))))
                n.append(sum(m >= least[j] for j, m in c.items()))
            return {"doc_id": cols["doc_id"], "score": out, "n_votes": n}

        return each

    s = map_rows(texts(docs), begin, struct(doc_id=LONG, score=DBL, n_votes=LONG))
    return s.select("doc_id", held_out(3, 1).alias("held_out"), "score", (F.col("score") >= cut).cast("int").alias("predicted"), "n_votes")
