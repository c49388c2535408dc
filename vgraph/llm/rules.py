"""Quality rules: an ordered decision list learned by sequential covering.

Statistics of each whole text feed threshold conjunctions that are grown on one part of the labelled
rows (best information gain), pruned on the other, and emitted as ordered Spark conditional
expressions. The first rule that holds decides; a text that no rule names is kept.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import LONG, SLICE, WORD, light, texts, unused

SYMBOLS = "#*$%&|<>"
WINDOW = 5
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
EXTRA = ("n_lines", "n_upper_words", "n_bang", "n_distinct_words", "n_digit_words")
#: What the rules may test: name -> (statistic, statistic that it is divided by).
FEATURES = {
    "n_words": ("n_words", None),
    "mean_word": ("word_chars", "n_words"),
    "symbols_per_word": ("n_symbols", "n_words"),
    "dup_line_share": ("n_dup_lines", "n_lines"),
    "repeat_share": ("n_repeat_words", "n_words"),
    "upper_share": ("n_upper_words", "n_words"),
    "bang_share": ("n_bang", "n_words"),
    "distinct_share": ("n_distinct_words", "n_words"),
    "digit_share": ("n_digit_words", "n_words"),
}
STATS = T.StructType([T.StructField(n, LONG) for n in (*BASE, *EXTRA)])


def feature(name: str, get: Callable[[str], Column] = F.col) -> Column:
    """A feature as an expression over the statistics that ``get`` finds by name."""
    part, whole = FEATURES[name]
    return get(part).cast("double") if whole is None else get(part) / F.greatest(get(whole), F.lit(1))


def repeated_words(words: list[str], k: int = WINDOW) -> int:
    """Words inside k-word windows that occur at least twice in the text, each word position once."""
    if len(words) <= k:
        return 0
    grams = list(zip(*(words[j:] for j in range(k)), strict=False))
    count = Counter(grams)
    if len(count) == len(grams):
        return 0
    hit = np.fromiter((count[g] > 1 for g in grams), np.int32, len(grams))
    edge = np.zeros(len(words) + 1, np.int32)
    edge[: len(grams)] += hit
    edge[k : k + len(grams)] -= hit
    return int((np.cumsum(edge)[:-1] > 0).sum())


def duplicate_lines(text: str) -> int:
    if "\n" not in text:
        return 0
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(lines) - len(set(lines))


def statistics_of(text: str) -> tuple[int, ...]:
    words = WORD.findall(text)
    return (
        len(words), sum(map(len, words)), sum(map(text.count, SYMBOLS)), duplicate_lines(text), repeated_words(words),
        text.count("\n") + 1, sum(map(str.isupper, words)), text.count("!"), len(set(words)), sum(map(str.isdigit, words)),
    )


@F.arrow_udf(STATS)
def measured(text: pa.Array) -> pa.Array:
    """All statistics of each text; null counts as empty. Only the text travels to Python."""
    found = []
    for at in range(0, len(text), SLICE):  # bounds the Python strings alive at once
        found += [statistics_of(t or "") for t in text.slice(at, SLICE).to_pylist()]
    cols = [pa.array([x[j] for x in found], pa.int64()) for j in range(len(STATS))]
    return pa.StructArray.from_arrays(cols, names=STATS.names)


#: Made once a row where it stands: the optimiser neither repeats it for each column that a rule reads nor moves it below a join.
measured = measured.asNondeterministic()


def statistics(docs: DataFrame) -> DataFrame:
    """(doc_id, the base and extra statistics) of every row; a null text counts as empty."""
    light(docs.sparkSession)
    return texts(docs).select("doc_id", measured("text").alias("found")).select("doc_id", "found.*")


def base_failed(get: Callable[[str], Column] = F.col) -> Column:
    return (get("n_words") < 10) | (100 * get("n_repeat_words") > 20 * get("n_words"))


@dataclass
class Rule:
    """A conjunction of (feature, '<=' or '>', threshold); texts that satisfy all of it are rejected."""

    tests: list[tuple[str, str, float]] = field(default_factory=list)
    precision: float = 0.0
    covered: int = 0

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        out = np.ones(len(next(iter(x.values()))), bool)
        for name, sign, cut in self.tests:
            out &= (x[name] <= cut) if sign == "<=" else (x[name] > cut)
        return out

    def condition(self, get: Callable[[str], Column] = F.col) -> Column:
        out = F.lit(True)
        for name, sign, cut in self.tests:
            value = feature(name, get)
            out = out & ((value <= cut) if sign == "<=" else (value > cut))
        return out

    def __str__(self):
        return " and ".join(f"{n} {s} {c:.6g}" for n, s, c in self.tests) or "true"


@dataclass
class DecisionList:
    rules: list[Rule] = field(default_factory=list)

    def rejects(self, get: Callable[[str], Column] = F.col) -> Column:
        """Ordered conditional expression: number of the first rule that holds, null for none."""
        out = F.lit(None).cast("int")
        for i, r in reversed(list(enumerate(self.rules))):
            out = F.when(r.condition(get), F.lit(i)).otherwise(out)
        return out

    def keeps(self, get: Callable[[str], Column] = F.col) -> Column:
        """The verdict: neither the base rule nor any learned one speaks against the text."""
        return ~base_failed(get) & self.rejects(get).isNull()

    def describe(self) -> list[str]:
        return [f"reject if {r}  (precision {r.precision:.3f}, covers {r.covered})" for r in self.rules]


def _grow(x, bad, most: int, cuts: int) -> Rule:
    rule, live = Rule(), np.ones(len(bad), bool)
    for _ in range(most):
        p0, n0 = int(bad[live].sum()), int((~bad[live]).sum())
        if not p0 or not n0:
            break
        base, best = math.log2(p0 / (p0 + n0)), (1e-9, None, None)
        for name, v in x.items():
            at = np.unique(np.quantile(v[live], np.linspace(0, 1, cuts)))
            at = (at[1:] + at[:-1]) / 2
            order = np.argsort(v[live], kind="stable")
            vs, bs = v[live][order], np.concatenate([[0], np.cumsum(bad[live][order])])
            k = np.searchsorted(vs, at, "right")
            for sign, p, n in (("<=", bs[k], k - bs[k]), (">", p0 - bs[k], (len(vs) - k) - (p0 - bs[k]))):
                with np.errstate(divide="ignore", invalid="ignore"):
                    gain = np.where(p > 0, p * (np.log2(p / (p + n)) - base), -1.0)
                if len(gain) and gain.max() > best[0]:
                    j = int(gain.argmax())
                    best = (float(gain[j]), (name, sign, float(at[j])), None)
        if best[1] is None:
            break
        rule.tests.append(best[1])
        live = rule.holds(x)
    return rule


def _worth(rule: Rule, x, bad) -> float:
    hit = rule.holds(x)
    p, n = int(bad[hit].sum()), int((~bad[hit]).sum())
    return (p - n) / (p + n) if p + n else -1.0


def learn(x: dict[str, np.ndarray], bad: np.ndarray, precision: float = 0.9, support: int = 4, most_rules: int = 24, most_tests: int = 4, cuts: int = 64) -> DecisionList:
    """Sequential covering. Two thirds of the rows grow a rule, one third prunes it; a rule is taken while its
    precision over all remaining rows reaches ``precision`` with ``support`` rejected rows."""
    out = DecisionList()
    if not len(bad) or not bad.any() or bad.all():
        return out
    grow = np.arange(len(bad)) % 3 != 2
    left = np.ones(len(bad), bool)
    for _ in range(most_rules):
        g, p = left & grow, left & ~grow
        if not bad[g].any():
            break
        rule = _grow({k: v[g] for k, v in x.items()}, bad[g], most_tests, cuts)
        if not rule.tests:
            break
        xp, bp = {k: v[p] for k, v in x.items()}, bad[p]
        while len(rule.tests) > 1 and len(bp):
            shorter = [Rule(rule.tests[:i] + rule.tests[i + 1 :]) for i in range(len(rule.tests))]
            best = max(shorter, key=lambda r: _worth(r, xp, bp))
            if _worth(best, xp, bp) < _worth(rule, xp, bp):
                break
            rule = best
        hit = rule.holds(x) & left
        good, n = int(bad[hit].sum()), int(hit.sum())
        if good < support or good < precision * n:
            break
        rule.precision, rule.covered = good / n, n
        out.rules.append(rule)
        left &= ~hit
    return out


def fit(docs: DataFrame, labels: DataFrame, bound: int = 20_000, **settings) -> DecisionList:
    """Learn from at most ``bound`` labelled rows (those of the smallest hashed ids); only their statistics reach the driver.

    Rows with a null id or label are no labels; of an id's several labels the lowest counts."""
    known = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("quality"))
    some = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    picked = docs.select("doc_id", "text").join(F.broadcast(some.select("doc_id")), "doc_id", "left_semi")
    stats = statistics(picked).join(F.broadcast(some), "doc_id")
    rows = stats.where(~base_failed()).select("doc_id", "quality", *[feature(n).alias(n) for n in FEATURES]).toPandas().drop_duplicates("doc_id").sort_values("doc_id")
    x = {n: rows[n].to_numpy(np.float64) for n in FEATURES}
    return learn(x, rows["quality"].to_numpy() == 0, **settings)


def judge(docs: DataFrame, rules: DecisionList) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, rule) for every row.

    A null or empty text has no words and fails the base rule; repeated rows are judged each."""
    out = statistics(docs)
    return out.select("doc_id", *BASE, base_failed().alias("base_failed"), rules.keeps().alias("kept"), rules.rejects().alias("rule"))


def keep_good(docs: DataFrame, rules: DecisionList) -> DataFrame:
    """The rows of ``docs`` that the list keeps, all columns as they are (extra ones of any name too), by the verdict of ``judge``.

    It is made beside the row's own text in one pass over the rows, without a join."""
    light(docs.sparkSession)
    (found,) = unused(docs.columns, "found")
    judged = docs.withColumn(found, measured("text"))
    return judged.where(rules.keeps(lambda n: F.col(found)[n])).select(*[F.col(f"`{n}`") for n in docs.columns])
