"""Personal data: fixed base patterns plus bootstrapped contextual extraction.

Seed entities (base matches and long hexadecimal strings) induce lexical patterns: the two tokens and
the opening mark before an identifier-like string. Patterns and instances form a bipartite graph that
Spark scores in rounds: a pattern is as good as the trusted share of its distinct instances,
an instance as good as its patterns together. Patterns that stay above a confidence find identifiers
of shapes that no base pattern names.
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import LONG, STR, cleared, light, map_rows, stored, struct, texts, unused

KINDS = ("email", "ip", "card", "phone", "id")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a start inside a run of digits fails or succeeds as the run's first digit does, so only run starts are tried
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
NOT_DIGIT = re.compile(r"[^0-9]")
#: Identifier-like: eight or more of these with a digit among them.
CANDIDATE = re.compile(r"(?<![A-Za-z0-9_])(?=[A-Za-z_-]*+[0-9])[A-Za-z0-9_-]{8,}+")
SEED_HEX = re.compile(r"[0-9a-f]{32,}")
MARKS = "\"'`([{<=:#"


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int, int]]:
    """Leftmost non-overlapping matches, found from the at signs: linear in the text, however long a run is."""
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        m = DOMAIN.match(text, at + 1)
        if m and at > floor:
            s = at
            while s > floor and text[s - 1] in LOCAL:
                s -= 1
            if s < at:
                out.append((s, 0, m.end()))
                floor = m.end()
        at = text.find("@", max(at + 1, floor))
    return out


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of all base matches, sorted."""
    out = emails(text) if "@" in text else []
    if "." in text:
        for m in IP.finditer(text):
            if all(len(p) < 4 and int(p) <= 255 for p in (x.lstrip("0") or "0" for x in m[0].split("."))):
                out.append((m.start(), 1, m.end()))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 14:
            d = NOT_DIGIT.sub("", m[0])
            if 14 <= len(d) <= 19 and luhn(d):
                out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= len(NOT_DIGIT.sub("", m[0])) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


def shown(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in sorted(spans))


def context(text: str, start: int) -> str | None:
    """The pattern before a position: two tokens (digits folded) and the opening mark, or None without them."""
    left = text[max(0, start - 64) : start]
    mark = ""
    if left and left[-1] in MARKS:
        mark, left = left[-1], left[:-1]
    tokens = left.split()[-2:]
    if len(tokens) < 2 or max(map(len, tokens)) > 32:
        return None
    return f"{' '.join(re.sub('[0-9]+', '0', t.lower()) for t in tokens)} {mark}"


SPAN = T.ArrayType(T.StructType([T.StructField("start", LONG), T.StructField("kind", T.IntegerType()), T.StructField("end", LONG)]))
CAND = T.ArrayType(T.StructType([T.StructField("start", LONG), T.StructField("end", LONG), T.StructField("pattern", STR), T.StructField("instance", STR), T.StructField("seed", T.BooleanType()), T.StructField("base", T.BooleanType())]))


def candidates(text: str, base: list[tuple[int, int, int]]) -> list[dict]:
    """Identifier-like strings with a pattern before them, and the base matches, which are all seeds."""
    out = []
    for s, _, e in base:
        if p := context(text, s):
            out.append({"start": s, "end": e, "pattern": p, "instance": text[s:e] if e - s <= 64 else hashlib.md5(text[s:e].encode("utf-8", "surrogatepass")).hexdigest(), "seed": True, "base": True})
    for m in CANDIDATE.finditer(text):
        s, e = m.span()
        if not any(a < e and s < b for a, _, b in base) and (p := context(text, s)):
            out.append({"start": s, "end": e, "pattern": p, "instance": hashlib.md5(m[0].encode()).hexdigest() if e - s > 64 else m[0], "seed": bool(SEED_HEX.fullmatch(m[0])), "base": False})
    return out


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, base spans, candidates) of every row in one pass over the texts."""

    def begin():
        def each(cols):
            base = [base_spans(t) for t in cols["text"]]
            return {"doc_id": cols["doc_id"], "base": [[{"start": s, "kind": k, "end": e} for s, k, e in b] for b in base], "cand": [candidates(t, b) for t, b in zip(cols["text"], base, strict=True)]}

        return each

    return map_rows(texts(docs), begin, struct(doc_id=LONG, base=SPAN, cand=CAND))


def patterns(found: DataFrame, rounds: int = 2, confidence: float = 0.9, support: int = 5) -> DataFrame:
    """(pattern, score): iterative scoring of the pattern-instance graph of ``found`` (a table of ``scan``).

    A pattern needs ``support`` distinct trusted instances; patterns of a text's chance neighbourhood have fewer."""
    edges = stored(found.select(F.explode("cand").alias("c")).groupBy("c.pattern", "c.instance").agg(F.max("c.seed").alias("seed")))
    trust = edges.groupBy("instance").agg(F.max(F.col("seed").cast("double")).alias("trust"))
    scores = None
    for _ in range(rounds):
        scores = edges.join(trust, "instance").groupBy("pattern").agg(F.avg("trust").alias("score"), F.sum(F.when(F.col("trust") >= 0.5, 1).otherwise(0)).alias("n"))
        scores = stored(scores.where((F.col("n") >= support) & (F.col("score") >= 0.5)).select("pattern", F.col("score")))
        # an instance is doubted by each of its good patterns independently; seeds keep full trust
        heard = edges.join(scores, "pattern", "left").groupBy("instance").agg(F.max(F.col("seed").cast("double")).alias("s"), F.sum(F.log(F.greatest(F.lit(1e-6), 1 - F.coalesce("score", F.lit(0.0))))).alias("doubt"))
        trust = stored(heard.select("instance", F.when(F.col("s") > 0, 1.0).otherwise(1 - F.exp("doubt")).alias("trust")))
    return scores.where(F.col("score") >= confidence)


@cleared
def extract(docs: DataFrame, rounds: int = 2, confidence: float = 0.9, support: int = 5) -> DataFrame:
    """(doc_id, base, extra) for every row: base spans and those that patterns add, arrays of (start, kind, end).

    Null texts are empty; rows with a null id get no added spans; rows that repeat an id get the added spans of
    that id's rows together, so ids should name one text."""
    found = stored(scan(docs))
    good = patterns(found, rounds, confidence, support)
    hits = found.where("doc_id is not null").select("doc_id", F.explode("cand").alias("c")).where("not c.base")
    extra = hits.select("doc_id", F.col("c.pattern").alias("pattern"), F.col("c.start").alias("start"), F.col("c.end").alias("end")).join(good, "pattern", "left_semi")
    per = extra.groupBy("doc_id").agg(F.collect_set(F.struct("start", F.lit(KINDS.index("id")).alias("kind"), "end")).alias("extra"))
    return found.select("doc_id", "base").join(per, "doc_id", "left").select("doc_id", "base", F.coalesce("extra", F.array().cast(SPAN)).alias("extra"))


def digest(spans: DataFrame) -> DataFrame:
    """The contract's columns from ``extract``: counts of base spans, a hash of them and all spans."""

    def text(c):
        sort = F.array_sort(c)
        return F.array_join(F.transform(sort, lambda x: F.concat_ws(":", F.element_at(F.array(*map(F.lit, KINDS)), x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")

    # candidates never touch a base span of their own row, and base spans are no candidates
    def count(k):
        return F.size(F.filter("base", lambda x: x["kind"] == k)).cast("long").alias(f"n_{KINDS[k]}")

    n = [count(k) for k in range(4)]
    return spans.select("doc_id", *n, F.sha2(text(F.col("base")), 256).alias("base_sha256"), text(F.concat("base", "extra")).alias("spans"), F.size("extra").cast("long").alias("n_added"))


def redact(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` with every span of a text replaced by its kind in brackets; other columns as they are, n_chars (where it
    is a column) as the new length. Base spans are found in the row's own text, so rows with a null id lose them too;
    added spans come by id. Null texts stay null."""
    light(docs.sparkSession)
    key, more, new_text = unused(docs.columns, "key", "extra", "new_text")
    extra = extract(docs.where("doc_id is not null"), **settings).where(F.size("extra") > 0)
    flat = extra.groupBy(F.col("doc_id").alias(key)).agg(F.flatten(F.collect_set("extra")).alias(more))
    out = docs.join(flat, docs["doc_id"] == flat[key], "left").withColumn(new_text, masked(F.col("text"), F.col(more)))
    new = {"text": F.col(new_text)}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col(new_text).eqNullSafe(F.col("text")), F.col("n_chars")).otherwise(F.length(new_text).cast(docs.schema["n_chars"].dataType))
    return out.select(*[new.get(n, F.col(f"`{n}`")).alias(n) for n in docs.columns])


def mask(text: str, extra=()) -> str:
    """The text with each base span and each of ``extra`` replaced by its kind; overlapping spans share one mark."""
    spans = base_spans(text) + [(int(x["start"]), int(x["kind"]), int(x["end"])) for x in extra]
    if not spans:
        return text
    parts, at, end = [], 0, 0
    for s, k, e in sorted(spans):
        if s >= end:
            parts += [text[at:s], f"[{KINDS[k].upper()}]"]
        end = max(end, e)
        at = end
    return "".join(parts) + text[at:]


@F.pandas_udf(STR)
def masked(text, extra):
    import pandas as pd

    return pd.Series([None if t is None else mask(t, () if x is None else x) for t, x in zip(text, extra, strict=True)], dtype=object)
