"""The other text operators: brute force, round trips, held-out accuracy, and odd rows."""

import random
import zlib
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from same import rows, twin

from vgraph.llm import decontam, id_store, lang_id, passages, piece_codec, pii, queries, rules, toxicity, url_filter, url_list
from vgraph.llm.common import WORD, Memo, hashed_words

ODD = [(1, None), (2, ""), (3, "   \n\t "), (4, "word " * 3000), (5, "x" * 5000), (6, "x" * 5000), (6, "x" * 5000), (7, "naïve café 中文 🎉́ \x00"), (None, "no id here")]
SCHEMA = "doc_id long, text string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeated rows, and extra columns whose names operators use inside."""
    return spark.createDataFrame([(*r, 1, "s", 2.0) for r in ODD], SCHEMA + ", n_words int, seeds string, score double")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 0, 1), (2, 1, 0), (None, 0, 1), (5, None, None), (5, 1, 0)], "doc_id long, quality int, toxic int")


def table(spark, sf, n):
    return spark.read.parquet(f"{sf}/{n}.parquet")


# -- op1 ---------------------------------------------------------------------------------------------
@pytest.fixture(scope="module")
def library():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=piece_codec.model_path()), piece_codec.Codec(piece_codec.model_path(), memo=500)


def ids_of(codec, text):
    return np.frombuffer(codec.encode(text), "<u4").tolist()


@given(st.text(alphabet=st.one_of(st.sampled_from("  \n\tabcdethe and of ing€中文éß\x00🎉.,;!?12==//__²"), st.characters(exclude_categories=["Cs"])), max_size=80))
@settings(max_examples=300, deadline=None)
def test_pieces_are_the_librarys(library, text):
    if "▁" in text:
        return
    lib, own = library
    assert ids_of(own, text) == lib.encode(text)
    assert own.decode(ids_of(own, text)) == text


def test_streaming_window_equals_library_on_long_runs(library):
    lib, own = library
    for text in ("abcdefgh" * 3000, " " * 777 + "end", "ab" * 999 + "中" * 50 + " " * 40 + "the" * 500):
        assert ids_of(own, text) == lib.encode(text)
        assert "".join(own.lattice("▁" + text.replace(" ", "▁"))) == "▁" + text.replace(" ", "▁")


def test_every_text_is_streamed_in_a_bounded_window():
    """Without a memo the lattice walks every character; its window stays a few pieces long on a million and a half characters without a space."""
    own = piece_codec.Codec(piece_codec.model_path(), memo=0)
    r = random.Random(3)
    texts = [" ".join(r.choice(["the", "of", "a", "stream", "zq"]) for _ in range(50)) for _ in range(20)]
    for t in texts:
        own.encode(t)
    assert own.streamed == sum(len(t) + 1 for t in texts) and own.commits >= own.streamed / 32
    own.streamed, own.commits = 0, 0
    long = "".join(r.choice("etaoinshrdlu") for _ in range(1_500_000))
    assert own.decode(ids_of(own, long)) == long
    assert own.streamed == len(long) + 1 and own.commits > len(long) / 100 and own.widest < 1000


def test_emptied_memo_changes_nothing(library):
    lib, own = library  # a memo of 500
    r = random.Random(7)
    words = ["".join(r.choice("etaoinshrdlucm") for _ in range(r.randint(1, 9))) for _ in range(6000)]
    for i in range(0, 6000, 300):
        t = " ".join(["the common words of every text", *words[i : i + 300]])
        assert ids_of(own, t) == lib.encode(t)


def test_score_objective_against_whole_lattice(library):
    own = piece_codec.Codec(piece_codec.model_path(), kind="score")
    r = random.Random(2)
    for _ in range(60):
        t = "".join(r.choice("▁theandofing") for _ in range(r.randint(1, 120)))
        best = [0.0]
        for i in range(1, len(t) + 1):
            best.append(max(best[s] + own.score.get(t[s:i], own.unknown if i - s == 1 else -1e18) for s in range(max(0, i - own.longest), i)))
        got = list(own.lattice(t, every=16))
        assert "".join(got) == t
        assert abs(sum(own.score.get(p, own.unknown) for p in got) - best[-1]) <= 1e-6 * max(1, abs(best[-1]))


def test_codec_frames(spark, odd):
    d = odd.where("doc_id is not null")
    coded = piece_codec.encode(d)
    back = {(r.doc_id, r.text) for r in piece_codec.decode(coded).collect()}
    assert back == {(i, t or "") for i, t in ODD if i is not None}
    dig = piece_codec.encode_digest(odd).collect()
    assert len(dig) == len(ODD) and all(r.round_trip for r in dig)


# -- op2 and op5: held-out accuracy --------------------------------------------------------------------
def test_toxicity_learns_and_spares(spark):
    """Made-up texts of two classes; labels of held-out rows are never read."""
    r = random.Random(1)
    word = lambda: "".join(r.choice(["ta", "ko", "mi", "re", "su"]) for _ in range(3))
    docs, labs = [], []
    for i in range(600):
        bad = i % 5 == 0
        t = [word() for _ in range(40)]
        if bad:
            for _ in range(4):
                t[r.randrange(40)] = r.choice(["zugro", "zugrot", "zugrin", "moron", "scum"])
        docs.append((i, " ".join(t)))
        labs.append((i, 1, int(bad)))
    d, lb = spark.createDataFrame(docs, SCHEMA), spark.createDataFrame(labs, "doc_id long, quality int, toxic int")
    s = toxicity.score(d, toxicity.fit(d, lb)).join(lb, "doc_id").where("held_out").collect()
    assert len(s) > 100
    assert all((zlib.crc32(str(x.doc_id).encode()) % 3 == 1) == x.held_out and 0 <= x.score <= 1 and x.predicted == int(x.score >= 0.7) for x in s)
    assert np.mean([x.predicted for x in s if x.toxic]) > 0.9 and np.mean([x.predicted for x in s if not x.toxic]) < 0.02
    flipped = lb.withColumn("toxic", F.when(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    assert toxicity.fit(d, flipped).voters == toxicity.fit(d, lb).voters


def test_label_posterior_is_the_enumerated_one():
    """Against plain Python over every vote pattern: a pattern's joint chance with either class, parents and components included."""
    r = np.random.default_rng(4)
    kind, share, parent = np.array([0, 0, 1, 1]), np.array([0.5, 0.2, 0.2, 0.1]), np.array([-1, 0, 0, -1, 3])
    m = toxicity.LabelModel(kind, share, parent, r.uniform(0.05, 0.9, (4, 2, 5)))
    patterns = [[(i >> j) & 1 for j in range(5)] for i in range(32)]
    want, total = [], 0.0
    for f in patterns:
        joint = [0.0, 0.0]
        for c in range(4):
            p = share[c]
            for j in range(5):
                led = parent[j] >= 0 and f[parent[j]]
                p *= m.rate[c, int(led), j] if f[j] else 1 - m.rate[c, int(led), j]
            joint[kind[c]] += p
        want.append(joint[1] / sum(joint))
        total += sum(joint)
    assert abs(total - 1) < 1e-9 and np.abs(m.posterior(np.array(patterns)) - want).max() < 1e-9


def test_label_model_counts_silence_and_finds_correlation():
    r = np.random.default_rng(1)
    y = r.random(2000) < 0.3
    f = np.where(y[:, None], r.random((2000, 12)) < 0.6, r.random((2000, 12)) < 0.05)
    lr = np.log(0.3 / 0.7) + np.where(f, np.log(0.6 / 0.05), np.log(0.4 / 0.95)).sum(1)
    exact = 1 / (1 + np.exp(-lr))
    for start in (y.astype(float), np.where(f.sum(1) > 2, 0.8, 0.2)):  # from labels, and from a vote count without any
        q, m = toxicity.label_model(f, 0.3, start, kinds=1)
        assert ((q > 0.5) == y).mean() > 0.98 and np.abs(q - exact).mean() < 0.01
        assert (m.parent >= 0).sum() == 0 and (m.accuracy() > 0.8).all()
    twice = np.hstack([f, f[:, :3], f[:, :3] ^ (r.random((2000, 3)) < 0.02)])  # voters that repeat others
    q, m = toxicity.label_model(twice, 0.3, y.astype(float), kinds=1)
    assert (m.parent >= 0).sum() == 6 and np.abs(q - exact).mean() < 0.01
    _, many = toxicity.label_model(f, 0.3, y.astype(float))
    assert ((many.posterior(f) > 0.5) == y).mean() > 0.98


def test_own_label_moves_no_posterior():
    """A row's returned posterior is that of its votes, whatever its label says."""
    r = np.random.default_rng(2)
    y = (r.random(1500) < 0.4).astype(float)
    f = np.where(y[:, None] == 1, r.random((1500, 8)) < 0.6, r.random((1500, 8)) < 0.1)
    known = y.copy()
    known[500:] = np.nan
    q, m = toxicity.label_model(f, 0.4, np.full(1500, 0.4), known)
    again = m.posterior(f)
    same = {}
    for row, p in zip(map(tuple, f.tolist()), again.tolist(), strict=True):
        assert abs(same.setdefault(row, p) - p) < 1e-9
    assert np.abs(q - again).max() < 1e-6


def test_toxicity_score_in_plain_python(spark):
    import math

    voters, least = ["badd*", "scum", *toxicity.PATTERNS], [2, 1, 1, 1, 1]
    k = len(voters)
    m = toxicity.Model(voters, least, None, np.arange(1, 2 * k + 2) / 7.0, -2.0)
    texts_ = ["", None, "scum scum", "baddly baddest badder", "AAAA!! BBBB!! you are a scum", "you're such f**k " * 9]
    for row in toxicity.score(spark.createDataFrame(list(enumerate(texts_)), SCHEMA), m).collect():
        t = texts_[row.doc_id] or ""
        words = set(toxicity.TOKEN.findall(t.lower()))
        count = [sum(len(w) > 4 and w[:4] == "badd" for w in words), int("scum" in words), *toxicity.pattern_votes(t)]
        over = [max(min(c, toxicity.CAP) - l + 1, 0) for c, l in zip(count, least, strict=True)]
        z = -2.0 + sum(m.weights[j] * (o > 0) + m.weights[k + j] * min(o, 4) / 4 for j, o in enumerate(over)) + m.weights[2 * k] * math.log1p(len(words)) / 4
        assert abs(row.score - 1 / (1 + math.exp(-z))) < 1e-9


def test_language_held_out(spark, sf):
    d = table(spark, sf, "documents")
    p = lang_id.predict(d, lang_id.fit(d)).join(d, "doc_id").where("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in p]) > 0.95
    assert all((zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in p)


def test_language_memo_bound_changes_nothing(spark):
    """Common words come back in every slice of one task, whose distinct words exceed the bound many times over."""
    docs = [(i, f"the common words of every text and t{'abcdefghij'[i % 10]}{'klmnopqrst'[i // 10 % 10]}{'uvwxyz'[i // 100]} here", "en" if i % 2 else "fr") for i in range(600)]
    d = spark.createDataFrame(docs, SCHEMA + ", lang string").coalesce(1)
    f = lang_id.fit(d)
    rows_of = lambda most: sorted((r.doc_id, r.lang_pred, r.score) for r in lang_id.predict(d, f, most).collect())
    assert len(rows_of(50)) == 600 and rows_of(50) == rows_of(300_000)


def test_filters_against_exact_sets(spark, sf):
    """Plain Python: every n-gram of a language's exact set is found, others about as often as the filter says, and corrected counts name
    the language that exact counts name."""
    from collections import Counter

    d = table(spark, sf, "documents")
    f = lang_id.fit(d)
    rows_ = [r for r in d.select("doc_id", "text", "lang").collect() if r.text and r.lang]
    count = {x: Counter() for x in f.langs}
    for r in rows_:
        if zlib.crc32(str(r.doc_id).encode()) % 4 != 2:
            for w in lang_id.LETTERS.findall(r.text.lower()):
                count[r.lang].update(lang_id.grams(w))
    exact = {x: {g for g, n in c.items() if n >= max(2.0, 3e-5 * sum(c.values()))} for x, c in count.items()}
    for k, x in enumerate(f.langs):
        own = sorted(exact[x])
        assert ((f.masks(lang_id.hashed(own)) >> np.uint64(k)) & np.uint64(1)).all()
        rest = [f"{i:06d}" for i in range(20_000)]
        rate = ((f.masks(lang_id.hashed(rest)) >> np.uint64(k)) & np.uint64(1)).mean()
        assert abs(rate - f.false[k]) < 0.01
    got = {r.doc_id: r.lang_pred for r in lang_id.predict(d, f).collect()}
    same = []
    for r in rows_:
        words = set(lang_id.LETTERS.findall(r.text.lower()))
        if words:
            grams_ = [g for w in words for g in lang_id.grams(w)]
            best = {x: sum(g in exact[x] for g in grams_) for x in f.langs}
            same.append(got[r.doc_id] == max(sorted(best), key=lambda x: best[x]))
    assert np.mean(same) > 0.99


def test_bloom_false_positive_correction():
    f = lang_id.Filters(["a", "b"], np.zeros(64, np.uint64), np.array([0.1, 0.0]))
    assert (f.masks(lang_id.hashed(["xy", "z"])) == 0).all()


# -- op3 ---------------------------------------------------------------------------------------------
def test_statistics_against_plain_counting():
    r = random.Random(5)
    for _ in range(200):
        t = "".join(r.choice(["a ", "b ", "c\n", "# ", "a b c d e ", "\n"]) for _ in range(r.randint(0, 40)))
        w = WORD.findall(t)
        hit = set()
        for i in range(len(w) - 4):
            if sum(w[j : j + 5] == w[i : i + 5] for j in range(len(w) - 4)) > 1:
                hit |= set(range(i, i + 5))
        lines, dup = [], 0
        for x in t.split("\n"):
            if WORD.search(x):
                dup += x in lines
                lines.append(x)
        assert rules.statistics_of(t)[:5] == (len(w), sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), dup, len(hit))


def test_decision_list_and_filter_agree(spark, sf):
    d, lb = table(spark, sf, "documents"), table(spark, sf, "labels")
    for bound in (20_000, 60):
        lst = rules.fit(d, lb, bound)
        kept = {r.doc_id for r in rules.judge(d, lst).where("kept").collect()}
        assert kept == {r.doc_id for r in rules.keep_good(d, lst).collect()}


def test_verdicts_in_plain_python(spark, sf):
    """Every row's base verdict, features and first rule, recomputed from its text."""
    d = table(spark, sf, "documents")
    lst = rules.fit(d, table(spark, sf, "labels"))
    lst.rules.append(rules.Rule([("distinct_share", "<=", 0.4), ("n_words", ">", 40.0)]))
    got = {r.doc_id: r for r in rules.judge(d, lst).collect()}
    for r in d.select("doc_id", "text").collect():
        x = dict(zip((*rules.BASE, *rules.EXTRA), rules.statistics_of(r.text or ""), strict=True))
        failed = x["n_words"] < 10 or 100 * x["n_repeat_words"] > 20 * x["n_words"]
        value = {n: float(x[a]) if b is None else x[a] / max(x[b], 1) for n, (a, b) in rules.FEATURES.items()}
        first = next((i for i, rule in enumerate(lst.rules) if all((value[n] <= c) if s == "<=" else (value[n] > c) for n, s, c in rule.tests)), None)
        y = got[r.doc_id]
        assert (y.base_failed, y.rule, y.kept) == (failed, first, not failed and first is None)


def test_sequential_covering_finds_a_planted_rule():
    r = np.random.default_rng(0)
    x = {n: r.random(900) for n in rules.FEATURES}
    bad = (x["symbols_per_word"] > 0.8) & (x["n_words"] > 0.3)
    lst = rules.learn(x, bad)
    hit = np.zeros(900, bool)
    for rule in lst.rules:
        hit |= rule.holds(x)
    assert (hit == bad).mean() > 0.98
    assert not rules.learn(x, np.zeros(900, bool)).rules


# -- op4, op7: SQL twins -------------------------------------------------------------------------------
@pytest.mark.parametrize("name", ["op4_temporal_url_filter", "op7_spaced_seed_decontamination"])
def test_twins(spark, sf, duck, name):
    assert rows(queries.queries()[name](spark, sf)) == twin(duck, queries.oracle_sql()[name])


def test_url_as_of(spark):
    e = url_list.entries(spark)
    caps = [(1, "http://A.casino-win.example.com:80/x", "2024-05-01"), (2, "https://x.example.net/", "2024-03-01"), (3, "https://x.example.net/", "2024-04-15"), (4, None, "2024-04-15"), (5, "nonsense", "2024-04-15"), (6, "http://example.org", None), (7, "http://tionsh.example.net/fr/1", "2024-03-01"), (7, "http://tionsh.example.net/fr/1", "2024-03-01")]
    c = spark.createDataFrame(caps, "page_id long, url string, at string").select("page_id", "url", F.to_timestamp("at").alias("fetched_at"), F.lit(1).alias("host"))
    got = sorted((r.page_id, r.entry_id, r.kept) for r in url_filter.judge(c, e).collect())
    assert got == [(1, 8, False), (2, 1, False), (3, None, True), (4, None, True), (5, None, True), (6, None, True), (7, 6, False), (7, 6, False)]
    assert url_filter.judge(c.where("false"), e).count() == 0
    assert url_filter.judge(c, e.where("false")).where("not kept").count() == 0


def test_deep_domains_and_long_histories(spark, duck):
    """A host of twelve labels is looked up under all its parents, a history of 300 entries by bisection, as SQL says; both joins agree."""
    deep = "a.b.c.d.e.f.g.h.i.j.example.com"
    rows_ = [(1, "domain", deep, "block", "2024-01-01"), (2, "domain", "d.e.f.g.h.i.j.example.com", "allow", "2024-01-01")]
    rows_ += [(10 + i, "host", "busy.example.org", ("block", "allow", "lift")[i % 3], str(np.datetime64("2024-01-01") + i)) for i in range(300)]
    e = spark.createDataFrame(rows_, "entry_id long, scope string, value string, action string, day string").withColumn("listed_on", F.to_timestamp("day"))
    caps = [(1, f"http://x.{deep}/", "2024-02-01"), (2, "http://z.e.f.g.h.i.j.example.com", "2024-02-01"), (3, f"http://{deep}", "2023-12-31"), (4, "http://" + "l." * 140 + "com", "2024-02-01")]
    caps += [(100 + i, "http://busy.example.org/x", f"{np.datetime64('2023-12-25') + i} 12:00:00") for i in range(320)]
    c = spark.createDataFrame(caps, "page_id long, url string, at string").select("page_id", "url", F.to_timestamp("at").alias("fetched_at"))
    got = sorted((r.page_id, r.entry_id, r.kept) for r in url_filter.judge(c, e).collect())
    want = {1: (1, False), 2: (None, True), 3: (None, True), 4: (None, True)}
    for i in range(320):
        day = i - 7
        on = None if day < 0 else min(day, 299)
        want[100 + i] = (None, True) if on is None or on % 3 == 2 else (10 + on, on % 3 != 0)
    assert got == sorted((i, *x) for i, x in want.items())
    kept, url_filter.BROADCAST_ENTRIES = url_filter.BROADCAST_ENTRIES, 10
    try:
        assert sorted((r.page_id, r.entry_id, r.kept) for r in url_filter.judge(c, e).collect()) == got
    finally:
        url_filter.BROADCAST_ENTRIES = kept


def test_decontamination_tolerates_substitutions(spark):
    r = random.Random(3)
    item = [f"w{r.randrange(10**6)}" for _ in range(30)]
    cut = list(item)
    for i in (4, 11, 12, 25):
        cut[i] = "other"
    bench = spark.createDataFrame([(1, " ".join(item)), (2, "just four short words"), (3, None), (4, "")], "item_id long, text string")
    docs = [(1, "before " + " ".join(item) + " after"), (2, "Before, " + " ".join(cut).upper() + "!"), (3, " ".join(item[:10])), (4, "so Just FOUR, short words."), (5, "clean text"), (6, None), (None, " ".join(item))]
    d = spark.createDataFrame(docs, SCHEMA)
    assert sorted((x.doc_id, x.item_id) for x in decontam.overlaps(d, bench).collect()) == [(1, 1), (2, 1), (4, 2)]
    assert sorted(x.doc_id or -1 for x in decontam.clean(d, bench).collect()) == [-1, 3, 5, 6]


# -- op6 ---------------------------------------------------------------------------------------------
def test_chains_against_quadratic_programme():
    r = random.Random(9)
    for _ in range(60):
        n = r.randint(1, 25)
        a, b = [r.randrange(60) for _ in range(n)], [r.randrange(60) for _ in range(n)]
        best = {}
        for i in sorted(range(n), key=lambda i: (a[i], b[i])):
            best[i] = 6.0
            for j in best:
                if a[j] < a[i] and b[j] < b[i]:
                    v = best[j] - 0.05 * (a[i] + b[i] - a[j] - b[j])
                    if v > 0:
                        best[i] = max(best[i], v + min(6, a[i] - a[j], b[i] - b[j]))
        got = passages.chains(a, b, 6, 0.05)
        assert sorted(i for c in got for i in c) == list(range(n))
        for c in got:
            assert all(a[x] < a[y] and b[x] < b[y] for x, y in zip(c, c[1:], strict=False))


def test_minimizers_guarantee():
    r = np.random.default_rng(1)
    h = r.integers(0, 1 << 62, 400).astype(np.uint64)
    g = np.concatenate([r.integers(0, 1 << 62, 90).astype(np.uint64), h[100:121], r.integers(0, 1 << 62, 90).astype(np.uint64)])
    seeds = lambda x: passages.sketched(x, np.array([0, len(x)]))[2]
    assert {int(i) - 90 for i in seeds(g)} & {int(i) - 100 for i in seeds(h)}


def test_sketch_against_one_text_at_a_time():
    """Texts sketched together have the seeds, positions and contexts that plain loops find in each alone; word hashes tell words apart."""
    r = random.Random(17)
    texts_ = ["", "one", "a b c d e", " lead  and trail \n", "w " * 60, None and "", "é ü\u3000x\x85y"] + [" ".join(r.choice(["aa", "b", "cde", "f" * 50, "é"]) + str(r.randrange(40)) for _ in range(r.randint(1, 90))) for _ in range(40)]
    texts_ = [t or "" for t in texts_]
    each = hashed_words(texts_)
    words = [WORD.findall(t) for t in texts_]
    assert [len(h) for h in each] == [len(w) for w in words]
    seen = {}
    for h, w in zip(each, words, strict=True):
        for x, y in zip(h.tolist(), w, strict=True):
            assert seen.setdefault(x, y) == y
    assert len(seen) == len({y for w in words for y in w})
    bounds = np.concatenate([[0], np.cumsum([len(h) for h in each])])
    cut, seeds, at, ctx = passages.sketched(np.concatenate(each), bounds)
    for i, h in enumerate(each):
        k, w = passages.K, passages.W
        want = set()
        g = passages.keyed(passages.windows(h, k), 99).tolist() if len(h) >= k else []
        for s in range(max(1, len(g) - w + 1) if g else 0):
            part = g[s : s + w]
            want.add(s + part.index(min(part)))
        mine = at[cut[i] : cut[i + 1]].tolist()
        assert mine == sorted(want)
        for p, c in zip(mine, ctx[cut[i] : cut[i + 1]].view(np.uint64).tolist(), strict=True):
            bit = lambda j: int(passages.mix64(h[j : j + 1])[0]) >> 60 if 0 <= j < len(h) else 0  # noqa: B023, E731
            assert c == sum(bit(p - 8 + j) << (4 * j) | bit(p + k + j) << (4 * (8 + j)) for j in range(8))
        alone = passages.sketched(h, np.array([0, len(h)]))[1]
        assert alone.tolist() == seeds[cut[i] : cut[i + 1]].tolist()


def test_only_hopeless_chains_are_spared_their_alignment(monkeypatch):
    spare = passages.hopeless
    monkeypatch.setattr(passages, "hopeless", lambda *_: False)
    r = np.random.default_rng(5)
    spared = 0
    for _ in range(3000):
        n = int(r.integers(40, 160))
        x = r.integers(0, 1 << 40, n).astype(np.uint64)
        y = np.where(r.random(n) < r.choice([0.1, 0.2, 0.3, 0.6]), r.integers(0, 1 << 40, n).astype(np.uint64), x)
        at = int(r.integers(0, n - 5))
        y[at : at + 5] = x[at : at + 5]
        if spare(x, y, [at], [at], 50, 0.8):
            spared += 1
            assert not passages.passages_of(x, y, [at], [at], 5, 50, 0.8)
    assert spared > 500


def test_planted_passages(spark):
    r = random.Random(6)
    word = lambda: f"{r.randrange(10**7):x}"
    fresh = lambda n: [word() for _ in range(n)]
    p, edited = fresh(60), None
    edited = p[:20] + ["changed"] + p[21:40] + ["in", "serted"] + p[40:]
    docs = {1: fresh(80) + p + fresh(80), 2: fresh(30) + p + fresh(10), 3: fresh(5) + edited + fresh(90), 4: fresh(300), 5: fresh(100) + p[:30], 6: p + fresh(3), 7: fresh(70)}
    rows_ = [(i, " ".join(w)) for i, w in docs.items()] + [(8, " ".join(docs[7])), (9, None), (10, ""), (None, " ".join(p))]
    got = passages.repeated(spark.createDataFrame(rows_, SCHEMA)).collect()
    assert {x.doc_id for x in got} | {x.match_doc_id for x in got} == {1, 2, 3, 6, 7, 8}
    exact = next(x for x in got if (x.doc_id, x.match_doc_id) == (2, 1))
    assert (exact.start, exact.end, exact.match_start, exact.match_end) == (30, 90, 80, 140)
    assert all(x.identity >= 0.8 and x.end - x.start >= 50 for x in got)


def test_passages_that_repeat_themselves(spark):
    r = random.Random(12)
    fresh = lambda n: [f"{r.randrange(10**7):x}" for _ in range(n)]
    line, other = fresh(10), fresh(7)
    docs = {1: fresh(40) + ["word"] * 60 + fresh(40), 2: fresh(90) + ["word"] * 80 + fresh(5), 3: fresh(30) + line * 8 + fresh(30), 4: fresh(70) + line * 8 + fresh(9), 5: other + fresh(90) + other * 9 + fresh(8), 6: fresh(3) + other * 10, 7: fresh(60) + line, 8: fresh(30) + ["word"] * 20}
    got = passages.repeated(spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)).collect()
    assert {(x.doc_id, x.match_doc_id) for x in got} == {(2, 1), (4, 3), (6, 5)}
    assert {(x.start, x.end, x.match_start, x.match_end) for x in got if x.doc_id == 4} >= {(70, 150, 30, 110)}


def test_passages_whose_parts_were_held_before(spark):
    """C and D share 70 words; earlier documents hold either half, and others between them hold pieces, so seed links scatter."""
    r = random.Random(21)
    fresh = lambda n: [f"{r.randrange(10**7):x}" for _ in range(n)]
    docs, want = {}, set()
    for g in range(6):
        p, at = fresh(70), 100 * g
        docs |= {at + 1: fresh(20) + p[:36] + fresh(20), at + 2: fresh(9) + p[34:] + fresh(40), at + 3: fresh(50) + p + fresh(20), at + 9: fresh(10) + p + fresh(60)}
        docs |= {at + 4: fresh(30) + p[:30] + fresh(30), at + 5: fresh(30) + p[25:48] + fresh(30), at + 6: fresh(30) + p[45:] + fresh(30)}
        want |= {at + 3, at + 9}
    got = passages.repeated(spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)).collect()
    assert {x.doc_id for x in got} | {x.match_doc_id for x in got} == want
    assert all(x.end - x.start == x.n_same == 70 for x in got)


def test_edited_passages_whose_seeds_all_have_other_holders(spark, monkeypatch):
    """B's edited copy of A's passage: earlier documents, and others between the two, hold every intact piece of it, apart from each other."""
    r = random.Random(44)
    fresh = lambda n: [f"{r.randrange(10**7):x}" for _ in range(n)]
    docs, want = {}, set()
    for g in range(6):
        p, at = fresh(72), 100 * g
        pieces = [p[i : i + 11] for i in range(0, 72, 12)]
        apart = lambda ps=pieces: sum((x + fresh(40) for x in ps), fresh(9))
        q = sum((x + fresh(1) for x in pieces), [])
        docs |= {at: apart(), at + 1: apart(), at + 2: fresh(20) + p + fresh(30), at + 3: apart(), at + 4: apart(), at + 5: fresh(50) + q + fresh(8)}
        want.add((at + 5, at + 2))
    frame = spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)
    assert {(x.doc_id, x.match_doc_id) for x in passages.repeated(frame).collect()} == want
    alike = passages.like_pairs
    monkeypatch.setattr(passages, "like_pairs", lambda *a: alike(*a, hot=2))  # the same when every seed is dealt into parts
    assert {(x.doc_id, x.match_doc_id) for x in passages.repeated(frame).collect()} == want


def test_alike_surroundings():
    r = np.random.default_rng(5)
    h = r.integers(1, 40, 400).astype(np.uint64)
    at = np.sort(r.choice(395, 90, replace=False))
    w = passages.surroundings(h, at, 5, 20)
    near = lambda i, j: max(sum(0 <= i + d < 400 and 0 <= j + d < 400 and w_same(i + d, j + d) for d in range(-s, 25 - s) if not 0 <= d < 5) for s in range(21))
    nibble = (passages.mix64(h) >> np.uint64(40)) % np.uint64(15)
    w_same = lambda a, b: nibble[a] == nibble[b]
    x, y = passages.alike(w, w, 6)
    assert set(zip(x.tolist(), y.tolist(), strict=True)) == {(i, j) for i in range(90) for j in range(90) if near(int(at[i]), int(at[j])) >= 6}


def test_recall_of_edited_passages(spark):
    """Against brute force over every diagonal of every pair: substitutions of a twentieth to a fifth of 55 to 100 words."""
    r = random.Random(33)
    fresh = lambda n: [f"{r.randrange(10**7):x}" for _ in range(n)]
    docs, rate = {}, {}
    for g in range(120):
        p = fresh(r.choice([55, 70, 100]))
        rate[2 * g + 1] = (0.05, 0.1, 0.15, 0.2)[g % 4]
        q = list(p)
        for i in r.sample(range(len(p)), int(rate[2 * g + 1] * len(p))):
            q[i] = fresh(1)[0]
        docs |= {2 * g: fresh(20) + p + fresh(25), 2 * g + 1: fresh(35) + q + fresh(15)}

    def brute(x, y):
        same = np.array(x)[:, None] == np.array(y)[None, :]
        for d in range(49 - len(x), len(y) - 48):
            c = np.concatenate([[0], np.cumsum(np.diagonal(same, d) - 0.8)])
            if any((c[n:] - c[:-n] >= -1e-9).any() for n in range(50, len(c))):
                return True
        return False

    want = {i for i in rate if brute(docs[i - 1], docs[i])}
    got = {x.doc_id for x in passages.repeated(spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)).collect()}
    assert got <= want
    recall = {v: np.mean([i in got for i in want if rate[i] == v]) for v in (0.05, 0.1, 0.15, 0.2)}
    assert min(recall[0.05], recall[0.1]) == 1 and recall[0.15] >= 0.97 and recall[0.2] >= 0.9, recall


def test_families_meet_in_blocks(spark):
    r = np.random.default_rng(8)
    root, docs = [f"r{i}" for i in range(150)], {}
    for i in range(14):  # near copies: every two differ
        w = list(root)
        for p in r.choice(150, 8, replace=False):
            w[p] = f"x{i}_{p}"
        docs[i] = w
    d = spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)
    multi = passages.stored(passages.occurrences(passages.sketch(d)))
    held = passages.stored(passages.holders(multi, spark.createDataFrame([], passages.PASSAGE), d))
    want = {(i, j) for i in docs for j in range(i)}
    rows = [{tuple(x) for x in passages.families(held, docs=n).collect()} for n in (128, 4)]  # one block, several
    assert rows[0] == rows[1] and {(x[0], x[3]) for x in rows[0]} == want
    assert passages.like_pairs(held, spark.createDataFrame([], passages.PASSAGE)).count() == 0
    alone = held.withColumn("family", F.when(F.col("doc") % 2 == 0, F.col("family")))  # families only say how documents meet
    some = {(x.doc, x.other) for x in passages.like_pairs(alone, spark.createDataFrame([], passages.PASSAGE)).collect()}
    some |= {(x.doc_id, x.match_doc_id) for x in passages.families(alone.where("seed is not null or family is not null")).collect()}
    assert some == want


def test_changed_words_in_the_middle_of_a_passage():
    x = np.arange(80, dtype=np.uint64)
    y = x.copy()
    y[32:48] += np.uint64(1000)  # 64 of 80 agree, but only 34 of any 50
    assert passages.passages_of(x, y, [5, 60], [5, 60], 5, 50, 0.8) == [(0, 80, 0, 80, 64)]
    y[48] += np.uint64(1000)
    assert not passages.passages_of(x, y, [5], [5], 5, 50, 0.8)


def test_edits_and_chains_as_by_their_definition():
    r = np.random.default_rng(3)
    for _ in range(300):
        u, v = r.integers(0, 4, r.integers(0, 12)), r.integers(0, 4, r.integers(0, 12))
        row = [0] * (len(v) + 1)
        for p in u:
            row = list(np.maximum.accumulate([0, *(max(row[j + 1], row[j] + (p == q)) for j, q in enumerate(v))]))
        assert passages._edits(u, v) == row[-1]
        x, y = r.integers(0, 2, (2, int(r.integers(1, 300))))
        y = np.where(r.random(len(x)) < r.random(), x, y)
        s = np.cumsum(np.where(x == y, 1.0, -2.0))
        low = np.flatnonzero(np.maximum.accumulate(np.maximum(s, 0)) - s > 8)
        end = int(low[0]) if len(low) else len(x)
        j = int(s[:end].argmax()) if end else 0
        assert passages._reach(x, y) == (j + 1 if end and s[j] > 0 else 0)


# -- op9 ---------------------------------------------------------------------------------------------
def test_words_are_the_tokenizers():
    w = id_store.WordIds(id_store.tokenizer_path(), 300)
    r = random.Random(8)
    al = "  \n\tabcdetheÀéİΣσςAB'ſ'sR'll12½٣²_.,!中文🎉́  ß<|endoftext|>\u0085\x1c"
    xs = ["".join(r.choice(al) for _ in range(r.randint(0, 60))) for _ in range(3000)] + ["<|endoftext|> a <|startoftext|>b", "word,", "word.", "x" * 3000]
    for i in range(0, len(xs), 100):
        for b, e in zip(w.encode(xs[i : i + 100]), w.tok.encode_batch(xs[i : i + 100], add_special_tokens=False), strict=True):
            assert np.frombuffer(b, "<u2").tolist() == e.ids


def test_store_round_trip(spark, odd, tmp_path):
    r = random.Random(1)
    shared = " ".join(f"w{r.randrange(999)}" for _ in range(900))
    more = spark.createDataFrame([(i, f"doc {i} {shared} end {i}") for i in range(20, 60)], SCHEMA)
    d = odd.select("doc_id", "text").union(more)
    id_store.write(d, str(tmp_path / "s"))
    got = id_store.read(spark, str(tmp_path / "s"), with_ids=True).orderBy("start").collect()
    w = id_store.WordIds(id_store.tokenizer_path())
    want = sorted((x.doc_id, x.text or "") for x in d.where("doc_id is not null").collect())
    assert [x.doc_id for x in got] == [i for i, _ in want]
    at = 0
    for x, (_, t) in zip(got, want, strict=True):
        ids = np.append(np.frombuffer(w.encode([t])[0], "<u2"), 1).astype("<u4")
        assert (x.start, x.n_tokens, x.ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes()))
        assert np.frombuffer(bytes(x.ids), "<u2").tolist() == ids.tolist()
        at += len(ids)
    packs = spark.read.parquet(str(tmp_path / "s")).collect()
    assert sum(len(p.payload) for p in packs) < 0.4 * 2 * at  # shared chunks lie once
    broken = packs[-1].asDict()
    broken["payload"] = bytes(broken["payload"])[:-2] + b"\xff\xff"
    with pytest.raises(ValueError):
        id_store.verify(broken)
    id_store.write(d.where("false"), str(tmp_path / "e"))
    assert id_store.read(spark, str(tmp_path / "e")).count() == 0


# -- op10 --------------------------------------------------------------------------------------------
def test_base_spans_are_the_patterns():
    import re

    r = random.Random(4)
    al = ["a", "1", "25", "@", ".", "-", "+", " ", "(", ")", "x.y", "a@b.c", "4111 1111 1111 1111", "1.2.3.4", "999.1.1.1", "+1 (555) 010-9999", "%", "é"]
    for _ in range(3000):
        t = "".join(r.choice(al) for _ in range(r.randint(0, 14)))
        want = [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        want += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m[0].split("."))]
        want += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t) if 14 <= len(x := re.sub("[^0-9]", "", m[0])) <= 19 and pii.luhn(x)]
        want += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
        assert pii.base_spans(t) == sorted(want), t


def test_contexts_find_new_identifiers(spark):
    docs = [(i, f"some words badge number: {i:08x}{i:08x}{i:08x}{i:08x} and more") for i in range(1, 12)] + [(50, "here badge number: Qx7_22kLm9 stands"), (51, "clean text 12345678 here"), (52, None), (53, "mail a@b.org now")]
    d = spark.createDataFrame(docs, SCHEMA).withColumn("n_chars", F.length("text")).withColumn("base", F.lit("x"))
    got = {r.doc_id: r for r in pii.digest(pii.extract(d)).collect()}
    t = dict(docs)[50]
    s = t.index("Qx7")
    assert got[50].spans == f"id:{s}:{s + 10}" and got[51].spans == "" and got[52].spans == ""
    assert got[53].n_email == 1 and got[53].spans == "email:5:12"
    red = {r.doc_id: r for r in pii.redact(d).collect()}
    assert red[50].text == "here badge number: [ID] stands" and red[53].text == "mail [EMAIL] now" and red[53].n_chars == len("mail [EMAIL] now")
    assert red[51].text == dict(docs)[51]
    assert red[52].text is None and red[50].base == "x"


def test_base_spans_are_never_added_again(spark):
    """Long e-mails, cards and numbers after a good pattern stay base spans alone, in plain Python over all rows."""
    long = "a.very.long.name.of.somebody@mail.example.org"
    docs = [(i, f"his badge number: {i:08x}{i:08x}{i:08x}{i:08x} here") for i in range(1, 12)] + [(50, f"his badge number: {long} here"), (51, f"his badge number: {'9' * 40}@{'b' * 70}.org and Qz7_22kLm9x"), (52, "his badge number: Qx7_22kLm9 and")]
    got = {r.doc_id: r.spans for r in pii.digest(pii.extract(spark.createDataFrame(docs, SCHEMA))).collect()}
    for i, t in docs:
        base = [(s, e) for s, _, e in pii.base_spans(t)]
        added = [tuple(map(int, x.split(":")[1:])) for x in got[i].split(",") if x.startswith("id:")]
        assert not any(a < e and s < b for a, b in added for s, e in base)
    assert got[50] == f"email:18:{18 + len(long)}" and got[52] == "id:18:28"


def test_pattern_scores_in_plain_python(spark):
    docs = [(i, f"his badge number: {i:08x}{i:08x}{i:08x}{i:08x} or order code Ab{i:06d}x") for i in range(1, 21)] + [(40 + i, f"his badge number: Zq{i:06d}k stands") for i in range(3)]
    found = pii.scan(spark.createDataFrame(docs, SCHEMA))
    got = {r.pattern: r.score for r in pii.patterns(found).collect()}
    edges, trust = {}, {}
    for r in found.collect():
        for c in r.cand:
            edges[c.pattern, c.instance] = max(c.seed, edges.get((c.pattern, c.instance), False))
    for (_, x), seed in edges.items():
        trust[x] = max(float(seed), trust.get(x, 0.0))
    for _ in range(2):
        score = {}
        for p in {p for p, _ in edges}:
            t = [trust[x] for q, x in edges if q == p]
            if sum(v >= 0.5 for v in t) >= 5 and sum(t) / len(t) >= 0.5:
                score[p] = sum(t) / len(t)
        new = {}
        for x in trust:
            doubt = 1.0
            for p, y in edges:
                if y == x:
                    doubt *= max(1e-6, 1 - score.get(p, 0.0))
            new[x] = 1.0 if any(s for (_, y), s in edges.items() if y == x) else 1 - doubt
        trust = new
    want = {p: v for p, v in score.items() if v >= 0.9}
    assert got.keys() == want.keys() and all(abs(got[p] - want[p]) < 1e-9 for p in want) and want


def test_clashing_columns_stay_what_they_are(spark, labels):
    """Columns named as the operators' internal ones, in any case of letters, come back with their own values."""
    names = ["found", "dirty", "key", "extra", "new_text", "FOUND_", "__s", "__id", "__extra", "__dirty", "n_words", "rep", "class_id"]
    text = " ".join(f"word{i}" for i in range(30))
    d = spark.createDataFrame([(i, f"{text} {i} mail a{i}@b.org", *[f"{n}{i}" for n in names]) for i in range(4)], f"{SCHEMA}, " + ", ".join(f"`{n}` string" for n in names))
    bench = spark.createDataFrame([(1, "not here at all but long enough to have a span of twelve tokens")], "item_id long, text string")
    from vgraph.llm import near_dedup

    for out in (rules.keep_good(d, rules.fit(d, labels)), decontam.clean(d, bench), pii.redact(d), near_dedup.keep_one(d.where("doc_id < 1"))):
        assert out.columns == d.columns and out.count() > 0
        assert all(r[n] == f"{n}{r.doc_id}" for r in out.collect() for n in names)


# -- odd rows for all ---------------------------------------------------------------------------------
def test_odd_rows(spark, odd, labels):
    bench = spark.createDataFrame([(1, "word word word word word word word word word word word word word"), (None, "x")], "item_id long, text string")
    lang = odd.withColumn("lang", F.lit("en"))
    n = len(ODD)
    assert rules.judge(odd, rules.fit(odd, labels)).count() == n
    assert toxicity.score(odd, toxicity.fit(odd, labels)).count() == n
    p = {r.doc_id: r for r in lang_id.predict(odd, lang_id.fit(lang)).collect()}
    assert p[1].lang_pred == p[2].lang_pred == p[3].lang_pred == "und" and p[5].lang_pred == "en"
    assert {r.doc_id for r in decontam.overlaps(odd, bench).collect()} == {4}
    assert pii.extract(odd).count() == n and pii.redact(odd).count() == n
    assert all(r.doc_id in (4, 5, 6, 7) for r in passages.repeated(odd).collect())
    e = odd.where("false")
    none = labels.where("false")
    assert rules.keep_good(e, rules.fit(e, none)).count() == 0 and rules.keep_good(e, rules.fit(e, none)).columns == odd.columns
    assert toxicity.score(e, toxicity.fit(e, none)).count() == lang_id.predict(e, lang_id.fit(lang.where("false"))).count() == 0
    assert passages.repeated(e).count() == decontam.overlaps(e, bench).count() == pii.redact(e).count() == piece_codec.encode(e).count() == 0
    assert lang_id.predict(odd, lang_id.fit(lang.where("false"))).where("lang_pred <> 'und'").count() == 0
    memo = Memo(str.upper, 2)
    assert [memo[x] for x in "abcabcaa"] == list("ABCABCAA") and len(memo) <= 2


def test_language_grams_laid_out_at_once_equal_plain_ones():
    words = ["a", "ab", "éa", "straße", "мир", "漢字", "x" * 90, "banana", "𐍈a"]
    times = {w: i + 1 for i, w in enumerate(words)}
    plain = Counter()
    for w, k in times.items():
        for g in lang_id.grams(w):
            plain[g] += k
    for most in (1, 20, 1 << 18):
        got = Counter()
        for some in lang_id.portions(words, most):
            got.update(dict(zip(*lang_id.counted({w: times[w] for w in some}), strict=True)))
        assert got == plain
    f = lang_id.Filters(["a", "b"], np.random.default_rng(1).integers(0, 4, 512).astype(np.uint64), np.array([0.1, 0.1]))
    memo = lang_id.WordCounts(f)
    memo.learn(words)
    for w in words:
        mask = f.masks(lang_id.hashed(lang_id.grams(w))).astype(int)
        assert memo[w] == len(mask) + (int((mask & 1).sum()) << 32) + (int((mask >> 1 & 1).sum()) << 64)


def test_unlabelled_sample_moves_ids_alone(spark):
    docs = spark.createDataFrame([(i, f"text {i}") for i in range(900)] + [(None, "x")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1) for i in range(0, 900, 3)] + [(1, None)], "doc_id long, toxic int")
    from vgraph.llm.common import held_out

    free = [r[0] for r in docs.where("doc_id % 3 <> 0").where(~held_out(3, 1)).orderBy(F.xxhash64("doc_id"), "doc_id").select("doc_id").collect()]
    for bound in (5, 40, 5000):
        got = toxicity.unlabelled(docs, labels, bound)
        assert got.columns == ["doc_id"] and sorted(r[0] for r in got.collect()) == sorted(free[:bound])


def test_passage_sides(spark):
    """A chain's hashed words are sent from one side only, to its other text's row; rows of many chains are dealt into parts."""
    docs = spark.createDataFrame([(i, " ".join(f"w{i if j % 40 == 0 else 0}_{j}" for j in range(120))) for i in range(3)], "doc_id long, text string")
    chain = spark.createDataFrame([(0, 1, 0, [41, 60], [41, 60]), (1, 2, 0, [41, 60], [41, 60])], "pid long, doc long, other long, a array<int>, b array<int>")
    rows = passages.around(chain, docs, passages.K, 10).collect()
    assert [(r.other, sorted(c.pid for c in r.cuts)) for r in rows] == [(0, [0, 1])]
    assert all(len(c.cut) == 8 * (60 + passages.K + 10 - 31) and c.off == 31 for c in rows[0].cuts)
    many = spark.range(passages.CUTS * 3).selectExpr("id pid", "0L other", "array(41, 60) b")
    parts = passages.sized(many, "other", "b", passages.FLANK).groupBy("other_part").count().collect()
    assert len(parts) == 3 and sum(r["count"] for r in parts) == passages.CUTS * 3
    assert passages.chains([9, 58, 1], [109, 158, 101]) == [[2, 0, 1]] and passages.chains([], []) == []
    assert sorted(map(len, passages.chains([1, 51], [101, 151]))) == [1, 1]


def test_links_in_unlike_surroundings_and_of_repeated_seeds(spark):
    """A passage whose changes lie beside its only shared seed is found; so is one that shares a seed with its first holder's second place of it."""
    r = random.Random(31)
    fresh = lambda n: [f"{r.randrange(10**7):x}" for _ in range(n)]
    docs, want = {}, set()
    while len(want) < 6:
        p = fresh(50)
        q = list(p)
        for i in r.sample([*range(14, 22), *range(27, 35)], 8) + r.sample([*range(14), *range(35, 50)], 2):
            q[i] = fresh(1)[0]
        x, y = fresh(30) + p + fresh(30), fresh(40) + q + fresh(20)
        hx, hy = hashed_words([" ".join(x), " ".join(y)])
        (_, sx, ax, cx), (_, sy, ay, cy) = (passages.sketched(h, np.array([0, len(h)])) for h in (hx, hy))
        if len(np.intersect1d(sx, sy)) != 1:
            continue
        i, j = int(np.flatnonzero(np.isin(sx, sy))[0]), int(np.flatnonzero(np.isin(sy, sx))[0])
        same = [((int(cx[i]) ^ int(cy[j])) >> 4 * b & 15) == 0 for b in range(16)]
        if max(sum(same[:8]), sum(same[8:])) > 4 or not passages.passages_of(hx, hy, [int(ax[i])], [int(ay[j])], 5, 50, 0.8):
            continue
        docs |= {len(docs): x, len(docs) + 1: y}
        want.add((len(docs) - 1, len(docs) - 2))
    got = passages.repeated(spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)).collect()
    assert {(x.doc_id, x.match_doc_id) for x in got} == want and all(x.end - x.start >= 50 and x.identity >= 0.8 for x in got)
    multi = spark.createDataFrame([(7, 1, 10, 1, 10, 3), (7, 1, 200, 1, 10, 3), (7, 2, 30, 1, 10, 3)], "seed long, doc long, at int, fdoc long, fat int, n long").withColumns({"ctx": F.lit(0).cast("long"), "fctx": F.lit(0).cast("long")})
    pair = passages.links(multi).first()
    assert sorted(zip(pair.a, pair.b, strict=True)) == [(30, 10), (30, 200)]


def test_single_links_seen_on_bytes_lose_no_passage(spark):
    """The look at bytes leaves every single link that gives a passage, at texts' edges too, and few that give none."""
    r = np.random.default_rng(6)
    docs, chain = {}, []
    for i in range(0, 240, 2):
        x = [f"{v:x}" for v in r.integers(0, 1 << 40, int(r.integers(50, 200)))]
        p = int(r.integers(0, len(x) - 4))
        share = float(r.choice([0.1, 0.2, 0.25, 0.9]))
        y = [w if p <= j < p + 5 or r.random() >= share else f"y{i}_{j}" for j, w in enumerate(x)]
        cut = int(r.integers(0, p + 1))  # the other text begins later
        docs |= {i: x, i + 1: y[cut:]}
        chain.append((i, i + 1, i, [p - cut], [p]))
    d = spark.createDataFrame([(i, " ".join(w)) for i, w in docs.items()], SCHEMA)
    c = spark.createDataFrame(chain, "pid long, doc long, other long, a array<int>, b array<int>").repartition(2)
    some = passages.stored(passages.hopeful(c, d))
    want, got = ({tuple(x) for x in passages.aligned(z, d).collect()} for z in (c, some))
    assert got == want and 20 < len(want) and some.count() < len(chain) - 20
