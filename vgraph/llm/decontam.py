"""Benchmark decontamination with spaced seeds, in DataFrame functions only.

Texts become lower-case tokens of letters and digits. A mask names which token positions of a span
are hashed and which are ignored, so a substitution under an ignored position leaves the hash
as it is. Benchmark hashes meet the corpus's hashes in an equi-join; every hit names a diagonal (text
position minus item position), along which the whole item is compared token by token.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cleared, stored, unused

#: Masks over twelve tokens, eight hashed (1), four ignored (0).
MASKS = ("111010011011", "110110101101")
SPAN = 12
#: Least share of an item's tokens that must agree along one diagonal, and the least number.
SHARE, LEAST = 0.5, 8
#: A benchmark of at most so many seeds is broadcast; a larger one is joined by shuffling.
BROADCAST_SEEDS = 200_000
#: Ids of documents with a hit are broadcast up to so many (16 bytes each); only those documents' texts are read again.
BROADCAST_IDS = 1_000_000


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def seeds(rows: DataFrame, id_col: str, masks: tuple[str, ...], lengths: list[int]) -> DataFrame:
    """(id, mask, pos, seed) of every masked window of column ``toks``; ``lengths`` adds full windows of those sizes."""
    h = rows.select(id_col, F.transform("toks", lambda t: F.xxhash64(t)).alias("h"))

    def at(span: int, picks: list[int]) -> Column:
        return F.when(F.size("h") >= span, F.transform(F.sequence(F.lit(0), F.size("h") - span), lambda i: F.xxhash64(F.lit(span), *[F.get("h", i + p) for p in picks]))).otherwise(F.array().cast("array<bigint>"))

    shapes = [(len(m), [i for i, c in enumerate(m) if c == "1"]) for m in masks] + [(n, list(range(n))) for n in lengths]
    each = F.array(*[F.struct(F.lit(k).alias("mask"), at(*s).alias("seeds")) for k, s in enumerate(shapes)])
    one = h.select(id_col, F.explode(each).alias("m"))
    return one.select(id_col, F.col("m.mask").alias("mask"), F.posexplode("m.seeds").alias("pos", "seed"))


@cleared
def overlaps(docs: DataFrame, benchmark: DataFrame, masks: tuple[str, ...] = MASKS, share: float = SHARE, least: int = LEAST) -> DataFrame:
    """(doc_id, item_id, n_match, n_item, at): documents that hold an item, with the best diagonal's agreeing tokens.

    An item counts as held when, from a seed hit on, at least ``share`` of its tokens and ``least`` of them (all of
    them, for items of fewer) agree along one diagonal. Items shorter than the masks' span are sought
    whole. Null and empty texts and items hold nothing; rows with null ids are left out; repeated ids are one document
    or item whose best row counts. Extra columns are ignored.
    """
    span = max(map(len, masks))
    d = docs.where("doc_id is not null").select("doc_id", tokens(F.col("text")).alias("toks"))
    b = stored(benchmark.where("item_id is not null").select("item_id", tokens(F.col("text")).alias("toks")).where("size(toks) > 0"))
    short = sorted(r[0] for r in b.where(F.size("toks") < span).select(F.size("toks")).distinct().collect())  # fewer than ``span`` values
    full = b.where(F.size("toks") >= span)
    bs = seeds(full, "item_id", masks, [])
    if short:  # a short item's only seed is its whole length
        own = seeds(b.where(F.size("toks") < span).withColumn("n", F.size("toks")), "item_id", (), short)
        sizes = b.select("item_id", F.size("toks").alias("n"))
        own = own.join(sizes, "item_id").where(F.element_at(F.array(*map(F.lit, short)), F.col("mask") + 1) == F.col("n")).drop("n")
        bs = bs.union(own.withColumn("mask", F.col("mask") + len(masks)))
    bs = stored(bs.select(F.col("item_id"), F.col("mask"), F.col("pos").alias("j"), "seed").distinct())
    small = bs.count() <= BROADCAST_SEEDS
    ds = seeds(d, "doc_id", masks, short)
    keys = bs.select("mask", "seed").distinct()
    hit = ds.join(F.broadcast(keys) if small else keys, ["mask", "seed"], "left_semi")
    hits = hit.join(F.broadcast(bs) if small else bs, ["mask", "seed"]).select("doc_id", "item_id", (F.col("pos") - F.col("j")).alias("diag")).distinct()
    hits = stored(hits)
    items = b.select("item_id", F.col("toks").alias("it"))
    ids = stored(hits.select("doc_id").distinct())
    few = ids.count() <= BROADCAST_IDS
    held = docs.select("doc_id", "text").join(F.broadcast(ids) if few else ids, "doc_id", "left_semi").select("doc_id", tokens(F.col("text")).alias("toks"))
    pairs = hits.join(F.broadcast(items) if small else items, "item_id").join(held, "doc_id")
    agree = F.size(F.filter(F.sequence(F.lit(0), F.size("it") - 1), lambda j: (j + F.col("diag") >= 0) & F.get("toks", j + F.col("diag")).eqNullSafe(F.get("it", j))))
    scored = pairs.select("doc_id", "item_id", "diag", agree.cast("long").alias("n_match"), F.size("it").cast("long").alias("n_item"))
    kept = scored.where((F.col("n_match") >= share * F.col("n_item")) & (F.col("n_match") >= F.least(F.lit(least), F.col("n_item"))))
    best = kept.groupBy("doc_id", "item_id").agg(F.max(F.struct("n_match", "n_item", (-F.col("diag")).cast("long").alias("neg"))).alias("b"))
    return best.select("doc_id", "item_id", "b.n_match", "b.n_item", (-F.col("b.neg")).alias("at"))


def clean(docs: DataFrame, benchmark: DataFrame, **settings) -> DataFrame:
    """The rows of ``docs`` that hold no benchmark item; rows with a null doc_id stay."""
    (mark,) = unused(docs.columns, "dirty")
    dirty = overlaps(docs, benchmark, **settings).select(F.col("doc_id").alias(mark)).distinct()
    return docs.join(dirty, docs["doc_id"] == dirty[mark], "left_anti").select(*[F.col(f"`{n}`") for n in docs.columns])


def oracle(masks: tuple[str, ...] = MASKS, share: float = SHARE, least: int = LEAST) -> str:
    """DuckDB SQL for ``overlaps`` on the given tables: masked windows meet as text, without hashes."""
    shapes = " union all ".join(
        f"select id, kind, {k} as mask, i - 1 as pos, concat_ws(' ', {', '.join(f't[i + {p}]' for p, c in enumerate(m) if c == '1')}) as seed from t, unnest(range(1, len(t) - {len(m)} + 2)) u(i) where len(t) >= {len(m)}"
        for k, m in enumerate(masks)
    )
    span = max(map(len, masks))
    return f"""
with t as (
  select doc_id as id, 'd' as kind, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') as t from documents
  union all
  select item_id, 'b', list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') from benchmark),
seeds as ({shapes}
  union all
  select x.id, x.kind, -n as mask, i - 1 as pos, list_aggregate(x.t[i : i + n - 1], 'string_agg', ' ') as seed
  from t x, (select distinct len(t) as n from t where kind = 'b' and len(t) between 1 and {span - 1}) s, unnest(range(1, len(x.t) - n + 2)) u(i)
  where len(x.t) >= n and (x.kind = 'd' or len(x.t) = n)),
hits as (select distinct d.id as doc_id, b.id as item_id, d.pos - b.pos as diag from seeds d join seeds b on d.mask = b.mask and d.seed = b.seed where d.kind = 'd' and b.kind = 'b'),
scored as (
  select h.doc_id, h.item_id, h.diag, len(i.t) as n_item,
    len(list_filter(range(1, len(i.t) + 1), lambda j: j + h.diag >= 1 and j + h.diag <= len(d.t) and d.t[j + h.diag] = i.t[j])) as n_match
  from hits h join t d on d.kind = 'd' and d.id = h.doc_id join t i on i.kind = 'b' and i.id = h.item_id),
held as (select *, row_number() over (partition by doc_id, item_id order by n_match desc, n_item desc, diag) as r from scored
  where n_match >= {share} * n_item and n_match >= least({least}, n_item))
select doc_id, item_id, n_match, n_item, diag as "at" from held where r = 1
"""
