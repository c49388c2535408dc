"""URL filters over time: dated list entries become validity intervals, and every capture is judged
as of its fetch time. DataFrame functions only.

A list is a log of dated entries (entry_id, scope, value, action, listed_on). For one (scope, value) an entry
holds from its date until the next entry's date; action 'lift' ends an earlier one. Scopes, most specific
first: url (host and path), prefix (host and first path part), host, domain (host or any parent).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SCOPES = ("url", "prefix", "host", "domain")
#: Longest host name that the domain name system allows; it bounds the parents of a host.
LONGEST_HOST = 253
#: Lists of at most so many entries are broadcast; larger ones are joined by shuffling, each key dealt into so many parts.
BROADCAST_ENTRIES, SALTS = 50_000, 16


def intervals(entries: DataFrame) -> DataFrame:
    """(scope, value, valid_from, valid_to, action, entry_id): half-open; valid_to is null for what still holds.

    Of entries for one key and date the one with the greatest entry_id counts; entries with a null scope, value or date are
    left out. A key's history is folded from one sorted array, bounded by that key's own entries."""
    e = entries.where("scope is not null and value is not null and listed_on is not null")
    e = e.select("scope", F.lower("value").alias("value"), F.col("listed_on").cast("timestamp").alias("ts"), "entry_id", "action")
    day = e.groupBy("scope", "value", "ts").agg(F.max(F.struct("entry_id", "action")).alias("x"))
    h = day.groupBy("scope", "value").agg(F.array_sort(F.collect_list(F.struct("ts", "x.entry_id", "x.action"))).alias("h"))
    one = h.select("scope", "value", "h", F.posexplode("h").alias("i", "x"))
    return one.select("scope", "value", F.col("x.ts").alias("valid_from"), F.get("h", F.col("i") + 1)["ts"].alias("valid_to"), F.col("x.action").alias("action"), F.col("x.entry_id").alias("entry_id"))


def host_of(url: Column) -> Column:
    """Lower-case host of an http or https URL without its port and user; null where there is none or it is too long for a name."""
    raw = F.regexp_extract(F.lower(F.trim(url)), r"^https?://(?:[^/?#@]*@)?([^/?#:@]+)", 1)
    return F.when((raw != "") & (F.length(raw) <= LONGEST_HOST), raw)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.lower(F.trim(url)), r"^https?://[^/?#]+([^?#]*)", 1)


def keys_of(url: Column) -> Column:
    """Everything a URL is looked up under: structs (scope, value), most specific first."""
    host, path = host_of(url), path_of(url)
    first = F.regexp_extract(path, r"^(/[^/]+)", 1)
    labels = F.split(host, r"\.")
    n = F.size(labels)
    parents = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.struct(F.lit("domain").alias("scope"), F.array_join(F.slice(labels, n - i, i + 1), ".").alias("value")))
    own = F.array(*[F.struct(F.lit(s).alias("scope"), v.alias("value")) for s, v in (("url", F.concat(host, path)), ("prefix", F.concat(host, first)), ("host", host))])
    return F.when(host.isNotNull(), F.concat(own, parents))


def as_of(history: Column, ts: Column) -> Column:
    """The last struct of an array sorted by valid_from that begins at ``ts`` or before, by bisection; null where none does."""
    steps = F.sequence(F.lit(0), F.ceil(F.log2(F.size(history) + F.lit(1))).cast("int"))

    def halve(s, _):
        mid = F.floor((s["lo"] + s["hi"]) / 2).cast("int")
        low = F.get(history, mid)["valid_from"] <= ts
        open_ = s["lo"] < s["hi"]
        return F.struct(F.when(open_ & low, mid + 1).otherwise(s["lo"]).alias("lo"), F.when(open_ & ~low, mid).otherwise(s["hi"]).alias("hi"))

    end = F.aggregate(steps, F.struct(F.lit(0).alias("lo"), F.size(history).alias("hi")), halve, lambda s: s["lo"])
    return F.when(ts.isNotNull() & history.isNotNull(), F.get(history, end - 1))


def judge(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", ts_col: str = "fetched_at") -> DataFrame:
    """(id, host, fetched_at, entry_id, action, kept): each capture with the most specific entry active when it was fetched.

    Among entries of one scope the longest value wins. kept is false where that entry's action is 'block'. Null or odd URLs, hosts of
    more than 253 characters, null fetch times and empty lists leave a capture without an entry: it is kept. Repeated rows
    are judged each; extra columns are ignored. A host is looked up under every one of its parents. The list is joined as one sorted
    history a key, in which the fetch time is sought by bisection, so a capture meets at most one row for each of its keys however
    long a history is. A list too large to broadcast is joined by shuffling, with every key in parts, for a top-level domain is a key of
    a large share of all captures."""
    iv = intervals(entries)
    hist = iv.groupBy("scope", "value").agg(F.array_sort(F.collect_list(F.struct("valid_from", "valid_to", "entry_id", "action"))).alias("h"))
    small = entries.limit(BROADCAST_ENTRIES + 1).count() <= BROADCAST_ENTRIES
    c = captures.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(ts_col).cast("timestamp").alias("ts")).withColumn("row", F.monotonically_increasing_id())
    c = c.withColumn("host", host_of(F.col("url")))
    rank = F.create_map(*[x for k, s in enumerate(SCOPES) for x in (F.lit(s), F.lit(len(SCOPES) - k))])
    keyed = c.withColumn("k", F.explode_outer(keys_of(F.col("url"))))
    same = (F.col("k.scope") == F.col("scope")) & (F.col("k.value") == F.col("value"))
    if small:
        looked = keyed.join(F.broadcast(hist), same, "left")
    else:
        parts = hist.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        looked = keyed.withColumn("part", F.pmod(F.xxhash64("row"), F.lit(SALTS)).cast("int")).join(parts, same & (F.col("part") == F.col("salt")), "left")
    m = as_of(F.col("h"), F.col("ts"))
    m = F.when((m["valid_to"].isNull() | (F.col("ts") < m["valid_to"])) & (m["action"] != "lift"), m)
    scored = looked.withColumn("m", m).withColumn("best", F.when(F.col("m").isNotNull(), F.struct(rank[F.col("scope")].alias("r"), F.length("value").alias("len"), F.col("m.entry_id").alias("entry_id"), F.col("m.action").alias("action"))))
    one = scored.groupBy("row", "id", "host", "ts").agg(F.max("best").alias("best"))
    return one.select(F.col("id").alias(id_col), "host", F.col("ts").alias("fetched_at"), F.col("best.entry_id").alias("entry_id"), F.col("best.action").alias("action"), (~(F.coalesce(F.col("best.action"), F.lit("")) == "block")).alias("kept"))
