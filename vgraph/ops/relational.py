"""One function an operator, (spark, sf_dir) -> DataFrame; the SQL twin of each stands in ``twins``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..core.mix import mix
from ..data import table

OPS: dict = {}


def op(f):
    OPS[f"op_{f.__name__}"] = f
    return f


def r(c, n: int = 4):
    return F.round(c, n)


# -- scans and filters ------------------------------------------------------------------------------
@op
def scan_prune(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), r(F.sum("l_quantity")).alias("qty"))


@op
def filter_pushdown(s, d):
    t = table(s, d, "lineitem").where((F.col("l_shipdate") >= "1995-01-01") & (F.col("l_shipdate") < "1996-01-01") & (F.col("l_quantity") < 24))
    return t.agg(F.count(F.lit(1)).alias("n"), r(F.sum(F.col("l_extendedprice") * F.col("l_discount")), 2).alias("revenue"))


@op
def filter_pattern(s, d):
    t = table(s, d, "part")
    return t.where(F.col("p_name").like("%a%") & F.col("p_brand").rlike("[1-3]$") & F.col("p_size").isin(1, 5, 10, 15, 20)).select("p_partkey", "p_name", "p_brand", "p_size")


@op
def case_coalesce(s, d):
    t = table(s, d, "orders")
    kind = F.when(F.col("o_totalprice") > 200000, "large").when(F.col("o_totalprice") > 50000, "middle").otherwise("small").alias("kind")
    return t.groupBy(kind, F.col("o_orderstatus").eqNullSafe("F").alias("done")).agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.max(F.lit(None).cast("string")), F.lit("none")).alias("filled"))


# -- joins ------------------------------------------------------------------------------------------
@op
def join_inner_broadcast(s, d):
    o, c, n, g = (table(s, d, x) for x in ("orders", "customer", "nation", "region"))
    # nation and region are fixed lists of 25 and 5 rows
    j = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(g), n.n_regionkey == g.r_regionkey)
    return j.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), r(F.sum("o_totalprice"), 2).alias("total"))


@op
def join_sort_merge(s, d):
    l, o = table(s, d, "lineitem"), table(s, d, "orders")
    return l.hint("merge").join(o, l.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), r(F.sum("l_extendedprice"), 2).alias("total"))


@op
def join_shuffle_hash(s, d):
    l, p = table(s, d, "lineitem"), table(s, d, "part")
    return l.join(p.hint("shuffle_hash"), l.l_partkey == p.p_partkey).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), r(F.sum("l_quantity"), 2).alias("qty"))


@op
def join_left(s, d):
    c, o = table(s, d, "customer"), table(s, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left").groupBy("c_mktsegment").agg(F.count("o_orderkey").alias("n_orders"), F.count_if(F.col("o_orderkey").isNull()).alias("n_without"))


@op
def join_right(s, d):
    l, t = table(s, d, "labels"), table(s, d, "documents")
    return l.join(t.select("doc_id", "lang"), "doc_id", "right").groupBy("lang").agg(F.count("quality").alias("labelled"), F.count(F.lit(1)).alias("n"))


@op
def join_full(s, d):
    n, u = table(s, d, "nation"), table(s, d, "supplier")
    return n.join(u, n.n_nationkey == u.s_nationkey, "full").groupBy("n_name").agg(F.count("s_suppkey").alias("n"))


@op
def join_semi(s, d):
    return table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_semi").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@op
def join_anti(s, d):
    return table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_anti").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@op
def join_self_twohop(s, d):
    """Nodes two steps away in the exact graph, direct neighbours and the node itself left out, with the number of ways."""
    from ..core.iterate import step
    from ..data import embeddings
    from ..exact import exact_knn_graph

    g = step(exact_knn_graph(embeddings(s, d), 10).select("src", "dst"))
    two = g.alias("a").join(g.alias("b"), F.col("a.dst") == F.col("b.src")).select(F.col("a.src").alias("src"), F.col("b.dst").alias("far")).where("src <> far")
    far = two.join(g, (two["src"] == g["src"]) & (two["far"] == g["dst"]), "left_anti")
    return far.groupBy("src", "far").agg(F.count(F.lit(1)).alias("ways"))


@op
def join_cross(s, d):
    g = table(s, d, "region")  # a fixed list of five rows
    return g.select(F.col("r_name").alias("a")).crossJoin(g.select(F.col("r_name").alias("b")))


@op
def join_theta(s, d):
    """Pairs of a brand whose prices are near: prices less than 0.5 apart lie in the same or in neighbouring cells of that width, so parts
    meet by an equi-join on brand and cell and a remaining test."""
    p = table(s, d, "part").select("p_brand", F.floor(F.col("p_retailprice") * 2).alias("cell"), F.col("p_partkey").alias("k"), F.col("p_retailprice").alias("price"))
    near = F.explode(F.array(F.col("cell") - 1, F.col("cell"), F.col("cell") + 1)).alias("cell")
    q = p.select("p_brand", near, F.col("k").alias("k2"), F.col("price").alias("price2"))
    return p.join(q, ["p_brand", "cell"]).where((F.col("k") < F.col("k2")) & (F.abs(F.col("price") - F.col("price2")) < 0.5)).groupBy("p_brand").agg(F.count(F.lit(1)).alias("pairs"))


BANDS = [(0, 0.0, 1000.0), (1, 1000.0, 5000.0), (2, 5000.0, 20000.0), (3, 20000.0, 60000.0), (4, 60000.0, 1000000.0)]


@op
def join_range(s, d):
    """Prices into bands: each band names the cells of width 1000 it covers, so lines meet bands by an equi-join and a remaining test."""
    b = s.createDataFrame(BANDS, "band int, low double, high double").withColumn("cell", F.explode(F.sequence(F.floor(F.col("low") / 1000), F.floor((F.col("high") - 0.01) / 1000))))
    l = table(s, d, "lineitem").select("l_extendedprice", F.floor(F.col("l_extendedprice") / 1000).alias("cell"))
    return l.join(F.broadcast(b), "cell").where("l_extendedprice >= low and l_extendedprice < high").groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@op
def join_interval(s, d):
    e = table(s, d, "events")
    v = e.where("event_type = 'view'").select("user_id", F.col("ts").alias("t0"))
    c = e.where("event_type = 'click'").select("user_id", F.col("ts").alias("t1"))
    j = v.join(c, "user_id").where("t1 >= t0 and t1 <= t0 + interval 10 minutes")
    return j.groupBy("user_id").agg(F.count(F.lit(1)).alias("pairs"))


@op
def join_asof(s, d):
    """Each purchase with the time of its user's latest earlier view, by one window over both kinds of event."""
    e = table(s, d, "events").where("event_type in ('view', 'purchase')")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    j = e.withColumn("seen", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w))
    return j.where("event_type = 'purchase'").select("event_id", "user_id", F.col("seen").alias("view_id"))


@op
def join_lateral_topk(s, d):
    l = table(s, d, "lineitem").groupBy("l_suppkey", "l_partkey").agg(r(F.sum("l_extendedprice"), 2).alias("revenue"))
    w = W.partitionBy("l_suppkey").orderBy(F.desc("revenue"), "l_partkey")
    return l.withColumn("rank", F.row_number().over(w)).where("rank <= 3").select("l_suppkey", "l_partkey", "revenue", "rank")


# -- aggregation ------------------------------------------------------------------------------------
@op
def agg_hash(s, d):
    l = table(s, d, "lineitem")
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return l.groupBy("l_returnflag", "l_linestatus").agg(r(F.sum("l_quantity"), 2).alias("qty"), r(F.sum(net), 2).alias("net"), r(F.avg("l_discount"), 6).alias("disc"), F.count(F.lit(1)).alias("n"))


@op
def agg_sort(s, d):
    return table(s, d, "part").groupBy("p_type").agg(F.max("p_name").alias("last_name"), F.min("p_name").alias("first_name"))


@op
def agg_distinct(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct(F.to_date("ts")).alias("days"))


@op
def agg_approx_distinct(s, d):
    return table(s, d, "events").groupBy(F.to_date("ts").alias("day")).agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@op
def agg_percentile(s, d):
    return table(s, d, "events").groupBy("event_type").agg(r(F.percentile("value", 0.5), 6).alias("median"), r(F.percentile("value", 0.9), 6).alias("p90"))


@op
def agg_filter(s, d):
    return table(s, d, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "O").alias("open"), F.count_if(F.col("o_totalprice") > 100000).alias("big"))


@op
def agg_stats(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(r(F.stddev("l_quantity"), 4).alias("sd"), r(F.variance("l_discount"), 6).alias("var"), r(F.corr("l_quantity", "l_extendedprice"), 4).alias("corr"), r(F.covar_samp("l_quantity", "l_tax"), 6).alias("cov"))


@op
def agg_minmaxby(s, d):
    t = table(s, d, "documents")
    return t.groupBy("source").agg(F.max(F.struct("n_chars", -F.col("doc_id"))).alias("m")).select("source", F.col("m.n_chars").alias("longest"), (-F.col("m.col2")).alias("doc_id"))


@op
def agg_collect(s, d):
    """Types of a user's first five events in order: the window keeps five before anything is gathered."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(s, d, "events").withColumn("n", F.row_number().over(w)).where("n <= 5")
    return e.groupBy("user_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("n", "event_type"))), lambda x: x["event_type"]), ">").alias("path"))


def _orders(s, d):
    return table(s, d, "orders").withColumn("year", F.year("o_orderdate"))


def _grouped(t):
    return t.agg(F.count(F.lit(1)).alias("n"), r(F.sum("o_totalprice"), 2).alias("total"))


@op
def grouping_sets(s, d):
    return _grouped(_orders(s, d).groupingSets([["o_orderstatus"], ["year"], []], "o_orderstatus", "year")).select("o_orderstatus", "year", "n", "total")


@op
def cube(s, d):
    return _grouped(_orders(s, d).cube("o_orderstatus", "year"))


@op
def rollup(s, d):
    return _grouped(_orders(s, d).rollup("o_orderstatus", "o_orderpriority"))


KINDS = ["view", "click", "purchase", "signup", "error"]


@op
def pivot(s, d):
    p = table(s, d, "events").groupBy("user_id").pivot("event_type", KINDS).count()
    return p.select("user_id", *[F.coalesce(k, F.lit(0)).alias(f"n_{k}") for k in KINDS])


@op
def unpivot(s, d):
    p = table(s, d, "lineitem").groupBy("l_returnflag").agg(r(F.sum("l_quantity"), 2).alias("qty"), r(F.sum("l_tax"), 2).alias("tax"))
    return p.unpivot("l_returnflag", ["qty", "tax"], "measure", "value")


@op
def having(s, d):
    return table(s, d, "lineitem").groupBy("l_suppkey").agg(r(F.sum("l_extendedprice"), 2).alias("revenue")).where("revenue > 1000000")


# -- windows ----------------------------------------------------------------------------------------
@op
def win_rank(s, d):
    w = W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    v = W.partitionBy("c_nationkey").orderBy("c_mktsegment")
    return table(s, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"), r(F.percent_rank().over(v), 6).alias("pr"), r(F.cume_dist().over(v), 6).alias("cd"))


@op
def win_offset(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    full = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(s, d, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_type").over(full).alias("first"), F.last("event_type").over(full).alias("last"), F.nth_value("event_type", 2).over(full).alias("second"))


@op
def win_rows(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-6, 0)
    return table(s, d, "events").select("event_id", r(F.avg("value").over(w)).alias("avg7"))


@op
def win_range(s, d):
    e = table(s, d, "events").withColumn("sec", F.unix_timestamp("ts"))
    w = W.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return e.select("event_id", r(F.sum("value").over(w)).alias("day_sum"))


@op
def win_session(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.when(F.col("ts") > F.lag("ts").over(w) + F.expr("interval 30 minutes"), 1).otherwise(0)
    e = table(s, d, "events").withColumn("new", gap).withColumn("session", F.sum("new").over(w))
    return e.groupBy("user_id").agg((F.max("session") + 1).alias("sessions"))


# -- order, limits, sets ----------------------------------------------------------------------------
@op
def sort_limit(s, d):
    return table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@op
def topk(s, d):
    return table(s, d, "lineitem").groupBy("l_partkey").agg(r(F.sum("l_quantity"), 2).alias("qty")).orderBy(F.desc("qty"), "l_partkey").limit(20)


@op
def topk_group(s, d):
    w = W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(s, d, "orders").withColumn("rank", F.row_number().over(w)).where("rank <= 5").select("o_orderpriority", "o_orderkey", "rank")


@op
def offset(s, d):
    return table(s, d, "customer").orderBy("c_custkey").offset(20).limit(10).select("c_custkey", "c_name")


def _keys(s, d):
    return table(s, d, "customer").select(F.col("c_custkey").alias("k")), table(s, d, "orders").select(F.col("o_custkey").alias("k"))


@op
def union(s, d):
    a, b = _keys(s, d)
    return a.union(b).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@op
def union_by_name(s, d):
    a = table(s, d, "customer").select(F.col("c_custkey").alias("k"), F.col("c_acctbal").alias("x"))
    b = table(s, d, "supplier").select(F.col("s_acctbal").alias("x"), F.col("s_suppkey").alias("k"))
    return a.unionByName(b).agg(F.count(F.lit(1)).alias("n"), r(F.sum("x"), 2).alias("total"))


@op
def intersect(s, d):
    a, b = _keys(s, d)
    return a.intersect(b)


@op
def intersect_all(s, d):
    a, b = _keys(s, d)
    return b.intersectAll(a.union(a))


@op
def except_(s, d):
    a, b = _keys(s, d)
    return a.subtract(b)


OPS["op_except"] = OPS.pop("op_except_")


@op
def except_all(s, d):
    a, b = _keys(s, d)
    return b.exceptAll(a)


@op
def distinct(s, d):
    return table(s, d, "documents").select("lang", "source").distinct()


@op
def dedupe(s, d):
    """Distinct texts by digest; the least id stands for its copies."""
    return table(s, d, "documents").groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n")).where("n > 1")


# -- scalar functions -------------------------------------------------------------------------------
@op
def str(s, d):  # noqa: A001
    p = table(s, d, "part")
    return p.select("p_partkey", F.upper(F.trim("p_name")).alias("up"), F.substring("p_name", 2, 4).alias("sub"), F.element_at(F.split("p_name", " "), 1).alias("head"), F.regexp_replace("p_name", "[aeiou]", "_").alias("re"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("lev"), F.concat_ws("-", "p_brand", "p_type").alias("cat"), F.lpad(F.col("p_size").cast("string"), 5, "0").alias("pad"))


@op
def date(s, d):
    o = table(s, d, "orders")
    return o.select("o_orderkey", F.date_trunc("month", "o_orderdate").alias("month"), F.datediff(F.lit("1999-01-01"), "o_orderdate").alias("days"), F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.date_format("o_orderdate", "yyyy-MM").alias("ym"), F.to_date(F.date_add("o_orderdate", 30)).alias("later"))


@op
def math(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(r(F.sum(F.pow("l_discount", 2))).alias("p"), r(F.sum(F.sqrt("l_quantity")), 2).alias("sq"), r(F.sum(F.log("l_extendedprice")), 2).alias("lg"), r(F.sum(F.acos("l_discount")), 2).alias("ac"), F.sum(F.pmod("l_orderkey", F.lit(7))).alias("pm"), r(F.sum(F.greatest("l_tax", "l_discount")), 2).alias("gr"))


@op
def array(s, d):
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    sq = F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)
    return e.select("vec_id", r(F.sqrt(sq)).alias("norm"), r(F.element_at(F.array_sort("v"), 1), 6).alias("low"), r(F.aggregate(F.slice("v", 1, 4), F.lit(0.0), lambda a, x: a + x), 5).alias("head"), F.exists("v", lambda x: x > 0.3).alias("any_big"), F.forall("v", lambda x: x > -1).alias("all_ok"), F.size(F.filter("v", lambda x: x > 0)).cast("long").alias("positive"))


@op
def map(s, d):  # noqa: A001
    e = table(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.element_at(F.transform_values("m", lambda k, v: v * 2), "view"), F.lit(0)).alias("twice_views"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@op
def json(s, d):
    e = table(s, d, "events")
    return e.groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k1"), F.sum(F.from_json("props", "k long")["k"]).alias("k2"))


@op
def decimal(s, d):
    return table(s, d, "orders").groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))


@op
def url_html(s, d):
    p = table(s, d, "pages")
    host = F.parse_url("url", F.lit("HOST"))
    title = F.regexp_replace(F.regexp_extract("html", "<title>([^<]*)</title>", 1), "<[^>]*>", "")
    return p.select("page_id", host.alias("host"), title.alias("title"))


# -- subqueries and others --------------------------------------------------------------------------
@op
def subquery_scalar(s, d):
    o = table(s, d, "orders")
    mean = o.agg(F.avg("o_totalprice").alias("mean"))  # one row
    return o.crossJoin(F.broadcast(mean)).where("o_totalprice > 2 * mean").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@op
def subquery_exists(s, d):
    table(s, d, "customer").createOrReplaceTempView("__c")
    table(s, d, "orders").createOrReplaceTempView("__o")
    return s.sql("select c_mktsegment, count(*) as n from __c where exists (select 1 from __o where o_custkey = c_custkey and o_totalprice > 150000) group by c_mktsegment")


@op
def subquery_in(s, d):
    table(s, d, "supplier").createOrReplaceTempView("__s")
    table(s, d, "nation").createOrReplaceTempView("__n")
    return s.sql("select s_suppkey, s_name from __s where s_nationkey in (select n_nationkey from __n where n_regionkey = 1)")


@op
def cte_recursive(s, d):
    table(s, d, "nation").createOrReplaceTempView("__n")
    table(s, d, "region").createOrReplaceTempView("__r")
    return s.sql(
        """with recursive tree(level, node, region) as (
             select 0, r_name, r_regionkey from __r
             union all
             select level + 1, n_name, tree.region from tree join __n on n_regionkey = tree.region where level = 0)
           select level, region, count(*) as n from tree group by level, region"""
    )


@op
def sample_portable(s, d):
    return table(s, d, "embeddings").where(mix(42, F.col("vec_id")) % 10 == 0).select("vec_id")


@op
def quantise(s, d):
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    q = e.withColumn("q", F.transform("v", lambda x: F.floor(x * 127 + 0.5)))
    return q.select("vec_id", F.aggregate("q", F.lit(0).cast("long"), lambda a, x: a + x).alias("sum_q"), r(F.sqrt(F.aggregate(F.zip_with("v", "q", lambda x, y: F.pow(x - y / 127, F.lit(2.0))), F.lit(0.0), lambda a, x: a + x)), 5).alias("err"))


@op
def centroid(s, d):
    e = table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("p", "x"))
    return e.groupBy("label", "p").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


@op
def tumbling(s, d):
    return table(s, d, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


@op
def sliding(s, d):
    return table(s, d, "events").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


@op
def session_window(s, d):
    return table(s, d, "events").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")
