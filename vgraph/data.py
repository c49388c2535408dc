"""Vector sets derived from the given tables; deterministic, never written back."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .core.mix import mix

#: Prime of the 3-gram fold.
FOLD = 1000003
#: Searches take every row whose id this divides as a query, against all rows.
EVERY = 100


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))


def embeddings_copies(spark: SparkSession, sf_dir: str, copies: int, noise: float = 0.05) -> DataFrame:
    """``copies`` perturbed copies, id = copy * n + vec_id; offsets from the portable mix, renormalised."""
    v = embeddings(spark, sf_dir)
    n = v.count()
    c = v.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))

    def moved(x, i):
        return x + F.when(F.col("copy") == 0, F.lit(0.0)).otherwise((mix(F.col("copy"), F.col("id"), i) / 2147483647.0 - 0.5) * 2 * noise)

    w = c.withColumn("w", F.transform("vec", moved))
    size = F.sqrt(F.aggregate("w", F.lit(0.0), lambda s, x: s + x * x))
    return w.withColumn("size", size).select((F.col("copy") * n + F.col("id")).cast("long").alias("id"), F.transform("w", lambda x: x / F.col("size")).alias("vec"))


def hashed_text(df: DataFrame, id_col: str, dim: int) -> DataFrame:
    """Folded 3-gram counts of whole texts, L2-normalised; texts under three characters are left out."""
    t = df.select(F.col(id_col).alias("id"), F.col("text").alias("t")).where("length(t) >= 3")
    code = F.transform(F.filter(F.split("t", ""), lambda c: c != ""), lambda c: F.ascii(c).cast("long"))
    u = t.select("id", code.alias("u"))
    slot = F.transform(F.sequence(F.lit(0), F.size("u") - 3), lambda i: F.pmod(F.pmod((F.get("u", i) * 31 + F.get("u", i + 1)) * 31 + F.get("u", i + 2), F.lit(FOLD)), F.lit(dim)))
    g = u.select("id", F.explode(slot).alias("slot")).groupBy("id", "slot").agg(F.count(F.lit(1)).cast("double").alias("n"))
    per = g.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("slot", "n"))).alias("m"), F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("size"))
    return per.select("id", F.transform(F.sequence(F.lit(0).cast("long"), F.lit(dim - 1).cast("long")), lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0)) / F.col("size")).alias("vec"))


def doc_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    return hashed_text(table(spark, sf_dir, "documents"), "doc_id", dim)


def benchmark_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    return hashed_text(table(spark, sf_dir, "benchmark"), "item_id", dim)


def line_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four scaled measures of every line; dense ids in a total order of the lines."""
    from .core.types import densify

    line = table(spark, sf_dir, "lineitem")
    top = line.agg(F.max("l_extendedprice").alias("top"))
    key = F.struct("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity")
    vec = F.array(F.col("l_quantity") / 50, F.col("l_extendedprice") / F.col("top"), F.col("l_discount") * 10, F.col("l_tax") * 12.5)
    return densify(line.crossJoin(F.broadcast(top)).select(key.alias("key"), vec.alias("vec")), "key").select("id", "vec")


def event_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    kinds = ["view", "click", "purchase", "signup", "error"]
    e = table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("id")).agg(*[F.count_if(F.col("event_type") == k).cast("double").alias(k) for k in kinds], F.avg("value").alias("v"))
    return e.select("id", F.array(*kinds, "v").alias("vec"))


def query_set(v: DataFrame, every: int = EVERY) -> DataFrame:
    """The stated query set: rows whose id ``every`` divides."""
    return v.where(F.col("id") % every == 0).select(F.col("id").alias("qid"), "vec")


def dense_rank_ids(v: DataFrame) -> DataFrame:
    """Ids replaced by their rank inside a set of bounded size (tests)."""
    return v.withColumn("id", F.row_number().over(Window.orderBy("id")).cast("long") - 1)
