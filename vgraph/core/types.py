"""Schemas of the data model, entry checks and conversions between graph forms."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

LONG, INT, DBL, BOOL = T.LongType(), T.IntegerType(), T.DoubleType(), T.BooleanType()


def fields(**kinds) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in kinds.items()])


VECTORS = fields(id=LONG, vec=T.ArrayType(DBL))
ENTRY = fields(id=LONG, d2=DBL, fresh=BOOL, visited=BOOL)
LISTS = fields(src=LONG, nbrs=T.ArrayType(ENTRY), seen=T.ArrayType(LONG))
FLAT = fields(src=LONG, dst=LONG, rank=INT, d2=DBL)
INDEX = fields(src=LONG, nbrs=T.ArrayType(LONG), deg=INT)
LOCAL = fields(shard=INT, src=LONG, dst=LONG, rank=INT, d2=DBL)
ASSIGNED = fields(shard=INT, id=LONG, choice=INT, d2=DBL)


def as_vectors(df: DataFrame, id_col: str = "id", vec_col: str = "vec", check: bool = True) -> DataFrame:
    """(id long, vec array<double>) or an error: no null or NaN component, one length for all, no repeated id.

    Float, double and byte arrays are accepted. The checks are aggregates over the table (one pass, nothing collected but
    three numbers and a count)."""
    v = df.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"))
    if not check:
        return v
    bad = F.col("id").isNull() | F.col("vec").isNull() | F.exists("vec", lambda x: x.isNull() | F.isnan(x))
    r = v.agg(F.count_if(bad).alias("bad"), F.min(F.size("vec")).alias("low"), F.max(F.size("vec")).alias("high")).first()
    if r.bad:
        raise ValueError(f"{r.bad} rows have a null id, a null vector or a null or NaN component")
    if r.low != r.high:
        raise ValueError(f"vectors of {r.low} and {r.high} components")
    if v.groupBy("id").count().where("count > 1").take(1):
        raise ValueError("an id occurs twice")
    return v


def densify(df: DataFrame, key: str) -> DataFrame:
    """Adds ``id`` 0..n-1 in order of ``key`` without a global window: range partitions, their sizes, and offsets."""
    from .iterate import step

    # row_number would meet in one task; each range partition numbers its own rows and adds the rows before it
    p = step(df.repartitionByRange(key).sortWithinPartitions(key).withColumn("__m", F.monotonically_increasing_id()))
    p = p.withColumn("__part", F.shiftright("__m", 33)).withColumn("__row", F.col("__m").bitwiseAND(F.lit((1 << 33) - 1)))
    from pyspark.sql.window import Window

    size = p.groupBy("__part").agg(F.count(F.lit(1)).alias("n"))
    before = size.select("__part", (F.sum("n").over(Window.orderBy("__part")) - F.col("n")).alias("__before"))  # one row for each partition
    return p.join(F.broadcast(before), "__part").withColumn("id", F.col("__before") + F.col("__row")).drop("__m", "__part", "__row", "__before")


def flat(lists: DataFrame) -> DataFrame:
    """(src, dst, rank, d2) from nested lists; rank starts at 1."""
    return lists.select("src", F.posexplode("nbrs").alias("p", "e")).select("src", F.col("e.id").alias("dst"), (F.col("p") + 1).alias("rank"), F.col("e.d2").alias("d2"))


def nested(edges: DataFrame, fresh: bool = True) -> DataFrame:
    """Nested lists in (d2, id) order from (src, dst, d2)."""
    e = F.struct(F.col("d2"), F.col("dst").alias("id"))
    g = edges.groupBy("src").agg(F.array_sort(F.collect_list(e)).alias("s"))
    entry = F.transform("s", lambda x: F.struct(x["id"].alias("id"), x["d2"].alias("d2"), F.lit(fresh).alias("fresh"), F.lit(False).alias("visited")))
    return g.select("src", entry.alias("nbrs"), F.array().cast("array<bigint>").alias("seen"))
