"""Structured Streaming operators over (event_id, ts, user_id, event_type, value)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LATE = "1 hour"


def read(spark: SparkSession, path: str) -> DataFrame:
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def changes(events: DataFrame, late: str = LATE) -> DataFrame:
    """(event_id, ts, id, op, value): 'delete' for errors, 'upsert' for everything else, once per event id inside the watermark."""
    e = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return e.select("event_id", "ts", F.col("user_id").alias("id"), F.when(F.col("event_type") == "error", "delete").otherwise("upsert").alias("op"), "value")


def churn(ch: DataFrame, shards: int = 8, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """Changes by window and shard; rows later than the watermark are dropped."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return ch.groupBy(w.alias("w"), (F.col("id") % shards).alias("shard")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "shard", "n")


def churn_sessions(ch: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return ch.groupBy("id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("id", F.col("w.start").alias("start"), "n")


def follow_ups(events: DataFrame, within: str = "10 minutes", late: str = LATE) -> DataFrame:
    """A view and the purchases of its user that follow within an interval: a stream-stream join with bounded state."""
    v = events.where("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("ts").alias("vt"), F.col("event_id").alias("view_id")).withWatermark("vt", late)
    p = events.where("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("ts").alias("pt"), F.col("event_id").alias("purchase_id")).withWatermark("pt", late)
    return v.join(p, F.expr(f"vu = pu and pt >= vt and pt <= vt + interval {within}")).select("view_id", "purchase_id")


LATEST_OUT = "id long, ts timestamp, value double, op string"
LATEST_STATE = "ts timestamp, value double, op string"


def latest(ch: DataFrame) -> DataFrame:
    """Last change of every id so far (update mode): one small state row an id."""
    import pandas as pd

    def last(key, frames, state):
        best = state.get if state.exists else None
        for f in frames:
            r = f.sort_values("ts").iloc[-1]
            if best is None or r["ts"] >= pd.Timestamp(best[0]):
                best = (r["ts"].to_pydatetime(), float(r["value"]), str(r["op"]))
        state.update(best)
        yield pd.DataFrame({"id": [key[0]], "ts": [best[0]], "value": [best[1]], "op": [best[2]]})

    return ch.groupBy("id").applyInPandasWithState(last, LATEST_OUT, LATEST_STATE, "update", "NoTimeout")


def rebuild_on(ch: DataFrame, sizes: dict[int, int], bound: float, rebuild: Callable[[int], None], shards: int = 8):
    """A foreachBatch sink: counts distinct changed ids by shard since the shard's last build and rebuilds (never patches) those over the bound.

    The counters are one number a shard."""
    pending = dict.fromkeys(range(shards), 0)

    def batch(df: DataFrame, _: int) -> None:
        for r in df.groupBy((F.col("id") % shards).alias("shard")).agg(F.countDistinct("id").alias("n")).collect():
            pending[r.shard] += r.n
            if pending[r.shard] > bound * sizes.get(r.shard, 1):
                rebuild(int(r.shard))
                pending[r.shard] = 0

    return ch.writeStream.foreachBatch(batch)


def merge_arrivals(local: DataFrame, degree: int, path: str):
    """Local indexes that arrive as files are merged into the index under ``path``: each batch writes the merge as a new version."""
    from ..shard.merge import merge_locals

    def batch(df: DataFrame, n: int) -> None:
        spark = df.sparkSession
        new = df.select("src", "dst", "d2")
        if n > 0:
            new = new.union(spark.read.parquet(f"{path}/version={n - 1}").select("src", "dst", "d2"))
        merge_locals(new, degree).write.mode("overwrite").parquet(f"{path}/version={n}")

    return local.writeStream.foreachBatch(batch)
