"""Cut lineage between the rounds of an iterative method, in a folder that outlives executors."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession) -> str:
    """A fresh folder under ``spark.checkpoint.dir``; a temporary one only where that is unset on a local master."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = getattr(spark, "_vgraph_scratch", None)
        if base is None:
            base = spark._vgraph_scratch = tempfile.mkdtemp(prefix="vgraph-")
            atexit.register(shutil.rmtree, base, True)
    return f"{base.rstrip('/')}/vgraph-{uuid.uuid4().hex}"


def step(df: DataFrame) -> DataFrame:
    """``df`` written once and read back: a fixed result for everything that follows, at any executor loss."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
