"""Send this package's modules to the executors of a session that started without them on its path."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parents[1]


def ship(spark: SparkSession) -> None:
    """Idempotent per Spark context."""
    sc = spark.sparkContext
    if getattr(sc, "_vgraph_shipped", False):
        return
    path = Path(tempfile.mkdtemp(prefix="vgraph-ship-")) / "vgraph_modules.zip"
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(ROOT.rglob("*.py")):
            z.write(p, str(p.relative_to(ROOT.parent)))
    sc.addPyFile(str(path))
    sc._vgraph_shipped = True
