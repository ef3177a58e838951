"""Making this package importable in Python workers that were started without it on their path."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_ROOT = Path(__file__).resolve().parents[2]


ARROW_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def ship(spark: SparkSession, rows_at_once: int = 2_000) -> None:
    """Send the package through Spark's file server, once per application, unless the workers find it anyway.

    Also bounds the rows of an Arrow batch (a runtime setting; smaller ones stay): a batch is held by the JVM and by Python at
    once, and rows here carry whole texts or sets."""
    if not 0 < int(spark.conf.get(ARROW_ROWS)) <= rows_at_once:
        spark.conf.set(ARROW_ROWS, str(rows_at_once))
    known = [Path(p).resolve() for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    sc = spark.sparkContext
    if _ROOT in known or Path.cwd().resolve() == _ROOT or getattr(sc, "_headcount_shipped", False):
        return
    target = Path(tempfile.mkdtemp()) / "headcount.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted((_ROOT / "headcount").rglob("*.py")):
            z.write(p, p.relative_to(_ROOT))
    sc.addPyFile(str(target))
    sc._headcount_shipped = True
