"""Makes the package importable for Python workers that do not share the driver's import path."""

from __future__ import annotations

import os
import re
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_SENT: set[str] = set()


BATCH_BYTES = 8 << 20
_LIMIT = "spark.sql.execution.arrow.maxBytesPerBatch"


def bound_batches(spark: SparkSession) -> None:
    """Hold Arrow batches to a number of bytes, not only of rows: ten thousand long texts at once would not fit a worker. A lower limit of the session stays."""
    now = re.fullmatch(r"(\d+)b?", spark.conf.get(_LIMIT) or "")
    if not now or not 0 < int(now[1]) <= BATCH_BYTES:
        spark.conf.set(_LIMIT, str(BATCH_BYTES))


def ship(spark: SparkSession) -> None:
    """Send the package to the executors once a session, unless their path already has it; and bound what a worker gets at once."""
    bound_batches(spark)
    root = Path(__file__).resolve().parents[2]
    app = spark.sparkContext.applicationId
    on_path = [os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    if app in _SENT or str(root) in on_path:
        return
    target = Path(tempfile.mkdtemp(prefix="twinfold-code-")) / "twinfold_code.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted((root / "twinfold").rglob("*.py")):
            z.write(p, p.relative_to(root))
    spark.sparkContext.addPyFile(str(target))
    _SENT.add(app)
