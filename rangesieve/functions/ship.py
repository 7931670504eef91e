"""Send this package to the executors, so that Python functions can be unpickled there."""

from __future__ import annotations

import os
import tempfile
import threading
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


#: Jobs run beside each other, and Spark takes a file of one name once.
_ONE = threading.Lock()


def ship(spark: SparkSession) -> None:
    """Once per context. The archive is made on the driver and fetched from it by Spark."""
    with _ONE:
        _send(spark.sparkContext)


def _send(sc) -> None:
    if getattr(sc, "_rangesieve_sent", False):
        return
    root = Path(__file__).resolve().parents[1]
    target = os.path.join(os.path.realpath(tempfile.mkdtemp(prefix="rangesieve_code_")), "rangesieve_filters.zip")
    with zipfile.ZipFile(target, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    sc.addPyFile(target)
    sc._rangesieve_sent = True
