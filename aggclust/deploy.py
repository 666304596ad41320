"""Make the package importable on Python workers, wherever the session was started from."""

from __future__ import annotations

import hashlib
import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

_sent: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send the package's sources to the executors once per application."""
    app = spark.sparkContext.applicationId
    if app in _sent:
        return
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    files = sorted(os.path.join(d, f) for d, _, names in os.walk(os.path.join(root, "aggclust")) for f in names if f.endswith(".py"))
    files += sorted(os.path.join(root, f) for f in os.listdir(root) if f.endswith(".py"))
    digest = hashlib.sha256(b"".join(open(f, "rb").read() for f in files)).hexdigest()[:16]
    path = os.path.join(tempfile.mkdtemp(prefix="aggclust-"), f"aggclust_{digest}.zip")
    with zipfile.ZipFile(path, "w") as z:
        for f in files:
            z.write(f, os.path.relpath(f, root))
    spark.sparkContext.addPyFile(path)
    _sent.add(app)
