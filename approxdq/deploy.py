"""Puts this package on the executors of a session that was started without it."""

from __future__ import annotations

import os
import tempfile
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import SparkSession

_SENT: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Sends the package's source once per application, so that Python workers can import it."""
    app = spark.sparkContext.applicationId
    if app not in _SENT:
        home = Path(__file__).resolve().parent
        path = os.path.join(tempfile.mkdtemp(), "approxdq_src.zip")
        with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
            for p in sorted(home.rglob("*.py")):
                z.write(p, f"approxdq/{p.relative_to(home)}")
        spark.sparkContext.addPyFile(path)
        _SENT.add(app)
    return spark


@contextmanager
def small_methods(spark: SparkSession) -> Iterator[None]:
    """Plans of jobs run within do without one generated method where it would exceed what the JVM compiles (8,000 bytes by
    default): subjects of many columns would else be interpreted."""
    key = "spark.sql.codegen.hugeMethodLimit"
    was = spark.conf.get(key)
    spark.conf.set(key, "8000")
    try:
        yield
    finally:
        spark.conf.set(key, was)
