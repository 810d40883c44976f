"""Python workers get this package from the driver, so a session started elsewhere needs no path set for it."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

_SENT: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Add the package to the application's Python files, once."""
    app = spark.sparkContext.applicationId
    if app not in _SENT:
        _SENT.add(app)
        root = os.path.dirname(os.path.abspath(__file__))
        path = os.path.join(tempfile.mkdtemp(prefix="coltypes-"), "coltypes_package.zip")
        with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
            for folder, _, names in os.walk(root):
                for name in sorted(n for n in names if n.endswith(".py")):
                    file = os.path.join(folder, name)
                    z.write(file, os.path.relpath(file, os.path.dirname(root)))
        spark.sparkContext.addPyFile(path)
    return spark
