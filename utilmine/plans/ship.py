"""The package on the workers' path, for sessions that were started elsewhere."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

PACKAGE = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def to_workers(spark: SparkSession) -> SparkSession:
    """Adds the package to the session's Python files, once for each Spark context, so that Python workers can import it anywhere."""
    sc = spark.sparkContext
    if not getattr(sc, "_utilmine_shipped", False):
        path = os.path.join(tempfile.mkdtemp(prefix="utilmine-"), "utilmine.zip")
        with zipfile.ZipFile(path, "w") as z:
            for folder, _, names in os.walk(PACKAGE):
                for n in names:
                    if n.endswith(".py"):
                        full = os.path.join(folder, n)
                        z.write(full, os.path.relpath(full, os.path.dirname(PACKAGE)))
        sc.addPyFile(path)
        sc._utilmine_shipped = True
    return spark
