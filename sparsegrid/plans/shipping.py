"""Sending this package to the executors."""

from __future__ import annotations

import shutil
import tempfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Makes the package importable in the workers of a session, once for each application.

    Functions that run on executors live in modules; where the cluster does not
    have the package installed, they need it sent.
    """
    app = spark.sparkContext.applicationId
    if app not in _sent:
        package = Path(__file__).resolve().parent.parent
        target = Path(tempfile.mkdtemp(prefix="sparsegrid-package-")) / package.name
        spark.sparkContext.addPyFile(shutil.make_archive(str(target), "zip", package.parent, package.name))
        _sent.add(app)
