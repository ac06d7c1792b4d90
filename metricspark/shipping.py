"""The package sent along with the jobs, so that Python workers find it wherever they start."""
from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give the session's workers this package, once an application."""
    sc = spark.sparkContext
    if sc.applicationId in _sent:
        return
    home = Path(__file__).resolve().parent
    archive = Path(tempfile.mkdtemp(prefix="metricspark-")) / f"{home.name}.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for p in sorted(home.rglob("*.py")):
            z.write(p, p.relative_to(home.parent))
    sc.addPyFile(str(archive))
    _sent.add(sc.applicationId)
