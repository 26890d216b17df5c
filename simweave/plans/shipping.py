"""Makes this package importable on the executors of a session that was started without it."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_SENT: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send the package's modules to the executors, once an application; Spark serves the archive from the driver."""
    context = spark.sparkContext
    if context.applicationId in _SENT:
        return
    home = Path(__file__).resolve().parent.parent
    archive = Path(tempfile.mkdtemp(prefix="simweave-code-")) / "simweave.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as out:
        for path in sorted(home.rglob("*.py")):
            out.write(path, path.relative_to(home.parent))
    context.addPyFile(str(archive))
    _SENT.add(context.applicationId)
