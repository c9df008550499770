"""Makes this package importable in Python workers of a session that was started elsewhere."""

from __future__ import annotations

import hashlib
import io
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[tuple[str, str]] = set()


def ship(spark: SparkSession) -> None:
    """Send the package's sources to the executors, once for each application and state of the sources."""
    top = Path(__file__).resolve().parent
    if ".zip" in str(top):
        return
    held = io.BytesIO()
    with zipfile.ZipFile(held, "w") as z:
        for p in sorted(top.rglob("*.py")):
            z.writestr(zipfile.ZipInfo(str(p.relative_to(top.parent))), p.read_bytes())
    mark = hashlib.sha256(held.getvalue()).hexdigest()[:16]
    app = spark.sparkContext.applicationId
    if (app, mark) in _sent:
        return
    path = Path(tempfile.mkdtemp(prefix="sources-")) / f"subsetheavy-{mark}.zip"
    path.write_bytes(held.getvalue())
    spark.sparkContext.addPyFile(str(path))
    _sent.add((app, mark))
