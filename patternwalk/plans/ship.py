"""Send this package to the workers of a session that cannot import it by themselves."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parents[2]
_SENT: set[str] = set()


def reachable() -> bool:
    """Whether workers find the package where this process does: by PYTHONPATH, or by a shared working directory."""
    own = [p or "." for p in os.environ.get("PYTHONPATH", "").split(os.pathsep)]
    return any(Path(p).resolve() == ROOT for p in own) or Path.cwd() == ROOT


def ship(spark: SparkSession) -> None:
    """Once an application: the package as a zip through Spark's own file server."""
    app = spark.sparkContext.applicationId
    if app in _SENT or reachable():
        return
    path = Path(tempfile.mkdtemp(prefix="patternwalk-")) / "patternwalk.zip"
    with zipfile.ZipFile(path, "w") as out:
        for f in sorted((ROOT / "patternwalk").rglob("*.py")):
            out.write(f, f.relative_to(ROOT))
    spark.sparkContext.addPyFile(str(path))
    _SENT.add(app)
