"""Makes this package importable by the Python workers of a session that was started without it on its path."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_ROOT = Path(__file__).resolve().parent.parent
_DONE: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Sends the package to the workers as a zip file, once for each application, unless they find it anyway."""
    context = spark.sparkContext
    paths = [Path(p).resolve() for p in [os.getcwd(), *os.environ.get("PYTHONPATH", "").split(":")] if p]
    if context.applicationId in _DONE or _ROOT in paths:
        return
    target = os.path.join(tempfile.mkdtemp(prefix="localcoef-code-"), "localcoef_code.zip")
    with zipfile.ZipFile(target, "w") as z:
        for f in (_ROOT / "localcoef").rglob("*.py"):
            z.write(f, f.relative_to(_ROOT))
    context.addPyFile(target)
    _DONE.add(context.applicationId)
