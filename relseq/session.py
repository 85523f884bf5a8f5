"""What a session needs to run this package's functions on its workers."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[int] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Lets Python workers find the package where it is not installed: on the driver's machine by its path, elsewhere
    by an archive that every worker fetches once."""
    root = Path(__file__).resolve().parent.parent
    context = spark.sparkContext
    known = os.environ.get("PYTHONPATH", "").split(os.pathsep) + context.environment.get("PYTHONPATH", "").split(os.pathsep)
    if str(root) not in known:
        context.environment["PYTHONPATH"] = os.pathsep.join(x for x in (str(root), context.environment.get("PYTHONPATH", "")) if x)
    if not context.master.startswith("local") and id(context) not in _sent:
        _sent.add(id(context))
        context.addPyFile(archive(root))
    return spark


def archive(root: Path) -> str:
    """The package's modules as a zip file."""
    path = Path(tempfile.mkdtemp(prefix="relseq-")) / "relseq.zip"
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as out:
        for file in sorted((root / "relseq").rglob("*.py")):
            out.write(file, file.relative_to(root))
    return str(path)
