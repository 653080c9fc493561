"""Makes the package known to the Python workers of a given session."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> None:
    """Send the package to all executors, once a context: their workers need not find it on a path of their own."""
    context, root = spark.sparkContext, Path(__file__).parent
    if getattr(context, "_blockgraph_shipped", False) or not root.is_dir():
        return
    archive = Path(tempfile.mkdtemp(prefix="blockgraph-code-")) / "blockgraph.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as out:
        for file in sorted(root.rglob("*.py")):
            out.write(file, file.relative_to(root.parent))
    context.addPyFile(str(archive))
    context._blockgraph_shipped = True
