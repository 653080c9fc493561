"""Where iterations keep their state: written tables in the shared folder, so a lost executor re-reads them."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or context._jsc.sc().getCheckpointDir().getOrElse(None)
    if not folder:
        context.setCheckpointDir(tempfile.mkdtemp(prefix="blockgraph-state-"))
        folder = context._jsc.sc().getCheckpointDir().get()
    return folder.rstrip("/")


def write_state(df: DataFrame, label: str) -> DataFrame:
    """df as a written table; cuts the lineage of the rounds before."""
    path = f"{shared_folder(df.sparkSession)}/state/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._state_path = path
    return out


def drop_state(df: DataFrame | None) -> None:
    path = getattr(df, "_state_path", None)
    if path:
        place = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(place, True)
