"""Edge-list readers, sinks and a partitioned generator source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGE = "src long, dst long"


def read_edges(spark: SparkSession, path: str, kind: str = "csv", sep: str = "\t", comment: str = "#", schema: str = EDGE) -> DataFrame:
    """An edge list in csv or tsv (with comment lines), json, orc, parquet or plain text, with a fixed schema."""
    if kind == "csv":
        return spark.read.schema(schema).csv(path, sep=sep, comment=comment)
    if kind == "text":
        lines = spark.read.text(path).where(~F.trim("value").startswith(comment) & (F.trim("value") != ""))
        parts = F.split(F.trim("value"), r"\s+")
        return lines.select(F.get(parts, F.lit(0)).cast("long").alias("src"), F.get(parts, F.lit(1)).cast("long").alias("dst"))
    return getattr(spark.read.schema(schema), kind)(path)


def write_edges(edges: DataFrame, path: str, kind: str = "parquet") -> None:
    """Release sink: parquet or csv, one directory a replica where there are replicas."""
    writer = edges.write.mode("overwrite")
    if "replica" in edges.columns:
        writer = writer.partitionBy("replica")
    getattr(writer, kind)(path)


def bucketed(edges: DataFrame, table: str, buckets: int) -> DataFrame:
    """edges as a table bucketed and sorted by src, so that joins by src move the other side only."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)
    return edges.sparkSession.table(table)


class PlantedSource(DataSource):
    """spark.read.format("planted_graph"): a block graph over 0 .. n - 1, rows of sources dealt to partitions.

    Options: n, blocks, inside, across, seed, parts. Pairs are drawn by the gap to the next edge, so work grows with edges.
    """

    @classmethod
    def name(cls) -> str:
        return "planted_graph"

    def schema(self) -> str:
        return EDGE

    def reader(self, schema: object) -> DataSourceReader:
        return PlantedReader(self.options)


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.n, self.blocks, self.parts = int(options.get("n", 1000)), int(options.get("blocks", 4)), int(options.get("parts", 4))
        self.inside, self.across, self.seed = float(options.get("inside", 0.05)), float(options.get("across", 0.001)), int(options.get("seed", 1))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int]]:
        import numpy as np

        for src in range(partition.value, self.n, self.parts):
            rng = np.random.default_rng([self.seed, src])
            for block in range(self.blocks):
                first = src + 1 + (block - src - 1) % self.blocks
                members = np.arange(first, self.n, self.blocks)
                p = self.inside if block == src % self.blocks else self.across
                drawn = rng.binomial(len(members), p) if len(members) else 0
                for dst in np.sort(rng.choice(members, drawn, replace=False)) if drawn else ():
                    yield src, int(dst)
