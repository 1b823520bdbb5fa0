"""Edge lists in files, a partitioned generator source, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from starfold.plans.loop import ComponentResult
from starfold.sources.graphs import normalize_edges


def edge_list(spark: SparkSession, path: str, fmt: str = "text") -> DataFrame:
    """Simple edges from ``text`` (white space between ids, # comments, or lines 'a u v w'), csv, json, orc or parquet."""
    if fmt == "text":
        lines = spark.read.text(path).where(~F.col("value").rlike("^\\s*([#cp%]|$)"))
        parts = F.split(F.trim(F.regexp_replace("value", "^\\s*[ae]\\s+", "")), "[\\s,]+")
        return normalize_edges(lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("a"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("b")))
    df = spark.read.schema("a long, b long").format(fmt).load(path) if fmt in ("csv", "json") else spark.read.format(fmt).load(path)
    return normalize_edges(df)


class SyntheticGraphSource(DataSource):
    """``spark.read.format("synthetic_graph")`` with options family (path, star, tree), size and partitions."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_graph"

    def schema(self) -> str:
        return "a long, b long"

    def reader(self, schema) -> DataSourceReader:
        return _SyntheticReader(self.options)


class _SyntheticReader(DataSourceReader):
    def __init__(self, options):
        self.family = options.get("family", "path")
        self.size = int(options.get("size", "1024"))
        self.parts = int(options.get("partitions", "8"))
        if self.family not in ("path", "star", "tree"):
            raise ValueError("family is path, star or tree")

    def partitions(self):
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition):
        step = -(-self.size // self.parts)
        parent = {"path": lambda i: i - 1, "star": lambda i: 0, "tree": lambda i: (i - 1) // 2}[self.family]
        for i in range(max(1, partition.value * step), min(self.size, (partition.value + 1) * step)):
            yield parent(i), i


def save_labels(result: ComponentResult, table: str, buckets: int = 32) -> None:
    """Labels as a table bucketed by vertex, so that later joins on it need no exchange."""
    result.labels.write.bucketBy(buckets, "vertex").sortBy("vertex").mode("overwrite").saveAsTable(table)


def save_metrics(result: ComponentResult, path: str, spark: SparkSession) -> None:
    result.steps(spark).write.mode("append").parquet(path)


def register(result: ComponentResult, prefix: str, spark: SparkSession) -> None:
    """Views ``<prefix>_labels`` and ``<prefix>_steps`` for SQL users."""
    result.labels.createOrReplaceTempView(f"{prefix}_labels")
    result.steps(spark).createOrReplaceTempView(f"{prefix}_steps")
