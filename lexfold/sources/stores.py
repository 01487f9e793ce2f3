"""Sources and sinks: plain files of records, folded stores, prompt exports, a data source for folded files."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from ..functions.text import unfold_expr

RECORD = "corpus string, rec_id long, ts timestamp, text string"


def read_records(spark: SparkSession, path: str, kind: str = "parquet", corpus: str = "text") -> DataFrame:
    """Records from parquet, json or csv files of the record schema, or from text files, one record a line."""
    if kind == "text":
        lines = spark.read.text(path).select("value", "_metadata.file_path", "_metadata.file_block_start")
        return lines.select(F.lit(corpus).alias("corpus"), F.monotonically_increasing_id().alias("rec_id"), F.lit(None).cast("timestamp").alias("ts"), F.col("value").alias("text"))
    reader = spark.read.schema(RECORD)
    return {"parquet": reader.parquet, "json": reader.json, "csv": lambda p: reader.option("header", True).option("escape", '"').option("multiLine", True).csv(p)}[kind](path)


def write_records(df: DataFrame, path: str, kind: str = "parquet") -> None:
    w = df.write.mode("overwrite")
    if kind == "csv":
        w.option("header", True).option("escape", '"').csv(path)
    else:
        {"parquet": w.parquet, "json": w.json}[kind](path)


def write_folded(folded: DataFrame, path: str) -> None:
    """A folded store by corpus; rows of a corpus are brought together, a large one split by Spark."""
    folded.hint("rebalance", "corpus").write.mode("overwrite").partitionBy("corpus").parquet(path)


def read_folded(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def read_unfolded(spark: SparkSession, path: str) -> DataFrame:
    """shard_id, corpus, text of a folded store; unfolding is an expression, so filters on corpus prune files."""
    return read_folded(spark, path).select("shard_id", "corpus", F.array_join(unfold_expr("folded", "legend"), " ").alias("text"))


def write_prompts(prompts: DataFrame, path: str) -> None:
    prompts.select("shard_id", "reader", "system", "user").write.mode("overwrite").json(path)


class _FilePartition(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _FoldedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, at = fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path.removeprefix("file:"))
        files = store.get_file_info(fs.FileSelector(at, recursive=True))
        return [_FilePartition(f.path) for f in files if f.path.endswith(".parquet")]

    def read(self, partition: _FilePartition) -> Iterator[tuple]:
        import pyarrow.parquet as pq
        from pyarrow import fs

        store = fs.FileSystem.from_uri(self.path)[0] if "://" in self.path else fs.LocalFileSystem()
        corpus = next((p.removeprefix("corpus=") for p in partition.path.split("/") if p.startswith("corpus=")), None)
        for batch in pq.ParquetFile(partition.path, filesystem=store).iter_batches(64, columns=["shard_id", "folded", "legend"]):
            for row in batch.to_pylist():
                entries = {e["marker"]: e["units"] for e in row["legend"]}
                yield row["shard_id"], corpus, " ".join(u for x in row["folded"] for u in entries.get(x, [x]))


class FoldedSource(DataSource):
    """spark.read.format("lexfold").load(path): the plain text of a folded store."""

    @classmethod
    def name(cls) -> str:
        return "lexfold"

    def schema(self) -> str:
        return "shard_id string, corpus string, text string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _FoldedReader(self.options)
