"""Streams of events: windows, late rows, joins, duplicates, and shards that close by budget."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.fold import fold
from ..operators.kernel import Options
from ..operators.lineage import shared_dir
from ..operators.shards import assign_shards_count, shard_units

LINE = ("INFO service=events user", "user_id", "performed", "event_type", "with value", "value", "props", "props")


def events_stream(spark: SparkSession, path: str, delay: str = "1 hour", files_per_trigger: int = 4) -> DataFrame:
    """Events with a watermark; ts is cast, as a watermark needs a timestamp with a zone."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory():
        d = reader.parquet(path)
    else:  # a stream reads folders: the file's own, with the other files left out
        folder, name = path.rsplit("/", 1)
        d = reader.option("pathGlobFilter", name).parquet(folder)
    return d.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def finished(stream: DataFrame, mode: str = "append", each: Callable[[DataFrame, int], DataFrame] | None = None) -> DataFrame:
    """Run a stream over what is there now into files of the shared folder, and read them back.

    complete: the last result alone; append: the results of all batches. Each batch writes a folder of
    its own number, so a repeated batch replaces its own output and nothing else.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        out = each(batch, number) if each else batch
        out.write.mode("overwrite").parquet(f"{base}/out/batch={0 if mode == 'complete' else number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").foreachBatch(put).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{base}/out").drop("batch")


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    d = events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return d.select(F.unix_seconds("w.start").alias("start_s"), "event_type", "n", F.round("total", 2).alias("total"))


def sliding(events: DataFrame, size: str = "12 hours", slide: str = "6 hours") -> DataFrame:
    d = events.groupBy(F.window("ts", size, slide).alias("w")).agg(F.count("*").alias("n"))
    return d.select(F.unix_seconds("w.start").alias("start_s"), "n")


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    d = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return d.select("user_id", F.unix_seconds("w.start").alias("start_s"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def clicks_with_purchases(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: purchases of the same user up to an hour after a click."""
    c = events.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("click_ts"), F.col("event_id").alias("click_id"))
    p = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("buy_ts"), F.col("event_id").alias("buy_id"))
    close = (F.col("u") == F.col("user_id")) & (F.col("buy_ts") >= F.col("click_ts")) & (F.col("buy_ts") <= F.col("click_ts") + F.expr(f"interval {within}"))
    return c.join(p, close).select("user_id", "click_id", "buy_id")


def rendered(events: DataFrame) -> DataFrame:
    words = [F.lit(w) if i % 2 == 0 else F.col(w).cast("string") for i, w in enumerate(LINE)]
    line = F.concat_ws(" ", F.date_format("ts", "yyyy-MM-dd'T'HH:mm:ss"), *words)
    return events.select(F.concat(F.lit("ev_"), "event_type").alias("corpus"), F.col("event_id").alias("rec_id"), "ts", line.alias("text"))


def fold_batch(options: Options, count: int = 2000) -> Callable[[DataFrame, int], DataFrame]:
    """Shards of a micro-batch folded at once; their ids hold its number, so no later batch uses them again."""
    return lambda batch, number: fold(shard_units(assign_shards_count(batch.withColumn("part", F.lit(number)), count)), options)


SHARD = "corpus string, first_rec long, n_recs long, text string"


def open_shards(records: DataFrame, count: int = 500, idle: str = "6 hours") -> DataFrame:
    """One open shard a corpus in state; it closes at `count` records, or when event time leaves it idle.

    State is bounded by count records a corpus. Which records share a shard follows the input's order.
    """
    wait_ms = int(pd.Timedelta(idle).total_seconds() * 1000)

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, texts, last_ms = state.get if state.exists else ([], [], 0)
        ids, texts = list(ids), list(texts)
        out = []

        def close(n: int) -> None:
            out.append((key[0], ids[0], n, "\n".join(texts[:n])))
            del ids[:n], texts[:n]

        if state.hasTimedOut:
            if ids:
                close(len(ids))
            state.remove()
        else:
            for f in frames:
                ids += f["rec_id"].tolist()
                texts += f["text"].tolist()
                last_ms = max(last_ms, int(f["ts"].max().timestamp() * 1000))
                while len(ids) >= count:
                    close(count)
            state.update((ids, texts, last_ms))
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), last_ms) + wait_ms + 1)
        if out:
            yield pd.DataFrame(out, columns=["corpus", "first_rec", "n_recs", "text"])

    return records.groupBy("corpus").applyInPandasWithState(run, SHARD, "ids array<long>, texts array<string>, last_ms long", "append", GroupStateTimeout.EventTimeTimeout)


def late_rows(stream: DataFrame) -> DataFrame:
    """(late): rows that a windowed count of the stream dropped behind its watermark."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    query = tumbling(stream).writeStream.outputMode("append").option("checkpointLocation", base).format("noop").trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = [int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"]]
    return spark.createDataFrame([(sum(dropped),)], "late long")
