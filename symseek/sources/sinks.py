"""Results to storage: Parquet by pattern, packed records, and streaming sinks that count a batch once."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from symseek.operators.measures import pack_result, unpack_result


def write_by_pattern(kept: DataFrame, path: str, *, mode: str = "append") -> None:
    """Occurrences as Parquet, a folder for each pattern. A pattern with many rows is written by many tasks."""
    kept.write.mode(mode).partitionBy("pattern_id").parquet(path)


def read_by_pattern(spark: SparkSession, path: str, *patterns: int) -> DataFrame:
    """All occurrences, or those of some patterns; other patterns' folders aren't read."""
    rows = spark.read.parquet(path)
    return rows.where(F.col("pattern_id").isin(*patterns)) if patterns else rows


def packed(kept: DataFrame) -> DataFrame:
    """stream_id, pattern_id, packed: a number a result."""
    return kept.select("stream_id", "pattern_id", pack_result(F.col("start"), F.col("len"), F.col("dist")).alias("packed"))


def unpacked(rows: DataFrame) -> DataFrame:
    return rows.select("stream_id", "pattern_id", unpack_result(F.col("packed")).alias("r")).select("stream_id", "pattern_id", "r.start", "r.len", "r.dist")


def stream_to_parquet(kept: DataFrame, path: str, state: str, *, as_records: bool = False, **trigger) -> StreamingQuery:
    """A streaming frame of occurrences to Parquet by pattern; as_records: packed. state: the folder of the query's progress, on shared storage."""
    rows = packed(kept.where("not late")) if as_records else kept
    return rows.writeStream.format("parquet").partitionBy("pattern_id").option("path", path).option("checkpointLocation", state).outputMode("append").trigger(**(trigger or {"availableNow": True})).start()


def stream_by_batch(kept: DataFrame, path: str, state: str, *, change: Callable[[DataFrame], DataFrame] | None = None, **trigger) -> StreamingQuery:
    """Each micro-batch to a folder of its number, replaced as a whole if the batch comes again after a failure, so that it counts once."""

    def write(batch: DataFrame, number: int) -> None:
        (change(batch) if change else batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return kept.writeStream.foreachBatch(write).option("checkpointLocation", state).outputMode("append").trigger(**(trigger or {"availableNow": True})).start()
