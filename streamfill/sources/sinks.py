"""Where imputed chunks, cached rows and model states go."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def write_windows(df: DataFrame, path: str) -> None:
    """Partitioned by window; writing a window again replaces it and no other."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("window_id").parquet(path)


def to_memory(stream: DataFrame, name: str, mode: str = "append"):
    return stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()


def foreach_batch(stream: DataFrame, step: Callable[[DataFrame, int], None], checkpoint: str):
    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def save_state(state: DataFrame, path: str) -> None:
    """States or cached rows, keyed by shard and window."""
    state.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("window_id").parquet(path)


def load_state(spark: SparkSession, path: str, window_id: int) -> DataFrame:
    return spark.read.parquet(path).where(f"window_id = {int(window_id)}")
