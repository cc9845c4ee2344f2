"""Continuous imputation of a stream.

A shard's state holds the open windows' rows, the cache and the weights. When the watermark passes a window's end,
that window is imputed, its rows come out, and what it leaves to the next is kept; late rows are dropped and no closed
window is trained again. Seeds depend on shard and window only, so a restart from the checkpoint gives the same.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from streamfill.plans.continuous import Chain
from streamfill.plans.impute import Options
from streamfill.schema import attributes
from streamfill.sources.tables import STREAM_BITS, joined_id


def window_rows(events: DataFrame, seconds: int, bucket: int, names: tuple[str, ...], *, stream: str = "user_id", kind: str = "event_type", value: str = "value", time_col: str = "ts", lateness: str = "1 day") -> DataFrame:
    """Readings to instances within the stream: one row a stream and bucket, closed by the watermark."""
    cents = F.round(F.col(value) * 100).cast("long")
    mean = lambda n: F.floor(F.try_divide(F.sum(F.when(F.col(kind) == n, cents)) * 100, F.count_if(F.col(kind) == n))).cast("double")
    rows = events.withWatermark(time_col, lateness).groupBy(F.window(time_col, f"{bucket} seconds").alias("w"), F.col(stream).cast("string").alias("stream_id")).agg(*(mean(n).alias(f"x{d}") for d, n in enumerate(names)))
    start = F.unix_seconds(F.col("w.start"))
    return rows.select(F.col("w.end").alias("closes"), F.floor(start / seconds).cast("long").alias("window_id"), "stream_id", joined_id(F.floor(start / bucket), F.col("stream_id").cast("long"), STREAM_BITS).alias("inst_id"), *(f"x{d}" for d in range(len(names))))


def deduplicated(events: DataFrame, key: str = "event_id", time_col: str = "ts", lateness: str = "1 day") -> DataFrame:
    return events.withWatermark(time_col, lateness).dropDuplicatesWithinWatermark([key])


def flushed(rows: DataFrame, time_col: str = "ts", after: str = "400 days") -> DataFrame:
    """One row past the last event time, whose text columns say flush: at a stream's end it moves the watermark on, so
    that the last windows close too."""
    last = rows.agg((F.max(time_col) + F.expr(f"INTERVAL {after}")).alias("last"))
    text = {f.name for f in rows.schema if f.dataType.typeName() == "string"}
    made = [F.col("last").alias(c) if c == time_col else (F.lit("flush") if c in text else F.lit(None).cast(rows.schema[c].dataType)).alias(c) for c in rows.columns]
    return last.select(*made)


def split_late(rows: DataFrame, watermark: int, position: str = "t") -> tuple[DataFrame, DataFrame]:
    """(rows at or past the watermark, the late ones): late rows as an output of their own, as closed windows are never
    trained again."""
    late = F.col(position) < watermark
    return rows.where(~late | F.col(position).isNull()), rows.where(late)


def live(rows: DataFrame, o: Options, seconds: int, scale: tuple[tuple[float, ...], tuple[float, ...]], *, time_col: str = "ts", lateness: str = "0 seconds", shards: int = 1) -> DataFrame:
    """Imputed rows of closed windows. rows: a stream of window_id, stream_id, inst_id, x... and an event time.
    scale: means and deviations of the attributes, as a stream has no last row to fit them on."""
    xs = attributes(rows)
    mean, deviation = np.array(scale[0]), np.array(scale[1])
    names = ["window_id", "stream_id", "inst_id", *xs, "cached"]

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        done, pending, cache, theta = pickle.loads(state.get[0]) if state.exists else (-(1 << 62), {}, None, None)
        chain = Chain(o, int(key[0]))
        chain.cache, chain.theta = cache, theta
        for frame in frames:
            for w, part in frame.groupby("window_id"):
                if w > done:
                    pending.setdefault(int(w), []).append(part[["stream_id", "inst_id", *xs]])
        mark = state.getCurrentWatermarkMs() / 1000
        for w in sorted(w for w in pending if (w + 1) * seconds <= mark):
            part = pd.concat(pending.pop(w)).sort_values("inst_id")
            x = (part[xs].to_numpy(np.float64) - mean) / deviation
            # codes must not depend on what else is in the batch
            streams = np.unique(part["stream_id"].to_numpy(str), return_inverse=True)[1]
            out, cached = chain.step(w, x, streams, part["inst_id"].to_numpy())
            made = part.assign(window_id=w, cached=cached)
            made[xs] = np.where(np.isnan(x), out.x * deviation + mean, part[xs].to_numpy(np.float64))
            done = w
            yield made[names]
        state.update((pickle.dumps((done, pending, chain.cache, chain.theta)),))
        if pending:
            state.setTimeoutTimestamp(max(int((min(pending) + 1) * seconds * 1000), state.getCurrentWatermarkMs() + 1))

    out = "window_id long, stream_id string, inst_id long, " + ", ".join(f"{c} double" for c in xs) + ", cached int"
    dealt = rows.withColumn("stream_id", F.col("stream_id").cast("string")).withWatermark(time_col, lateness).withColumn("shard", F.pmod(F.xxhash64("stream_id"), F.lit(shards)).cast("int"))
    return dealt.groupBy("shard").applyInPandasWithState(step, out, "state binary", "append", GroupStateTimeout.EventTimeTimeout)


def by_batches(batches: DataFrame, sink: str, o: Options, scale: tuple[tuple[float, ...], tuple[float, ...]], folder: str, shards: int = 1):
    """The same chains by micro-batches, each holding whole windows, for sources that deliver a window at a time; returns
    the started query.

    Shards meet their state in a cogroup, so rows stay on the executors. What a batch makes, rows and states, is
    written under its number before anything else reads it, and written over if the batch is run again: a restart takes
    the state of the batch before and gives the same rows once.
    """
    xs = attributes(batches)
    mean, deviation = np.array(scale[0]), np.array(scale[1])
    names = ["shard", "window_id", "stream_id", "inst_id", *xs, "cached", "state"]
    schema = "shard int, window_id long, stream_id string, inst_id long, " + ", ".join(f"{c} double" for c in xs) + ", cached int, state binary"

    def chain_on(key: tuple, rows: pd.DataFrame, states: pd.DataFrame) -> pd.DataFrame:
        chain = Chain(o, int(key[0]))
        if len(states):
            chain.cache, chain.theta = pickle.loads(states["state"].iloc[0])
        made = []
        for w, part in rows.sort_values(["window_id", "inst_id"]).groupby("window_id"):
            x = (part[xs].to_numpy(np.float64) - mean) / deviation
            streams = np.unique(part["stream_id"].to_numpy(str), return_inverse=True)[1]
            out, cached = chain.step(int(w), x, streams, part["inst_id"].to_numpy())
            part = part.assign(cached=cached, state=None)
            part[xs] = np.where(np.isnan(x), out.x * deviation + mean, part[xs].to_numpy(np.float64))
            made.append(part[names])
        state = {c: [None] for c in names} | {"shard": [int(key[0])], "state": [pickle.dumps((chain.cache, chain.theta))]}
        if made:  # the state rides on a row of its own, typed like the others
            state |= {"stream_id": [""], "inst_id": [0], "window_id": [0], "cached": [0]} | {c: [0.0] for c in xs}
        return pd.concat([*made, pd.DataFrame(state)[names]], ignore_index=True) if made else pd.DataFrame(state)[names]

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        rows = batch.withColumn("stream_id", F.col("stream_id").cast("string"))
        rows = rows.select(F.pmod(F.xxhash64("stream_id"), F.lit(shards)).cast("int").alias("shard"), "window_id", "stream_id", "inst_id", *xs)
        made = f"{folder}/made"
        last = number - 1
        states = spark.read.schema(schema).parquet(f"{made}/batch={last}").where("state is not null") if last >= 0 else spark.createDataFrame([], schema)
        out = rows.groupBy("shard").cogroup(states.select("shard", "state").groupBy("shard")).applyInPandas(chain_on, schema)
        out.write.mode("overwrite").parquet(f"{made}/batch={number}")
        done = spark.read.schema(schema).parquet(f"{made}/batch={number}").where("state is null")
        done.drop("state", "shard").write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return batches.writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
