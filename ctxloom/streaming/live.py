"""Structured Streaming: live context counts, adaptive functions per key, drift against a frozen model, state joins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ctxloom.operators.adapt import CDF_BITS, step_target, uniform_cdf


def event_source(spark: SparkSession, folder: str, schema, ts: str = "ts", delay: str = "1 hour", files_per_trigger: int = 1) -> DataFrame:
    """A file stream of events. Times without a zone are cast, as watermarks need an instant."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return rows.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def live_counts(events: DataFrame, ctx, sym, ts: str = "ts", width: str = "1 day", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """(window, ctx, sym, n) in tumbling, sliding or session windows; late rows beyond the watermark are dropped."""
    span = F.session_window(ts, gap) if gap else F.window(ts, width, slide or width)
    return events.groupBy(span.alias("span"), ctx.alias("ctx"), sym.alias("sym")).agg(F.count("*").alias("n"))


def drift(events: DataFrame, model: DataFrame, ctx, sym, ts: str = "ts", width: str = "1 day") -> DataFrame:
    """Bits per value of each window against a frozen model (ctx, sym, bits): a stream-static join."""
    coded = events.select(ts, ctx.alias("ctx"), sym.alias("sym")).join(model.select("ctx", "sym", "bits"), ["ctx", "sym"])
    return coded.groupBy(F.window(ts, width).alias("span")).agg(F.count("*").alias("n"), (F.sum("bits") / F.count("*")).alias("bpv"))


def with_bins(events: DataFrame, ctx, bins: DataFrame) -> DataFrame:
    """Stream-static join with a bin table."""
    return events.withColumn("ctx", ctx).join(bins, "ctx", "left").withColumn("bin", F.coalesce("bin", F.lit(0)))


def deduplicated(events: DataFrame, id_col: str) -> DataFrame:
    return events.dropDuplicatesWithinWatermark([id_col])


def adaptive_per_key(events: DataFrame, key: str, order: str, sym: str, m: int, rate: int, idle: str | None = None) -> DataFrame:
    """key, n, bits, cdf after each trigger: one adaptive function per key kept as state (code first, update then).

    Rows of a trigger are taken in order; rows that come in a later trigger come later in the sequence, too. With ``idle`` a
    key's state is dropped that long (ms) after its last row.
    """
    targets = [step_target(m, s) for s in range(m)]

    def step(name: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, bits, cdf = state.get if state.exists else (0, 0.0, uniform_cdf(m))
        cdf = list(cdf)
        import math

        for x in pd.concat(list(batches)).sort_values(order)[sym].tolist():
            bits += CDF_BITS - math.log2(cdf[x + 1] - cdf[x])
            cdf = [a + ((b - a) >> rate) for a, b in zip(cdf, targets[x])]
            n += 1
        state.update((n, bits, cdf))
        if idle:
            state.setTimeoutDuration(int(idle))
        yield pd.DataFrame({key: [name[0]], "n": [n], "bits": [bits], "cdf": [cdf]})

    kind = events.schema[key].dataType.simpleString()
    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle else GroupStateTimeout.NoTimeout
    return events.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, n long, bits double, cdf array<int>", "n long, bits double, cdf array<int>", "update", timeout)


def run_once(df: DataFrame, name: str, mode: str, checkpoint: str):
    """Runs a streaming query over all that is there and stops: results in the in-memory table ``name``."""
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def to_tables(df: DataFrame, path: str, checkpoint: str, mode: str = "update"):
    """Every trigger's rows as one versioned folder (foreachBatch: a repeated batch overwrites itself)."""

    def put(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={batch}")

    return df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
