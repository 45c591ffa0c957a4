"""A gate feed read as a stream: windows, late gates, repeated gates, and registers kept as state.

Streams run with the availableNow trigger and write what each micro-batch gives to the shared folder under its batch's number, so a batch
that is run again replaces its own rows. Event time is a TIMESTAMP: watermarks don't take times without a zone.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.gates import Gate, apply_dense
from ..functions.shared import shared_folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
AMPS = "circuit_id long, idx long, re double, im double, n_gates long"
STATE = "n_gates long, re array<double>, im array<double>"


def event_stream(spark: SparkSession, path: str, max_files: int = 64) -> DataFrame:
    """The feed's files as a stream with event time. path may name a file or a folder."""
    head, _, tail = path.rpartition("/")
    s = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", max_files).parquet(f"{head}/{tail}*")
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str, schema: str | None = None, each: Callable[[DataFrame, int], DataFrame] | None = None, folder: str | None = None) -> DataFrame:
    """Run the stream until its source is empty; all batches' rows with the column `batch`. folder: that of an earlier run, which this one goes on from."""
    spark = df.sparkSession
    folder = folder or shared_folder(spark, "stream")

    def sink(batch: DataFrame, k: int) -> None:
        (each(batch, k) if each else batch).write.mode("overwrite").parquet(f"{folder}/rows/batch={k}")

    df.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    kind = schema or ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)
    return spark.read.schema(f"{kind}, batch long").parquet(f"{folder}/rows")


def split_late(events: DataFrame, delay: str, folder: str) -> DataFrame:
    """All events with the column `late`: more than `delay` before the latest event time of earlier batches. Late ones are the dead-letter table.

    A batch's latest time is written under its number before its rows are, and a batch looks at lower numbers only, so one that is run again decides alike.
    """
    spark = events.sparkSession
    marks = f"{folder}/marks"

    def each(batch: DataFrame, k: int) -> DataFrame:
        batch.agg(F.max("ts").alias("top")).write.mode("overwrite").parquet(f"{marks}/batch={k}")
        top = spark.read.schema("top timestamp, batch long").parquet(marks).where(F.col("batch") < k).agg(F.max("top")).first()[0]
        return batch.withColumn("late", F.coalesce(F.col("ts") < F.lit(top) - F.expr(f"INTERVAL {delay}"), F.lit(False)) if top else F.lit(False))

    kind = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in events.schema)
    return drained(events, "append", f"{kind}, late boolean", each, folder)


def last_batch(rows: DataFrame) -> DataFrame:
    """What the last batch gave: the whole result of a stream in complete mode."""
    top = rows.agg(F.max("batch").alias("_b"))
    return rows.join(F.broadcast(top), F.col("batch") == F.col("_b"), "left_semi").drop("batch")


def tumbling_gates(events: DataFrame, width: str = "1 day") -> DataFrame:
    w = events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("gates"))
    return w.select(F.unix_timestamp("w.start").alias("start"), "event_type", "gates")


def sliding_gates(events: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    w = events.groupBy(F.window("ts", width, slide).alias("w")).agg(F.count(F.lit(1)).alias("gates"))
    return w.select(F.unix_timestamp("w.start").alias("start"), "gates")


def session_circuits(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """A user's gates without a longer pause are one circuit."""
    s = events.withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("gates"))
    return s.select("user_id", F.unix_timestamp("w.start").alias("start"), "gates")


def fold_registers(gates: DataFrame, n: int) -> DataFrame:
    """Each circuit's register as state; gates (circuit_id, ord, kind, qubits, params) are applied in order as they arrive."""

    def fold(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.exists:
            count, re, im = state.get
            v = np.array(re) + 1j * np.array(im)
        else:
            count, v = 0, np.zeros(2**n, complex)
            v[0] = 1
        rows = pd.concat(list(frames)).sort_values("ord")
        for r in rows.itertuples():
            v = apply_dense(v, Gate(r.kind, tuple(int(q) for q in r.qubits), tuple(float(x) for x in r.params)))
        count += len(rows)
        state.update((count, v.real.tolist(), v.imag.tolist()))
        yield pd.DataFrame({"circuit_id": key[0], "idx": np.arange(2**n), "re": v.real, "im": v.imag, "n_gates": count})

    return gates.groupBy("circuit_id").applyInPandasWithState(fold, AMPS, STATE, "update", "NoTimeout")


def newest(rows: DataFrame) -> DataFrame:
    """Of each circuit the register after its last gate."""
    top = rows.groupBy("circuit_id").agg(F.max("n_gates").alias("n_gates"))
    return rows.join(top, ["circuit_id", "n_gates"], "left_semi")
