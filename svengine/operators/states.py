"""Registers in row form (idx, re, im) and packed form (chunk, amp: little-endian complex128); encoders of tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.bits import col

AMP = "idx long, re double, im double"
CHUNK = "chunk long, amp binary"
WIDTH = {"double": ("<c16", 16), "single": ("<c8", 8)}


def basis_state(spark: SparkSession, n: int, j: int = 0) -> DataFrame:
    if not 0 <= j < 2**n:
        raise ValueError(f"{j} isn't an index of {n} qubits")
    return spark.range(2**n).select(F.col("id").alias("idx"), F.when(F.col("id") == j, 1.0).otherwise(0.0).alias("re"), F.lit(0.0).alias("im"))


def zero_state(spark: SparkSession, n: int, nc: int | None = None, form: str = "rows", precision: str = "double") -> DataFrame:
    """The all-zero register; in packed form only chunk 0 gets an amplitude."""
    if form == "rows":
        return basis_state(spark, n, 0)
    nc = n if nc is None else nc
    dtype, _ = WIDTH[precision]

    def fill(batches):
        for b in batches:
            for c in b.column(0).to_pylist():
                a = np.zeros(2**nc, dtype)
                a[0] = c == 0
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.int64()), pa.array([a.tobytes()], pa.binary())], ["chunk", "amp"])

    return spark.range(2 ** (n - nc)).mapInArrow(fill, CHUNK)


def uniform_state(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(2**n).select(F.col("id").alias("idx"), F.lit(2.0 ** (-n / 2)).alias("re"), F.lit(0.0).alias("im"))


def tensor(a: DataFrame, b: DataFrame, nb: int) -> DataFrame:
    """a is the high part. Every pair of amplitudes is an amplitude of the result, so the cross product is the output itself."""
    y = b.select(F.col("idx").alias("_i"), F.col("re").alias("_r"), F.col("im").alias("_m"))
    return a.crossJoin(y).select((F.shiftleft("idx", nb) + F.col("_i")).alias("idx"), (F.col("re") * F.col("_r") - F.col("im") * F.col("_m")).alias("re"), (F.col("re") * F.col("_m") + F.col("im") * F.col("_r")).alias("im"))


def dense_index(df: DataFrame, order: list[str], out: str = "idx") -> DataFrame:
    """Rank from 0 by `order` without a window over all rows: range partitions are counted, and each adds the rows before it.

    The partition of a row must not change between counting and ranking, so the range-partitioned rows are written.
    """
    from ..functions.shared import written

    dealt = written(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "ranges")
    counts = dealt.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))  # a row for each partition
    before = counts.withColumn("_before", F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    local = F.row_number().over(Window.partitionBy("_part").orderBy(*order)) - 1
    return dealt.withColumn("_local", local).join(F.broadcast(before), "_part").withColumn(out, (F.col("_before") + F.col("_local")).cast("long")).drop("_part", "_local", "_before")


def amplitude_encode(df: DataFrame, key: str, value: str | Column, n: int, checked: bool = True) -> DataFrame:
    """Amplitude key of the register is value over the norm of all values; keys that don't occur are 0.

    One aggregate for the norm (with the checks: a zero norm, keys out of range or repeated are errors) and one outer join for the padding.
    """
    rows = df.select(col(key).cast("long").alias("idx"), col(value).cast("double").alias("v"))
    sums = rows.agg(F.sum(F.col("v") * F.col("v")).alias("s"), F.count(F.lit(1)).alias("c"), F.min("idx").alias("lo"), F.max("idx").alias("hi")).first()
    if not sums["s"]:
        raise ValueError("the norm of the encoded column is zero")
    if sums["lo"] < 0 or sums["hi"] >= 2**n:
        raise ValueError(f"keys don't fit into {n} qubits")
    if checked and not rows.groupBy("idx").count().where("count > 1").isEmpty():
        raise ValueError("a key occurs twice")
    all_ = df.sparkSession.range(2**n).withColumnRenamed("id", "idx")
    return all_.join(rows, "idx", "left").select("idx", (F.coalesce("v", F.lit(0.0)) / F.lit(float(sums["s"]) ** 0.5)).alias("re"), F.lit(0.0).alias("im"))


def qubits_for(rows: int) -> int:
    return max(1, (rows - 1).bit_length())


def basis_encode(df: DataFrame, key: str, n: int) -> DataFrame:
    """One basis register for each row, as its only non-zero amplitude."""
    return df.select(col(key).cast("long").alias("circuit_id"), (col(key) % 2**n).cast("long").alias("idx"), F.lit(1.0).alias("re"), F.lit(0.0).alias("im"))


def angle_encode(df: DataFrame, key: str, angles: list[Column]) -> DataFrame:
    """One product register for each row: qubit q is rotated about y by angles[q]."""
    rows = df.select(col(key).cast("long").alias("circuit_id"), *[a.alias(f"_a{q}") for q, a in enumerate(angles)])
    rows = rows.withColumn("idx", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(2 ** len(angles) - 1).cast("long"))))
    amp = F.lit(1.0)
    for q in range(len(angles)):
        half = F.col(f"_a{q}") / 2
        amp = amp * F.when(F.shiftright("idx", q).bitwiseAND(F.lit(1)) == 1, F.sin(half)).otherwise(F.cos(half))
    return rows.select("circuit_id", "idx", amp.alias("re"), F.lit(0.0).alias("im"))


def with_chunk(state: DataFrame, nc: int) -> DataFrame:
    return state.select(F.shiftright("idx", nc).alias("chunk"), F.col("idx").bitwiseAND(F.lit(2**nc - 1)).alias("off"), "re", "im")


def to_chunks(state: DataFrame, nc: int, precision: str = "double") -> DataFrame:
    """Rows to packed chunks: one exchange by chunk; offsets that don't occur are 0."""
    dtype, _ = WIDTH[precision]

    def pack(key, t):
        a = np.zeros(2**nc, dtype)
        a[t["off"].to_numpy()] = t["re"].to_numpy() + 1j * t["im"].to_numpy()
        return pa.table({"chunk": pa.array([key[0].as_py()], pa.int64()), "amp": pa.array([a.tobytes()], pa.binary())})

    return with_chunk(state, nc).groupBy("chunk").applyInArrow(pack, CHUNK)


def to_rows(chunks: DataFrame, nc: int, precision: str = "double") -> DataFrame:
    dtype, _ = WIDTH[precision]

    def unpack(batches):
        for b in batches:
            for c, a in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                v = np.frombuffer(a.as_buffer(), dtype).astype("<c16")
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(2**nc, dtype="int64") + (c << nc)), pa.array(v.real.copy()), pa.array(v.imag.copy())], ["idx", "re", "im"])

    return chunks.mapInArrow(unpack, AMP)


def chunk_base(chunk, nc: int) -> Column:
    return F.shiftleft(col(chunk), nc)


def assign_contiguous(chunk, k: int, m: int) -> Column:
    """Space of a chunk: equal runs of neighbouring chunks."""
    return F.floor(col(chunk) * m / k).cast("long")
