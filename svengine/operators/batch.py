"""Many small circuits: the gates of a circuit meet in one row, and each row is simulated where it lies. One shuffle by circuit."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.gates import Gate, apply_dense

BATCH = "circuit_id long, n int, re array<double>, im array<double>"


def run_batch(gates: DataFrame, n: int, start: DataFrame | None = None) -> DataFrame:
    """circuit_id, n, re, im of every circuit in gates. start: (circuit_id, re, im arrays); the zero register where it has no row."""
    lists = gates.groupBy("circuit_id").agg(F.sort_array(F.collect_list(F.struct("ord", "kind", "qubits", "params"))).alias("gates"))
    if start is not None:
        lists = lists.join(start.select("circuit_id", F.struct("re", "im").alias("start")), "circuit_id", "full")
    else:
        lists = lists.withColumn("start", F.lit(None).cast("struct<re:array<double>,im:array<double>>"))

    def run(batches):
        for b in batches:
            out = []
            for gs, s in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                v = np.zeros(2**n, complex)
                if s is None:
                    v[0] = 1
                else:
                    v[:] = np.array(s["re"]) + 1j * np.array(s["im"])
                for g in gs or []:
                    v = apply_dense(v, Gate(g["kind"], tuple(g["qubits"]), tuple(g["params"])))
                out.append(v)
            kind = pa.list_(pa.float64())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([n] * len(out), pa.int32()), pa.array([v.real.tolist() for v in out], kind), pa.array([v.imag.tolist() for v in out], kind)], ["circuit_id", "n", "re", "im"])

    return lists.select("circuit_id", "gates", "start").mapInArrow(run, BATCH)


def amplitudes(batch: DataFrame) -> DataFrame:
    """circuit_id, idx, re, im: a row for each amplitude."""
    return batch.select("circuit_id", F.posexplode(F.arrays_zip("re", "im")).alias("idx", "a")).select("circuit_id", F.col("idx").cast("long").alias("idx"), "a.re", "a.im")
