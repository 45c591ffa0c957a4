"""Functions and views for SQL users."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .operators import measure


@udtf(returnType="ord long, kind string, q0 int, q1 int, angle double")
class QftGates:
    """qft_gates(n): the gates of a Fourier circuit, in order."""

    def eval(self, n: int):
        k = 0
        for q in reversed(range(n)):
            yield k, "h", q, None, None
            k += 1
            for r in reversed(range(q)):
                yield k, "cp", r, q, math.pi / 2 ** (q - r)
                k += 1
        for i in range(n // 2):
            yield k, "swap", i, n - 1 - i, None
            k += 1


def register_sql(spark: SparkSession, registers: dict[str, DataFrame] | None = None) -> None:
    """Registers qft_gates and a view (and one of its probabilities, <name>_p) for each register."""
    spark.udtf.register("qft_gates", QftGates)
    for name, df in (registers or {}).items():
        df.createOrReplaceTempView(name)
        measure.probabilities(df).createOrReplaceTempView(f"{name}_p")


