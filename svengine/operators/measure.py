"""Reading registers: probabilities, marginals, samples, collapse, expectations, overlaps, noise."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import bit, col


def p() -> Column:
    return F.col("re") * F.col("re") + F.col("im") * F.col("im")


def probabilities(state: DataFrame) -> DataFrame:
    return state.select("idx", p().alias("p"))


def marginals(state: DataFrame, qubits: list[int]) -> DataFrame:
    value = sum((F.shiftleft(bit("idx", q), i) for i, q in enumerate(qubits)), F.lit(0).cast("long"))
    return state.groupBy(value.alias("value")).agg(F.sum(p()).alias("p"))


def qubit_p1(state: DataFrame, n: int) -> DataFrame:
    """p(1) of every qubit in one pass: n conditional sums, then one row each."""
    sums = state.agg(*[F.sum(F.when(bit("idx", q) == 1, p()).otherwise(0.0)).alias(f"q{q}") for q in range(n)])
    return sums.select(F.posexplode(F.array(*[f"q{q}" for q in range(n)])).alias("qubit", "p1"))


def billionths(state: DataFrame) -> DataFrame:
    """Probabilities as whole billionths, so that sums don't depend on the order of adding."""
    return state.select("idx", F.floor(p() * 1e9 + 0.5001).cast("long").alias("w"))


#: Indices in a run of sample_shots().
RUN_BITS = 12


def _in_spans(points: DataFrame, at: str, spans: DataFrame, width: Column, keys: tuple[str, ...] = ()) -> DataFrame:
    """Each point with the span lo <= at < hi that holds it (of the same keys): an equi-join on steps of `width`, into which spans are cut. Empty spans hold nothing."""
    cut = spans.where("hi > lo").withColumn("_step", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    return points.withColumn("_step", F.floor(F.col(at) / width)).join(cut, [*keys, "_step"]).where(f"{at} >= lo and {at} < hi").drop("_step")


def sample_shots(state: DataFrame, shots: int, nc: int) -> DataFrame:
    """Inverse distribution in two levels: sums of runs of indices (2^nc, 2^RUN_BITS at most) first, then inside the runs that were drawn.

    The window over runs sees one row for each run, and those inside a run its rows; none sees the whole register. Draw s is
    (s * 2654435761) mod the total. Draws meet their run, and then their index, by equi-joins on steps of about a run's (an index's) mean mass.
    """
    spark = state.sparkSession
    w = billionths(state).withColumn("run", F.shiftright("idx", min(nc, RUN_BITS)))
    runs = w.groupBy("run").agg(F.sum("w").alias("mass"), F.count(F.lit(1)).alias("n"))
    total, n = runs.agg(F.coalesce(F.sum("mass"), F.lit(0)), F.count(F.lit(1))).first()
    if not total:
        return spark.createDataFrame([], "shot long, outcome long")
    runs = runs.withColumn("hi", F.sum("mass").over(Window.orderBy("run"))).withColumn("lo", F.col("hi") - F.col("mass"))
    draws = spark.range(shots).select(F.col("id").alias("shot"), ((F.col("id") * 2654435761) % total).alias("draw"))
    hit = _in_spans(draws, "draw", runs, F.lit(total // n + 1)).select("shot", "run", "mass", "n", (F.col("draw") - F.col("lo")).alias("inside"))
    step = F.floor(F.col("mass") / F.col("n")) + 1
    inner = w.withColumn("hi", F.sum("w").over(Window.partitionBy("run").orderBy("idx"))).withColumn("lo", F.col("hi") - F.col("w"))
    inner = inner.withColumns({"mass": F.sum("w").over(Window.partitionBy("run")), "n": F.count(F.lit(1)).over(Window.partitionBy("run"))})
    return _in_spans(hit, "inside", inner, step, ("run", "mass", "n")).select("shot", F.col("idx").alias("outcome"))


def quantile(rows: DataFrame, column: str, share: float, bins: int = 4096) -> float:
    """The exact quantile, between neighbours: counts of `bins` ranges, then of the one that holds its rank, until that holds one value."""
    v = F.col(column)
    n, lo, hi = rows.agg(F.count(v), F.min(v), F.max(v)).first()
    at = (n - 1) * share
    rank, after = int(at), hi
    while lo < hi:
        place = F.least(F.floor((v - lo) / ((hi - lo) / bins)), F.lit(bins - 1))
        parts = rows.where(v.between(lo, hi)).groupBy(place.alias("bin")).agg(F.count(v), F.min(v), F.max(v)).orderBy("bin").collect()  # bins rows at most
        k = 0
        while rank >= parts[k][1]:
            rank -= parts[k][1]
            k += 1
        after = parts[k + 1][2] if k + 1 < len(parts) else after
        _, n, lo, hi = parts[k]
    return lo + (at - int(at)) * ((lo if rank + 1 < n else after) - lo)


def collapse(state: DataFrame, qubit: int, outcome: int) -> DataFrame:
    """After a measurement: the part with that bit, renormalised. An impossible outcome leaves no row with a value."""
    part = state.where(bit("idx", qubit) == outcome)
    return part.crossJoin(F.broadcast(part.agg(F.sqrt(F.sum(p())).alias("_n")))).select("idx", (F.col("re") / F.col("_n")).alias("re"), (F.col("im") / F.col("_n")).alias("im"))


def expect_pauli(state: DataFrame, x_mask: int, z_mask: int) -> DataFrame:
    """Expectation of a product of X on x_mask and Z on z_mask (disjoint masks): a sum, or a join with the flipped index."""
    sign = F.when(F.bit_count(F.col("idx").bitwiseAND(F.lit(z_mask))) % 2 == 0, 1.0).otherwise(-1.0)
    if not x_mask:
        return state.agg(F.sum(p() * sign).alias("value"))
    other = state.select(F.col("idx").bitwiseXOR(F.lit(x_mask)).alias("idx"), F.col("re").alias("r"), F.col("im").alias("i"))
    return state.join(other, "idx").agg(F.sum((F.col("re") * F.col("r") + F.col("im") * F.col("i")) * sign).alias("value"))


def fidelity(a: DataFrame, b: DataFrame) -> DataFrame:
    """Squared overlap and greatest difference of two registers."""
    y = b.select("idx", F.col("re").alias("r"), F.col("im").alias("i"))
    sums = a.join(y, "idx").agg(F.sum(F.col("re") * F.col("r") + F.col("im") * F.col("i")).alias("x"), F.sum(F.col("re") * F.col("i") - F.col("im") * F.col("r")).alias("y"), F.max(F.greatest(F.abs(F.col("re") - F.col("r")), F.abs(F.col("im") - F.col("i")))).alias("max_error"))
    return sums.select((F.col("x") * F.col("x") + F.col("y") * F.col("y")).alias("fidelity"), "max_error")


def with_readout_error(probs: DataFrame, qubit: int, p01: float, p10: float) -> DataFrame:
    """Probabilities after one qubit's bit is misread: 0 as 1 with p01, 1 as 0 with p10."""
    one = bit("idx", qubit) == 1
    keep = F.when(one, 1 - p10).otherwise(1 - p01)
    rows = F.array(F.struct(F.col("idx"), (F.col("p") * keep).alias("p")), F.struct(F.col("idx").bitwiseXOR(F.lit(1 << qubit)).alias("idx"), (F.col("p") * (1 - keep)).alias("p")))
    return probs.select(F.explode(rows).alias("a")).groupBy(F.col("a.idx").alias("idx")).agg(F.sum("a.p").alias("p"))


def noisy_gates(gates: DataFrame, shots: int, rate: float) -> DataFrame:
    """Each shot's circuit with random Paulis after gates. Draws are a hash of shot and gate. gates: circuit_id, ord, kind, qubits, params.

    Remaps of a rewritten circuit aren't gates here, so they never get noise.
    """
    spark = gates.sparkSession
    s = gates.crossJoin(F.broadcast(spark.range(shots).withColumnRenamed("id", "shot")))
    h = (F.col("shot") * 7919 + F.col("ord") * 104729 + 17) % 10007
    own = s.select(F.col("shot").alias("circuit_id"), (F.col("ord") * 2).alias("ord"), "kind", "qubits", "params")
    pauli = F.element_at(F.array(F.lit("x"), F.lit("y"), F.lit("z")), (h % 3 + 1).cast("int"))
    err = s.where(h < rate * 10007).select(F.col("shot").alias("circuit_id"), (F.col("ord") * 2 + 1).alias("ord"), pauli.alias("kind"), F.array(F.element_at("qubits", -1)).alias("qubits"), F.array().cast("array<double>").alias("params"))
    return own.unionByName(err)


def outcome_counts(shots: DataFrame) -> DataFrame:
    return shots.groupBy(col("outcome")).agg(F.count(F.lit(1)).alias("shots"))
