"""Gates on the row form, inside Catalyst: projections where amplitudes only move or turn, one aggregate where two mix."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import bit, permuted
from ..functions.gates import Circuit, Gate, as_u3, diagonal_of, matrix_of, u3_matrix


def _times(re: Column, im: Column, z: complex) -> tuple[Column, Column]:
    return re * z.real - im * z.imag, re * z.imag + im * z.real


def apply_u3(df: DataFrame, k: int, theta: float, phi: float, lam: float, keys: tuple[str, ...] = ()) -> DataFrame:
    """One aggregate brings the two partners of a pair together, and two rows come out of each.

    keys: columns that the pairs' rows share. Where df is already partitioned by them, the aggregate needs no exchange.
    """
    m, hi = u3_matrix(theta, phi, lam), bit("idx", k) == 1
    pick = lambda c, b: F.sum(F.when(hi if b else ~hi, F.col(c)).otherwise(0.0)).alias(f"{c}{b}")
    pairs = df.groupBy(*keys, F.col("idx").bitwiseAND(F.lit(~(1 << k))).alias("pair")).agg(pick("re", 0), pick("im", 0), pick("re", 1), pick("im", 1))

    def row(b: int) -> Column:
        x, y = _times(F.col("re0"), F.col("im0"), m[b, 0]), _times(F.col("re1"), F.col("im1"), m[b, 1])
        return F.struct((F.col("pair") + (b << k)).alias("idx"), (x[0] + y[0]).alias("re"), (x[1] + y[1]).alias("im"))

    return pairs.select(*keys, F.explode(F.array(row(0), row(1))).alias("a")).select(*keys, "a.idx", "a.re", "a.im")


def apply_u3_selfjoin(df: DataFrame, k: int, theta: float, phi: float, lam: float) -> DataFrame:
    """The same by joining each amplitude with its partner, the index with bit k flipped."""
    m, hi = u3_matrix(theta, phi, lam), bit("idx", k) == 1
    other = df.select(F.col("idx").bitwiseXOR(F.lit(1 << k)).alias("idx"), F.col("re").alias("re_p"), F.col("im").alias("im_p"))
    j = df.join(other, "idx")
    parts = [[_times(F.col("re"), F.col("im"), m[b, b]), _times(F.col("re_p"), F.col("im_p"), m[b, 1 - b])] for b in (0, 1)]
    pick = lambda i: F.when(hi, parts[1][0][i] + parts[1][1][i]).otherwise(parts[0][0][i] + parts[0][1][i])
    return j.select("idx", pick(0).alias("re"), pick(1).alias("im"))


def apply_u3_window(df: DataFrame, k: int, theta: float, phi: float, lam: float) -> DataFrame:
    """The same by a window over each pair."""
    m, hi = u3_matrix(theta, phi, lam), bit("idx", k) == 1
    w = Window.partitionBy(F.col("idx").bitwiseAND(F.lit(~(1 << k)))).orderBy("idx")
    j = df.select("idx", "re", "im", *[F.coalesce(F.lead(c).over(w), F.lag(c).over(w)).alias(f"{c}_p") for c in ("re", "im")])
    parts = [[_times(F.col("re"), F.col("im"), m[b, b]), _times(F.col("re_p"), F.col("im_p"), m[b, 1 - b])] for b in (0, 1)]
    pick = lambda i: F.when(hi, parts[1][0][i] + parts[1][1][i]).otherwise(parts[0][0][i] + parts[0][1][i])
    return j.select("idx", pick(0).alias("re"), pick(1).alias("im"))


def apply_diagonal(df: DataFrame, g: Gate) -> DataFrame:
    """Every amplitude by its own entry: a projection on any qubits."""
    entries = diagonal_of(g)
    at = sum((F.shiftleft(bit("idx", q), i) for i, q in enumerate(g.qubits)), F.lit(0))
    re, im = F.col("re"), F.col("im")
    for i, z in enumerate(entries):
        if z != 1:
            x = _times(F.col("re"), F.col("im"), complex(z))
            re, im = F.when(at == i, x[0]).otherwise(re), F.when(at == i, x[1]).otherwise(im)
    return df.withColumns({"re": re, "im": im})


def apply_moves(df: DataFrame, g: Gate, n: int) -> DataFrame:
    """x, cx, ccx and swap only renumber indices: a projection."""
    if g.kind == "swap":
        perm = list(range(n))
        perm[g.qubits[0]], perm[g.qubits[1]] = g.qubits[1], g.qubits[0]
        return df.withColumn("idx", permuted("idx", perm))
    on = F.lit(1)
    for q in g.qubits[:-1]:
        on = on.bitwiseAND(bit("idx", q))
    return df.withColumn("idx", F.col("idx").bitwiseXOR(F.shiftleft(on.cast("long"), g.qubits[-1])))


def apply_unitary(df: DataFrame, g: Gate, keys: tuple[str, ...] = ()) -> DataFrame:
    """Any small unitary: groups of 2^k amplitudes, one aggregate."""
    m, k = matrix_of(g), len(g.qubits)
    mask = sum(1 << q for q in g.qubits)
    at = sum((F.shiftleft(bit("idx", q), i) for i, q in enumerate(g.qubits)), F.lit(0))
    pick = lambda c, i: F.sum(F.when(at == i, F.col(c)).otherwise(0.0)).alias(f"{c}{i}")
    groups = df.groupBy(*keys, F.col("idx").bitwiseAND(F.lit(~mask)).alias("pair")).agg(*[pick(c, i) for i in range(2**k) for c in ("re", "im")])

    def row(i: int) -> Column:
        parts = [_times(F.col(f"re{j}"), F.col(f"im{j}"), complex(m[i, j])) for j in range(2**k) if m[i, j] != 0]
        place = sum(((i >> b) & 1) << q for b, q in enumerate(g.qubits))
        return F.struct((F.col("pair") + place).alias("idx"), sum((p[0] for p in parts), F.lit(0.0)).alias("re"), sum((p[1] for p in parts), F.lit(0.0)).alias("im"))

    return groups.select(*keys, F.explode(F.array(*[row(i) for i in range(2**k)])).alias("a")).select(*keys, "a.idx", "a.re", "a.im")


def apply_gate(df: DataFrame, g: Gate, n: int, keys: tuple[str, ...] = ()) -> DataFrame:
    if g.is_diagonal:
        return apply_diagonal(df, g)
    if g.kind in ("x", "cx", "ccx", "swap"):
        return apply_moves(df, g, n)
    if len(g.qubits) == 1 and g.kind != "unitary":
        return apply_u3(df, g.qubits[0], *as_u3(g.kind, g.params), keys=keys)
    return apply_unitary(df, g, keys)


def run_gates(df: DataFrame, c: Circuit, cut: int = 16) -> DataFrame:
    """Gate by gate on rows; plans are cut every `cut` aggregates."""
    from ..functions.shared import written

    mixing = 0
    for g in c.gates:
        mixing += bool(g.written) and g.kind not in ("x", "cx", "ccx", "swap")
        df = apply_gate(df, g, c.n)
        if mixing == cut:
            df, mixing = written(df), 0
    return df


def run_rows(df: DataFrame, plan, cut: int = 16) -> DataFrame:
    """A plan on rows kept partitioned by chunk: blocks add no exchange, a remap renumbers and deals the rows anew."""
    from ..functions.shared import written

    nc, chunk = plan.nc, F.shiftright("idx", plan.nc)
    perm = list(plan.start)
    df = df.withColumn("idx", permuted("idx", perm)) if perm != list(range(plan.n)) else df
    deal = lambda d: d.withColumn("chunk", chunk).repartition("chunk")
    df, mixing = deal(df), 0
    for s in plan.sections:
        if s.op == "remap":
            df = deal(df.withColumn("idx", permuted("idx", list(s.perm))))
            continue
        for x in s.steps:
            g = x.gate.on(x.at)
            inside = max([*g.written, 0]) < nc
            if g.kind in ("cx", "ccx", "x", "swap") and not inside or s.op == "global":
                df = deal(apply_gate(df.select("idx", "re", "im"), g, plan.n))
            else:
                df = apply_gate(df, g, plan.n, ("chunk",))
            mixing += not g.is_diagonal
            if mixing >= cut:
                df, mixing = deal(written(df)), 0
    df = df.select("idx", "re", "im")
    if plan.end != tuple(range(plan.n)):
        back = [0] * plan.n
        for q, p in enumerate(plan.end):
            back[p] = q
        df = df.withColumn("idx", permuted("idx", back))
    return df


def norm(df: DataFrame) -> DataFrame:
    return df.agg(F.sum(F.col("re") * F.col("re") + F.col("im") * F.col("im")).alias("norm"))


