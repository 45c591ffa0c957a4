"""Single gates on encoded tables."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..functions.bits import u6
from ..functions.gates import Circuit, Gate, decompose, fuse, inverse, matrix_of
from ..operators import rows as R
from ..operators import states as S
from ..sources import workloads as W
from . import oracle as O
from . import query
from .states import amps, customer, mismatches, orders, supplier, table

T, P, L = 0.7, 0.3, 1.1


@query(O.amps(O.u3(O.ORDERS, 2, T, P, L)))
def u3_low_orders(spark, sf_dir):
    return amps(R.apply_u3(orders(spark, sf_dir)[0], 2, T, P, L))


@query(O.amps(O.u3(O.ORDERS, 9, T, P, L)))
def u3_high_orders(spark, sf_dir):
    return amps(R.apply_u3(orders(spark, sf_dir)[0], 9, T, P, L))


@query(O.amps(O.u3(O.ORDERS, 5, T, P, L)))
def u3_selfjoin(spark, sf_dir):
    return amps(R.apply_u3_selfjoin(orders(spark, sf_dir)[0], 5, T, P, L))


@query(O.amps(O.u3(O.ORDERS, 4, T, P, L)))
def u3_window(spark, sf_dir):
    return amps(R.apply_u3_window(orders(spark, sf_dir)[0], 4, T, P, L))


_S16 = O.encoded("(SELECT * FROM supplier WHERE s_suppkey < 16)", "s_suppkey", "s_acctbal", "16")


@query(O.amps(O.u3(_S16, 2, T, P, L)))
def u3_four_qubit_example(spark, sf_dir):
    a = S.amplitude_encode(table(spark, sf_dir, "supplier").where("s_suppkey < 16"), "s_suppkey", "s_acctbal", 4)
    return amps(R.apply_u3(a, 2, T, P, L))


@query(f"SELECT idx, {O.u6('CASE WHEN (idx >> 8) & 1 = 1 THEN re*cos(0.9) ELSE re END')} AS re_u6, {O.u6('CASE WHEN (idx >> 8) & 1 = 1 THEN re*sin(0.9) ELSE 0.0 END')} AS im_u6 FROM {O.ORDERS}")
def u1_orders(spark, sf_dir):
    return amps(R.apply_gate(orders(spark, sf_dir)[0], Gate("u1", (8,), (0.9,)), 14))


def _cx(c: int, t: int) -> str:
    return O.amps(f"(SELECT xor(idx, ((idx >> {c}) & 1) << {t}) AS idx, re, im FROM {O.ORDERS})")


for _n, _c, _t in (("cx_low", 0, 3), ("cx_high_control", 9, 1), ("cx_high_target", 1, 9)):
    query(_cx(_c, _t), _n)(lambda s, d, c=_c, t=_t: amps(R.apply_gate(orders(s, d)[0], Gate("cx", (c, t)), 14)))

_SWAP = "(SELECT (idx & ~((1 << 2) | (1 << 7))) | (((idx >> 2) & 1) << 7) | (((idx >> 7) & 1) << 2) AS idx, re, im FROM {})"


@query(O.amps(_SWAP.format(O.ORDERS)))
def swap_gate(spark, sf_dir):
    a, n = orders(spark, sf_dir)
    return amps(R.apply_gate(a, Gate("swap", (2, 7)), n))


@query(O.MISMATCHES)
def swap_as_three_cx(spark, sf_dir):
    a, n = orders(spark, sf_dir)
    return mismatches(R.apply_gate(a, Gate("swap", (2, 7)), n), R.run_gates(a, decompose(Circuit(n, (Gate("swap", (2, 7)),)))))


def _cp(a: int, b: int) -> str:
    on = f"(idx >> {a}) & (idx >> {b}) & 1 = 1"
    return f"SELECT idx, {O.u6(f'CASE WHEN {on} THEN re*cos(0.6) ELSE re END')} AS re_u6, {O.u6(f'CASE WHEN {on} THEN re*sin(0.6) ELSE 0.0 END')} AS im_u6 FROM {O.ORDERS}"


for _n, _a, _b in (("cp_gate", 0, 1), ("cp_high", 1, 10)):
    query(_cp(_a, _b), _n)(lambda s, d, a=_a, b=_b: amps(R.apply_gate(orders(s, d)[0], Gate("cp", (a, b), (0.6,)), 14)))


@query(O.amps(f"(SELECT xor(idx, ((idx >> 1) & (idx >> 4) & 1) << 6) AS idx, re, im FROM {O.ORDERS})"))
def ccx_gate(spark, sf_dir):
    return amps(R.apply_gate(orders(spark, sf_dir)[0], Gate("ccx", (1, 4, 6)), 14))


_NAMED = [("id", ()), ("x", ()), ("y", ()), ("z", ()), ("h", ()), ("s", ()), ("sdg", ()), ("t", ()), ("tdg", ()), ("rx", (0.4,)), ("ry", (0.4,)), ("u1", (0.4,)), ("u2", (0.4, 0.2))]
_ANGLES = """('id',0,0,0),('x',pi(),0,pi()),('y',pi(),pi()/2,pi()/2),('z',0,0,pi()),('h',pi()/2,0,pi()),('s',0,0,pi()/2),('sdg',0,0,-pi()/2),('t',0,0,pi()/4),('tdg',0,0,-pi()/4),
    ('rx',0.4,-pi()/2,pi()/2),('ry',0.4,0,0),('u1',0,0,0.4),('u2',pi()/2,0.4,0.2)"""


@query(f"""WITH g(kind, t, p, l) AS (VALUES {_ANGLES}) SELECT kind, CAST(r AS INT) AS r, CAST(c AS INT) AS c,
    {O.u6("CASE WHEN r=0 AND c=0 THEN cos(t/2) WHEN r=0 THEN -cos(l)*sin(t/2) WHEN c=0 THEN cos(p)*sin(t/2) ELSE cos(p+l)*cos(t/2) END")} AS re_u6,
    {O.u6("CASE WHEN r=0 AND c=0 THEN 0 WHEN r=0 THEN -sin(l)*sin(t/2) WHEN c=0 THEN sin(p)*sin(t/2) ELSE sin(p+l)*cos(t/2) END")} AS im_u6 FROM g, range(2) a(r), range(2) b(c)""")
def named_gates_table(spark, sf_dir):
    rows = [(k, i, j, float(m[i, j].real), float(m[i, j].imag)) for k, p in _NAMED for m in [matrix_of(Gate(k, (0,), p))] for i in (0, 1) for j in (0, 1)]
    return spark.createDataFrame(rows, "kind string, r int, c int, re double, im double").select("kind", "r", "c", u6("re").alias("re_u6"), u6("im").alias("im_u6"))


_PAIR = Circuit(2, tuple(Gate("u3", (q % 2,), (0.3 + q, 0.2 * q, 0.1)) if q % 3 < 2 else Gate("cx", (0, 1)) for q in range(6)))


@query(O.loop(O.CUSTOMER, O.gates(Circuit(11, tuple(g.on((1, 5)[q] for q in g.qubits) for g in _PAIR.gates)))))
def unitary2_gate(spark, sf_dir):
    a, n = customer(spark, sf_dir)
    m = fuse(list(_PAIR.gates), 2)[0]
    return amps(R.apply_unitary(a, m.on((1, 5))))


@query(O.MISMATCHES)
def fused_equals_sequence(spark, sf_dir):
    c = W.brickwork(5, 2)
    return mismatches(R.run_gates(S.uniform_state(spark, 5), c), R.run_gates(S.uniform_state(spark, 5), Circuit(5, tuple(fuse(list(c.gates), 3)))))


@query(f"WITH d(k, a) AS (SELECT i, i * 0.2 FROM range(8) t(i)) SELECT idx, {O.u6('re*cos(a)')} AS re_u6, {O.u6('re*sin(a)')} AS im_u6 FROM {O.ORDERS} JOIN d ON k = (idx >> 3) & 7")
def diagonal_lookup_join(spark, sf_dir):
    """A diagonal on three qubits as a join with its phase table (8 rows, broadcast)."""
    d = spark.range(8).select(F.col("id").alias("k"), (F.col("id") * 0.2).alias("a"))
    a = orders(spark, sf_dir)[0].withColumn("k", F.shiftright("idx", 3).bitwiseAND(F.lit(7)))
    j = a.join(F.broadcast(d), "k")
    return amps(j.select("idx", (F.col("re") * F.cos("a")).alias("re"), (F.col("re") * F.sin("a")).alias("im")))


@query(O.MISMATCHES)
def inverse_returns_to_zero(spark, sf_dir):
    c = W.brickwork(5, 2)
    return mismatches(R.run_gates(S.zero_state(spark, 5), Circuit(5, c.gates + inverse(c).gates)), S.zero_state(spark, 5))


@query(O.MISMATCHES)
def decompose_equiv(spark, sf_dir):
    c = Circuit(4, (Gate("h", (0,)), Gate("ry", (1,), (0.4,)), Gate("swap", (0, 2)), Gate("cp", (1, 3), (0.7,)), Gate("ccx", (0, 1, 2)), Gate("cz", (2, 3))))
    return mismatches(R.run_gates(S.uniform_state(spark, 4), c), R.run_gates(S.uniform_state(spark, 4), decompose(c)))


@query("SELECT p_partkey AS idx, CAST(round(100 * (2.5 * p_retailprice + s_acctbal)) AS BIGINT) AS y_cents FROM part JOIN supplier ON s_suppkey = p_partkey")
def axpy_part_supplier(spark, sf_dir):
    j = table(spark, sf_dir, "part").join(table(spark, sf_dir, "supplier"), F.col("s_suppkey") == F.col("p_partkey"))
    return j.select(F.col("p_partkey").alias("idx"), F.round(100 * (2.5 * F.col("p_retailprice") + F.col("s_acctbal"))).cast("long").alias("y_cents"))


@query(O.amps("(SELECT i AS idx, 1/sqrt(256.0) AS re, 0.0 AS im FROM range(256) t(i))"))
def hadamard_all(spark, sf_dir):
    return amps(R.run_gates(S.zero_state(spark, 8), W.hadamards(8)))


@query("SELECT s_suppkey AS circuit_id, " + ", ".join(f"{O.u6(x)} AS {n}" for n, x in (("m00_u6", "cos(s_suppkey/20.0)"), ("m01_re_u6", "-cos(0.2)*sin(s_suppkey/20.0)"), ("m10_im_u6", "sin(0.1)*sin(s_suppkey/20.0)"), ("m11_re_u6", "cos(0.1+0.2)*cos(s_suppkey/20.0)"))) + " FROM supplier")
def udf_u3_matrix(spark, sf_dir):
    """The matrix of a u3 from columns, as an Arrow-batched function."""
    @F.pandas_udf("struct<m00:double,m01_re:double,m10_im:double,m11_re:double>")
    def u3_entries(t: pd.Series, p: pd.Series, l: pd.Series) -> pd.DataFrame:
        c, s = np.cos(t / 2), np.sin(t / 2)
        return pd.DataFrame({"m00": c, "m01_re": -np.cos(l) * s, "m10_im": np.sin(p) * s, "m11_re": np.cos(p + l) * c})

    t = table(spark, sf_dir, "supplier").withColumn("m", u3_entries(F.col("s_suppkey") / 10.0, F.lit(0.1), F.lit(0.2)))
    return t.select(F.col("s_suppkey").alias("circuit_id"), *[u6(f"m.{x}").alias(f"{x}_u6") for x in ("m00", "m01_re", "m10_im", "m11_re")])


