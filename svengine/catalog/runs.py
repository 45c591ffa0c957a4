"""Whole circuits: rewritten and per-gate runs, the Fourier and volume families, batches."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.bits import u6
from ..functions.gates import Circuit, inverse
from ..functions.shared import shared_folder
from ..operators import batch as B
from ..operators import chunks as C
from ..operators import measure as M
from ..operators import rows as R
from ..operators import states as S
from ..operators import tiers as T
from ..plans.cost import baseline_cost, blocked_cost, totals
from ..plans.transpile import plan_blocks
from ..sources import workloads as W
from . import oracle as O
from . import query
from .states import amps, customer, mismatches, orders, table


def zero(spark, n: int, nc: int) -> C.Register:
    return C.Register(S.zero_state(spark, n, nc, "chunks"), n, nc, symmetric=True)


def blocked(spark, c: Circuit, nc: int, start: C.Register | None = None, **options):
    return C.rows_of(C.run_blocked(start or zero(spark, c.n, nc), plan_blocks(c, nc, **options)))


@query(O.volume(8))
def qv_blocked(spark, sf_dir):
    return amps(blocked(spark, W.quantum_volume(spark, sf_dir, 8), 4))


@query(O.volume(6, 4))
def qv_baseline(spark, sf_dir):
    return amps(C.rows_of(C.run_baseline(zero(spark, 6, 4), W.quantum_volume(spark, sf_dir, 6, 4))))


@query(O.volume(6, 2))
def qv_rows_blocked(spark, sf_dir):
    return amps(R.run_rows(S.zero_state(spark, 6), plan_blocks(W.quantum_volume(spark, sf_dir, 6, 2), 4)))


@query(O.MISMATCHES)
def qv_nc_sweep(spark, sf_dir):
    c = W.quantum_volume(spark, sf_dir, 6, 2)
    one = blocked(spark, c, 6)
    parts = [mismatches(one, blocked(spark, c, nc)) for nc in (2, 3, 5)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).agg(F.sum("mismatches").cast("long").alias("mismatches"))


for _d in (1, 3):
    query(O.volume(6, _d), f"qv_depth_{_d}")(lambda s, d, depth=_d: amps(blocked(s, W.quantum_volume(s, d, 6, depth), 4)))


@query(" UNION ALL ".join(f"SELECT {d}::INT AS depth, * FROM ({O.volume(6, d)})" for d in (1, 2, 3)))
def qv_depth_sweep(spark, sf_dir):
    parts = [amps(blocked(spark, W.quantum_volume(spark, sf_dir, 6, d), 4)).withColumn("depth", F.lit(d)) for d in (1, 2, 3)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("SELECT CAST(n AS INT) AS n, CAST(nc AS INT) AS nc, CAST(n - nc AS INT) AS per_gate_exchanges, CASE WHEN n = nc THEN 0 ELSE 2 END AS exchanges, 1000000::BIGINT AS fidelity_u6 FROM (VALUES (5, 5), (6, 5), (7, 5), (8, 5)) v(n, nc)")
def single_node_sweep(spark, sf_dir):
    """Growing Fourier circuits in chunks of five qubits: exchanges of the per-gate and of the rewritten run, and the overlap of their results."""
    out = None
    for n in (5, 6, 7, 8):
        c = W.qft(n, with_swaps=False)
        p = plan_blocks(c, 5, diagonal_free=True, idle_first=False)
        f = M.fidelity(C.rows_of(C.run_blocked(zero(spark, n, 5), p)), C.rows_of(C.run_baseline(zero(spark, n, 5), c)))
        row = f.select(F.lit(n).alias("n"), F.lit(5).alias("nc"), F.lit(totals(baseline_cost(c, 5, 1))["exchanges"]).alias("per_gate_exchanges"), F.lit(totals(blocked_cost(p, 1))["exchanges"]).alias("exchanges"), u6("fidelity").alias("fidelity_u6"))
        out = row if out is None else out.unionByName(row)
    return out


@query(O.amps("(SELECT k AS idx, cos(2*pi()*((k*37) % 256)/256)/16 AS re, sin(2*pi()*((k*37) % 256)/256)/16 AS im FROM range(256) t(k))"))
def qft_basis(spark, sf_dir):
    return amps(R.run_gates(S.basis_state(spark, 8, 37), W.qft(8)))


_FOURIER = O.amps(O.fourier(O.CUSTOMER, O.size_of("customer")))


def encoded_customer(spark, sf_dir, nc: int) -> C.Register:
    a, n = customer(spark, sf_dir)
    return C.Register(S.to_chunks(a, min(nc, n)), n, min(nc, n))


@query(_FOURIER)
def qft_customer(spark, sf_dir):
    r = encoded_customer(spark, sf_dir, 16)  # one chunk
    return amps(blocked(spark, W.qft(r.n), r.nc, r))


@query(_FOURIER)
def qft_blocked(spark, sf_dir):
    r = encoded_customer(spark, sf_dir, 6)
    return amps(blocked(spark, W.qft(r.n), r.nc, r, diagonal_free=True))


@query(_FOURIER)
def qft_blocked_plain(spark, sf_dir):
    r = encoded_customer(spark, sf_dir, 6)
    return amps(blocked(spark, W.qft(r.n), r.nc, r))


@query(_FOURIER)
def qft_baseline(spark, sf_dir):
    r = encoded_customer(spark, sf_dir, 6)
    return amps(C.rows_of(C.run_baseline(r, W.qft(r.n))))


@query(O.MISMATCHES)
def qft_inverse_roundtrip(spark, sf_dir):
    a, n = customer(spark, sf_dir)
    c = W.qft(n)
    r = C.Register(S.to_chunks(a, 6), n, 6)
    return mismatches(a, blocked(spark, Circuit(n, c.gates + inverse(c).gates), 6, r, diagonal_free=True))


@query(O.MISMATCHES)
def serial_equals_chunked(spark, sf_dir):
    c = W.brickwork(6, 3)
    return mismatches(blocked(spark, c, 6), blocked(spark, c, 3))


@query(O.loop(O.basis(5), O.gates(W.worked_example())))
def worked_example_state(spark, sf_dir):
    return amps(blocked(spark, W.worked_example(), 3))


@query("SELECT i AS idx, CASE WHEN i IN (0, 63) THEN 707107 ELSE 0 END::BIGINT AS re_u6, 0::BIGINT AS im_u6 FROM range(64) t(i)")
def ghz(spark, sf_dir):
    return amps(blocked(spark, W.ghz(6), 3))


@query("SELECT i AS idx, CASE WHEN i = s THEN 1000000 ELSE 0 END::BIGINT AS p_u6 FROM range(128) t(i), (SELECT bit_xor(o_custkey) & 63 AS s FROM orders)")
def bernstein_vazirani(spark, sf_dir):
    """The secret is the parity word of the orders' customer keys, six bits of it."""
    secret = table(spark, sf_dir, "orders").agg(F.bit_xor("o_custkey").bitwiseAND(F.lit(63))).first()[0]
    return M.probabilities(blocked(spark, W.bernstein_vazirani(6, secret), 4)).select("idx", u6("p").alias("p_u6"))


@query(f"SELECT i AS idx, {O.u6('pow(CASE WHEN i = 11 THEN 3*32 - 4 ELSE 32 - 4 END / (32*sqrt(32.0)), 2)')} AS p_u6 FROM range(32) t(i)")
def grover_step(spark, sf_dir):
    return M.probabilities(R.run_gates(S.zero_state(spark, 5), W.grover_step(5, 11))).select("idx", u6("p").alias("p_u6"))


@query(O.loop(O.ORDERS, O.gates(W.brickwork(8, 2))))
def brickwork_orders(spark, sf_dir):
    a, n = orders(spark, sf_dir)
    c = Circuit(n, W.brickwork(8, 2).gates)
    return amps(blocked(spark, c, 6, C.Register(S.to_chunks(a, 6), n, 6)))


@query(O.MISMATCHES)
def precision_single(spark, sf_dir):
    """Single precision stays within 1e-5 of double."""
    c = W.brickwork(6, 3)
    single = C.Register(S.zero_state(spark, 6, 3, "chunks", "single"), 6, 3, precision="single")
    return mismatches(blocked(spark, c, 3), C.rows_of(C.run_blocked(single, plan_blocks(c, 3))), 1e-5)


@query(O.MISMATCHES)
def parquet_tier_roundtrip(spark, sf_dir):
    """Generations partitioned by space after each section, and a second run that goes on after the last of them."""
    c = W.brickwork(6, 3)
    folder, p = shared_folder(spark, "generations"), plan_blocks(c, 3)
    C.run_blocked(zero(spark, 6, 3), p, 1, folder, 1).df.count()
    nothing = C.Register(S.zero_state(spark, 6, 3, "chunks").where("chunk < 0"), 6, 3)
    return mismatches(blocked(spark, c, 3), C.rows_of(C.run_blocked(nothing, p, 1, folder, 1)))


@query(O.volume(6, 2))
def tiered_state(spark, sf_dir):
    """Three of eight chunks in memory, the others fetched for each section."""
    return amps(C.rows_of(T.run_tiered(zero(spark, 6, 3), plan_blocks(W.quantum_volume(spark, sf_dir, 6, 2), 3), 3)[0]))


@query(O.volume(6, 1))
def in_place_state(spark, sf_dir):
    """Slow chunks computed where they lie, gate by gate."""
    return amps(C.rows_of(T.run_in_place(zero(spark, 6, 3), W.quantum_volume(spark, sf_dir, 6, 1), 3)[0]))


@query("SELECT * FROM (VALUES ('sections', CAST(2 * 2 * 3 AS BIGINT)), ('exchanges', CAST(2 * 2 * 3 AS BIGINT)), ('in_place', CAST(2 * 2 * 5 AS BIGINT)), ('in_place_exchanges', CAST(2 * 2 * 2 AS BIGINT))) v(kind, chunk_moves)")
def tier_traffic(spark, sf_dir):
    """Slow chunks read and written by runs of the worked example, two of its four chunks slow: three sections and three remaps against five gates inside chunks and two exchanges."""
    c = W.worked_example()
    a = T.run_tiered(zero(spark, 5, 3), plan_blocks(c, 3, restore_order=False), 2)[1]
    b = T.run_in_place(zero(spark, 5, 3), c, 2)[1]
    return spark.createDataFrame([*a.items(), ("in_place", b["in_place"]), ("in_place_exchanges", b["exchanges"])], "kind string, chunk_moves long")


@query("SELECT CAST(pow(2, q) AS BIGINT) AS idx, CAST(floor(1.0/6*1e6 + 0.5001) AS BIGINT) AS p_u6 FROM range(6) t(q)")
def w_state(spark, sf_dir):
    return M.probabilities(blocked(spark, W.w_state(6), 3)).where("p > 1e-12").select("idx", u6("p").alias("p_u6"))


# batches of small circuits

_ORDERS_G = f"""SELECT l_orderkey AS circuit_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY {O.LINE_ORDER}) - 1 AS step,
    CASE l_returnflag WHEN 'R' THEN 'cx' WHEN 'A' THEN 'u3' ELSE 'u1' END AS kind,
    CASE WHEN l_returnflag = 'R' THEN (l_partkey % 4 + 1 + l_suppkey % 3) % 4 ELSE l_partkey % 4 END AS t, l_partkey % 4 AS c,
    pi()*l_discount*10 AS theta, pi()*l_tax*10 AS phi, pi()*l_quantity/50 AS lam FROM lineitem"""


def _zeros(ids: str, n: int) -> str:
    return f"(SELECT circuit_id, i AS idx, CASE WHEN i = 0 THEN 1.0 ELSE 0.0 END AS re, 0.0 AS im FROM ({ids}), range({2**n}) t(i))"


def _key_amps(df):
    return amps(df, "circuit_id", "idx")


@query(O.batch_loop(_zeros("SELECT DISTINCT l_orderkey AS circuit_id FROM lineitem", 4), _ORDERS_G, O.amps("fin", "circuit_id, idx")))
def batch_orders_circuits(spark, sf_dir):
    return _key_amps(B.amplitudes(B.run_batch(W.orders_gates(spark, sf_dir), 4)))


_CONV_G = """SELECT conv_id AS circuit_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn) - 1 AS step, CASE role WHEN 'assistant' THEN 'cx' ELSE 'u3' END AS kind,
    CASE role WHEN 'assistant' THEN (turn + 1) % 3 ELSE turn % 3 END AS t, turn % 3 AS c, CASE role WHEN 'system' THEN pi()/2 ELSE radians(coalesce(length(text), 0) % 360) END AS theta,
    0.0 AS phi, CASE role WHEN 'system' THEN pi() ELSE 0.0 END AS lam FROM conversations"""


@query(O.batch_loop(_zeros("SELECT DISTINCT conv_id AS circuit_id FROM conversations", 3), _CONV_G, O.amps("fin", "circuit_id, idx")))
def batch_conversations(spark, sf_dir):
    return _key_amps(B.amplitudes(B.run_batch(W.conversation_gates(spark, sf_dir), 3)))


_EV = """ev AS (SELECT user_id AS circuit_id, event_id, event_type, value, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events),
    ev2 AS (SELECT *, k % 6 AS q0, (k + 1 + circuit_id % 5) % 6 AS q1 FROM ev),
    parts(event_type, j) AS (VALUES ('view', 0), ('click', 0), ('purchase', 0), ('error', 0), ('signup', 0), ('signup', 1), ('signup', 2)),"""
_EVENTS_G = """SELECT circuit_id, row_number() OVER (PARTITION BY circuit_id ORDER BY event_id, j) - 1 AS step,
    CASE event_type WHEN 'view' THEN 'u3' WHEN 'click' THEN 'u3' WHEN 'error' THEN 'u1' ELSE 'cx' END AS kind,
    CASE WHEN event_type = 'purchase' OR (event_type = 'signup' AND j <> 1) THEN q1 ELSE q0 END AS t, CASE WHEN event_type = 'signup' AND j = 1 THEN q1 ELSE q0 END AS c,
    CASE event_type WHEN 'view' THEN pi()/2 ELSE value/500*pi() END AS theta, CASE event_type WHEN 'view' THEN 0.0 ELSE k*pi()/50 END AS phi,
    CASE event_type WHEN 'view' THEN pi() WHEN 'error' THEN value/500*pi() ELSE 0.0 END AS lam FROM ev2 JOIN parts USING (event_type)"""


@query(O.batch_loop(_zeros("SELECT DISTINCT user_id AS circuit_id FROM events", 6), _EVENTS_G, O.amps("fin", "circuit_id, idx"), _EV))
def events_circuits_state(spark, sf_dir):
    return _key_amps(B.amplitudes(B.run_batch(W.events_gates(spark, sf_dir), 6)))


_EMB = "(SELECT vec_id AS circuit_id, CAST(i AS BIGINT) AS idx, CAST(embedding[i+1] AS DOUBLE) / sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE)*CAST(x AS DOUBLE)))) AS re FROM embeddings, range(64) t(i))"
_EMB_H = f"(SELECT a.circuit_id, a.idx, (CASE WHEN (a.idx >> 3) & 1 = 0 THEN a.re + b.re ELSE b.re - a.re END)/sqrt(2) AS re FROM {_EMB} a JOIN {_EMB} b ON a.circuit_id = b.circuit_id AND b.idx = xor(a.idx, 8::BIGINT))"


@query(f"SELECT circuit_id, idx, {O.u6('re')} AS re_u6 FROM {_EMB_H}")
def batch_embeddings_h(spark, sf_dir):
    """A Hadamard on qubit 3 of every embedding's register, with array functions only."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("circuit_id"), F.col("embedding").cast("array<double>").alias("a"))
    e = e.withColumn("norm", F.sqrt(F.aggregate("a", F.lit(0.0), lambda s, x: s + x * x)))
    h = F.transform("a", lambda x, i: (F.element_at("a", i.bitwiseXOR(F.lit(8)) + 1) + F.when(F.shiftright(i, 3) % 2 == 0, x).otherwise(-x)) / (F.col("norm") * math.sqrt(2)))
    return e.select("circuit_id", F.posexplode(h).alias("idx", "re")).select("circuit_id", F.col("idx").cast("long").alias("idx"), u6("re").alias("re_u6"))


@query("SELECT user_id AS circuit_id, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - 1 AS ord, CASE event_type WHEN 'view' THEN 'h' WHEN 'click' THEN 'u3' WHEN 'purchase' THEN 'cx' WHEN 'error' THEN 'u1' ELSE 'swap' END AS kind, CAST(json_extract(props, '$.k') AS BIGINT) % 6 AS q0 FROM events")
def events_gate_table(spark, sf_dir):
    return W.events_gates(spark, sf_dir).select("circuit_id", "ord", "kind", F.element_at("qubits", 1).cast("long").alias("q0"))


@query(f"SELECT circuit_id, step AS ord, kind, CAST(t AS BIGINT) AS target FROM ({_ORDERS_G})")
def orders_gate_table(spark, sf_dir):
    return W.orders_gates(spark, sf_dir).select("circuit_id", "ord", "kind", F.element_at("qubits", -1).cast("long").alias("target"))
