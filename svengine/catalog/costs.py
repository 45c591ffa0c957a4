"""Cost and capacity measures, placement and scaling models."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.bits import u6
from ..operators import measure as M
from ..operators import rows as R
from ..plans import cost as K
from ..plans.placement import place_chunks
from ..plans.transpile import plan_blocks
from ..sources import workloads as W
from . import oracle as O
from . import query
from .plans import _FEED, each_circuit, each_register
from .runs import blocked
from .states import line_registers, orders, table


@query(f"SELECT l_suppkey, (28::BIGINT << (n - 1)) AS flops, (64::BIGINT << (n - 1)) AS bytes, CAST(floor(64/28.0*1e6 + 0.5001) AS BIGINT) AS byte_per_flop_u6 FROM {O.LINE_REGISTERS}")
def byte_per_flop(spark, sf_dir):
    """A gate on one qubit of the register of each supplier's lines: all its pairs."""
    gate = lambda n: [(K.PAIR_FLOPS << (n - 1), K.PAIR_BYTES << (n - 1))]
    t = each_register(line_registers(spark, sf_dir), gate, "flops long, bytes long")
    return t.select("l_suppkey", "flops", "bytes", u6(F.col("bytes") / F.col("flops")).alias("byte_per_flop_u6"))


@query("SELECT CAST(n AS INT) AS n, CAST(pow(2, n + 4) AS BIGINT) AS bytes FROM range(1, 51) t(n)")
def state_bytes_table(spark, sf_dir):
    return spark.range(1, 51).select(F.col("id").cast("int").alias("n"), F.expr("shiftleft(16L, cast(id as int))").alias("bytes"))


@query("SELECT o_orderkey, memory, CAST(floor(log2(memory/16.0)) AS BIGINT) AS pair_qubits, CAST(floor(log2(memory/32.0)) AS BIGINT) AS copy_qubits FROM (SELECT o_orderkey, CAST(round(o_totalprice * 1e6) AS BIGINT) AS memory FROM orders) WHERE memory >= 32")
def capacity_table(spark, sf_dir):
    """Each order as a node with a megabyte for each unit of its price: the largest registers that fit."""
    t = table(spark, sf_dir, "orders").select("o_orderkey", F.round(F.col("o_totalprice") * 1e6).cast("long").alias("memory")).where("memory >= 32")
    return each_register(t, lambda memory: [(memory, K.max_qubits(memory), K.max_qubits(memory, "copy"))], "memory long, pair_qubits long, copy_qubits long")


@query(f"SELECT l_suppkey, m::BIGINT AS spaces, (16::BIGINT << n) AS copy_bytes, m * (16::BIGINT << ((n + 1) // 2)) AS pair_bytes FROM {O.LINE_REGISTERS}, (VALUES (1), (2), (4), (8)) v(m)")
def buffer_overhead(spark, sf_dir):
    """Memory beside the register of each supplier's lines: a second register, or a chunk of half its qubits for each space."""
    beside = lambda n: [(m, K.state_bytes(n), m * K.state_bytes((n + 1) // 2)) for m in (1, 2, 4, 8)]
    return each_register(line_registers(spark, sf_dir), beside, "spaces long, copy_bytes long, pair_bytes long")


_COSTS = "method string, section int, gate_ord int, movement string, chunk_moves long, bytes long, flops long"


def _cost_df(spark, costs):
    return spark.createDataFrame([tuple(c.__dict__[f] for f in ("method", "section", "gate_ord", "movement", "chunk_moves", "bytes", "flops")) for c in costs], _COSTS)


@query(f"""WITH {O.volume_ctes(8, 10)[:-1]}, g AS ({O.volume_gates(8)}) SELECT CASE WHEN t < 4 THEN 'in_chunk' WHEN t < 6 THEN 'in_space' ELSE 'cross_space' END AS movement, count(*) AS gates,
    CAST(sum(CASE WHEN t >= 4 THEN 16 ELSE 0 END) AS BIGINT) AS chunk_moves, CAST(sum(CASE WHEN t >= 4 THEN 4096 ELSE 0 END) AS BIGINT) AS bytes FROM g GROUP BY 1""")
def exchange_cost_qv(spark, sf_dir):
    c = _cost_df(spark, K.baseline_cost(W.quantum_volume(spark, sf_dir, 8), 4, 4))
    return c.groupBy("movement").agg(F.count(F.lit(1)).alias("gates"), F.sum("chunk_moves").alias("chunk_moves"), F.sum("bytes").alias("bytes"))


@query("SELECT 'per_gate_pair' AS method, 7 AS exchanges, CAST(7 * 16 * 16384 AS BIGINT) AS bytes UNION ALL SELECT 'blocked_fused', 2, CAST(2 * 16 * 16384 AS BIGINT)")
def exchange_cost_qft(spark, sf_dir):
    """A Fourier circuit of 14 qubits in chunks of 7, without its closing swaps: the per-gate run exchanges for each of the seven high
    Hadamards; with diagonal gates free the rewritten one remaps once to bring the high qubits in, and once to restore the order."""
    c = W.qft(14, with_swaps=False)
    base = K.totals(K.baseline_cost(c, 7, 4))
    plan = K.totals(K.blocked_cost(plan_blocks(c, 7, diagonal_free=True, idle_first=False), 4))
    return spark.createDataFrame([("per_gate_pair", base["exchanges"], base["bytes"]), ("blocked_fused", plan["exchanges"], plan["bytes"])], "method string, exchanges int, bytes long")


@query(f"""WITH t AS (SELECT user_id, CASE kind WHEN 'u1' THEN -1 WHEN 'cx' THEN q1 WHEN 'swap' THEN greatest(q0, q1) ELSE q0 END AS top FROM ({_FEED}))
    SELECT user_id AS circuit_id, count(*) FILTER (top >= 3) AS exchanges, CAST(count(*) FILTER (top >= 3) * 8 AS BIGINT) AS chunk_moves, CAST(count(*) FILTER (top >= 3) * 1024 AS BIGINT) AS bytes FROM t GROUP BY user_id""")
def exchange_cost_events(spark, sf_dir):
    """Per-gate costs of every user's circuit."""
    cost = lambda c: [tuple(K.totals(K.baseline_cost(c, 3, 4))[k] for k in ("exchanges", "chunk_moves", "bytes"))]
    return each_circuit(W.events_gates(spark, sf_dir), 6, cost, "exchanges long, chunk_moves long, bytes long")


@query("SELECT * FROM (VALUES ('pair', CAST(7 * 128 * 2048 AS BIGINT)), ('copy', CAST(2 * 7 * 128 * 2048 AS BIGINT))) v(strategy, bytes)")
def exchange_cost_copy(spark, sf_dir):
    """The full-copy exchange sends every chunk to two tasks."""
    c = W.qft(14, with_swaps=False)
    return spark.createDataFrame([(s, K.totals(K.baseline_cost(c, 7, 4, s))["bytes"]) for s in ("pair", "copy")], "strategy string, bytes long")


@query("SELECT * FROM (VALUES ('full_chunk', CAST(16 * 16384 AS BIGINT)), ('minimal', CAST(16 * 16384 * 7 / 8 AS BIGINT))) v(wire, bytes)")
def remap_wire_bytes(spark, sf_dir):
    """A fused remap of three low/high pairs of a 14-qubit register: whole chunks, or only what changes place."""
    from ..plans.transpile import Plan, Section

    p = Plan(14, 7, (Section("remap", swaps=((0, 7), (1, 8), (2, 9))),), (), ())
    return spark.createDataFrame([(w, K.totals(K.blocked_cost(p, 4, w))["bytes"]) for w in ("full_chunk", "minimal")], "wire string, bytes long")


@query("SELECT * FROM (VALUES ('in_chunk', 3, CAST(0 AS BIGINT)), ('in_space', 2, 8), ('cross_space', 1, 4)) v(movement, steps, chunk_moves)")
def movement_kinds(spark, sf_dir):
    """The worked example on two spaces: three sections inside chunks, and remaps of which the second one crosses spaces."""
    t = _cost_df(spark, K.blocked_cost(plan_blocks(W.worked_example(), 3, restore_order=False), 2))
    return t.groupBy("movement").agg(F.count(F.lit(1)).cast("int").alias("steps"), F.sum("chunk_moves").alias("chunk_moves"))


@query("SELECT * FROM (VALUES ('cpu_load', 0::BIGINT), ('cpu_to_fast', 12), ('fast_load', 28), ('fast_to_fast', 8), ('node_to_node', 4)) v(movement, chunk_moves)")
def movement_profile(spark, sf_dir):
    """The worked example in four chunks on two spaces, two of the chunks in the slow tier: three remaps, the second one across spaces."""
    p = plan_blocks(W.worked_example(), 3, restore_order=False)
    return spark.createDataFrame(list(K.movement_profile(p, 2, 2).items()), "movement string, chunk_moves long")


#: A Fourier circuit of n qubits on 2^p spaces, a chunk each: gate by gate it exchanges for each of the p high Hadamards, rewritten it remaps twice.
_EXCHANGES = "(VALUES ('per_gate'), ('blocked')) e(method)"


def _model_sql(rows: str) -> str:
    moved = "16*pow(2, n)*(CASE WHEN method = 'per_gate' THEN p WHEN p > 0 THEN 2 ELSE 0 END)"
    return f"SELECT n, CAST(pow(2, p) AS INT) AS m, method, {O.u6('1e6*(n*(n + 1)/2*(pow(2, n)/pow(2, p))*32/1e11 + CASE WHEN p > 0 THEN ' + moved + '/pow(2, p)/1e10 ELSE 0 END)')} AS time_u6 FROM {rows}, {_EXCHANGES}"


def _model(spark, pairs):
    """Microseconds from the plans' own gates and bytes."""
    rows = []
    for n, p in pairs:
        c, nc, m = W.qft(n, with_swaps=False), n - p, 2**p
        moved = {"per_gate": K.totals(K.baseline_cost(c, nc, m))["bytes"], "blocked": K.totals(K.blocked_cost(plan_blocks(c, nc, diagonal_free=True, idle_first=False), m))["bytes"]}
        rows += [(n, m, method, 1e6 * K.time_model(n, m, len(c.gates), x, 1e11, 1e10)) for method, x in moved.items()]
    return spark.createDataFrame(rows, "n int, m int, method string, t double").select("n", "m", "method", u6("t").alias("time_u6"))


@query(_model_sql("(SELECT CAST(14 AS INT) AS n, p FROM range(5) v(p))"))
def strong_scaling_model(spark, sf_dir):
    return _model(spark, [(14, p) for p in range(5)])


@query(_model_sql("(SELECT CAST(10 + p AS INT) AS n, p FROM range(5) v(p))"))
def weak_scaling_model(spark, sf_dir):
    return _model(spark, [(10 + p, p) for p in range(5)])


@query("SELECT CAST(n AS INT) AS n, CASE WHEN n <= 29 THEN 'one_fast' WHEN n <= 32 THEN 'all_fast' WHEN n <= 35 THEN 'fast_and_slow' ELSE 'too_large' END AS step FROM range(25, 37) t(n)")
def time_steps_model(spark, sf_dir):
    """Where a register of n qubits fits on one node: 16 GB, six times that, and 512 GB more."""
    one, six, all_ = (K.max_qubits(x) for x in (16 * 10**9, 96 * 10**9, 608 * 10**9))
    step = lambda n: "one_fast" if n <= one else "all_fast" if n <= six else "fast_and_slow" if n <= all_ else "too_large"
    return spark.createDataFrame([(n, step(n)) for n in range(25, 37)], "n int, step string")


_SPACES = [(0, 0, "fast", 4, 0), (1, 0, "fast", 4, 1), (2, 0, "slow", 20, 2)]


def _place(spark, reserve):
    s = spark.createDataFrame(_SPACES, "space int, node int, tier string, capacity_bytes long, priority int")
    return place_chunks(s, spark.range(16).withColumnRenamed("id", "chunk"), 1, reserve).select("chunk", "space", "tier")


@query("SELECT i AS chunk, CASE WHEN i < 4 THEN 0 WHEN i < 8 THEN 1 ELSE 2 END::INT AS space, CASE WHEN i < 8 THEN 'fast' ELSE 'slow' END AS tier FROM range(16) t(i)")
def placement_tiers(spark, sf_dir):
    return _place(spark, 0)


@query("SELECT i AS chunk, CASE WHEN i < 3 THEN 0 WHEN i < 6 THEN 1 ELSE 2 END::INT AS space, CASE WHEN i < 6 THEN 'fast' ELSE 'slow' END AS tier FROM range(16) t(i)")
def placement_with_buffers(spark, sf_dir):
    return _place(spark, 1)


@query("""WITH s AS (SELECT n_nationkey, n_regionkey, (n_nationkey + 1) * 3 AS room, sum((n_nationkey + 1) * 3) OVER (ORDER BY n_nationkey) AS hi FROM nation)
    SELECT n_nationkey AS node, n_regionkey AS site, count(*) AS chunks, min(i) AS first_chunk FROM range(512) t(i) JOIN s ON i >= hi - room AND i < hi GROUP BY ALL""")
def placement_multi_node(spark, sf_dir):
    """512 chunks over the nations as nodes, neighbouring chunks together."""
    s = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("space"), F.col("n_regionkey").alias("node"), F.lit("slow").alias("tier"), ((F.col("n_nationkey") + 1) * 3).cast("long").alias("capacity_bytes"), F.col("n_nationkey").alias("priority"))
    placed = place_chunks(s, spark.range(512).withColumnRenamed("id", "chunk"), 1)
    return placed.groupBy(F.col("space").alias("node"), F.col("node").alias("site")).agg(F.count(F.lit(1)).alias("chunks"), F.min("chunk").alias("first_chunk"))


_CQ = f"WITH {O.volume_ctes(8, 2)[:-1]}, g AS (SELECT kind, CASE WHEN t < 4 THEN 'in_chunk' WHEN t < 6 THEN 'in_space' ELSE 'cross_space' END AS movement, CASE WHEN t >= 4 THEN 4096 ELSE 0 END AS bytes FROM ({O.volume_gates(8)}))"


def _volume_costs(spark, sf_dir):
    c = W.quantum_volume(spark, sf_dir, 8, 2)
    return _cost_df(spark, K.baseline_cost(c, 4, 4)).join(W.gate_table(c, spark).select(F.col("ord").alias("gate_ord"), "kind"), "gate_ord")


@query(f"{_CQ} SELECT kind, movement, count(*) AS gates, CAST(sum(bytes) AS BIGINT) AS bytes FROM g GROUP BY CUBE (kind, movement)")
def cost_cube(spark, sf_dir):
    return _volume_costs(spark, sf_dir).cube("kind", "movement").agg(F.count(F.lit(1)).alias("gates"), F.sum("bytes").alias("bytes"))


@query(f"{_CQ} SELECT kind, movement, CAST(sum(bytes) AS BIGINT) AS bytes FROM g GROUP BY GROUPING SETS ((kind), (movement))")
def cost_grouping_sets(spark, sf_dir):
    _volume_costs(spark, sf_dir).createOrReplaceTempView("volume_costs")
    return spark.sql("SELECT kind, movement, sum(bytes) AS bytes FROM volume_costs GROUP BY GROUPING SETS ((kind), (movement))")


@query(f"SELECT {O.u6('sum(re*re + im*im)')} AS norm_u6 FROM {O.u3(O.ORDERS, 3, 0.7, 0.3, 1.1)}")
def norm_check(spark, sf_dir):
    return R.norm(R.apply_u3(orders(spark, sf_dir)[0], 3, 0.7, 0.3, 1.1)).select(u6("norm").alias("norm_u6"))


@query("SELECT 1000000::BIGINT AS fidelity_u6, 0::BIGINT AS max_error_u6")
def fidelity_blocked_vs_direct(spark, sf_dir):
    from ..operators import states as S

    c = W.quantum_volume(spark, sf_dir, 6, 2)
    return M.fidelity(blocked(spark, c, 3), R.run_gates(S.zero_state(spark, 6), c)).select(u6("fidelity").alias("fidelity_u6"), u6("max_error").alias("max_error_u6"))


@query(f"SELECT {O.u6('sum(re*re)')} AS norm_u6 FROM {O.ORDERS}")
def udaf_norm(spark, sf_dir):
    """The norm as a grouped-aggregate function over Arrow batches, by chunk first so that no task gets the register."""
    import pandas as pd

    def squares(re, im):
        return float((re * re + im * im).sum())

    squares.__annotations__ = {"re": pd.Series, "im": pd.Series, "return": float}
    f = F.pandas_udf(squares, "double")
    a = orders(spark, sf_dir)[0].withColumn("chunk", F.shiftright("idx", 8))
    return a.groupBy("chunk").agg(f("re", "im").alias("s")).agg(u6(F.sum("s")).alias("norm_u6"))
