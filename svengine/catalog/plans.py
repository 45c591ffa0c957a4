"""Plans of the rewriter and exchange strategies."""

from __future__ import annotations

import pyspark.sql.functions as F

from ..functions.bits import u6
from ..functions.gates import Circuit, Gate
from ..operators import chunks as C
from ..operators import states as S
from ..plans import transpile as T
from ..plans.cost import classify
from ..sources import workloads as W
from . import oracle as O
from . import query
from .runs import blocked, encoded_customer, zero
from .states import amps, line_registers, mismatches


@query("SELECT * FROM (VALUES (0, 2), (1, 0), (2, 3), (3, 4), (4, 1)) v(qubit, position)")
def reorder_idle_plan(spark, sf_dir):
    at = T.reorder_idle(Circuit(5, (Gate("h", (1,)), Gate("h", (4,)))))
    return spark.createDataFrame(list(enumerate(at)), "qubit int, position int")


@query(O.MISMATCHES)
def reorder_idle_state(spark, sf_dir):
    """Only qubits 1 and 4 are busy: one section without any exchange, and the state of the direct run."""
    c = Circuit(5, (Gate("h", (1,)), Gate("cx", (1, 4)), Gate("ry", (4,), (0.3,))))
    p = T.plan_blocks(c, 3, restore_order=False)
    assert len(p.sections) == 1
    return mismatches(blocked(spark, c, 3, restore_order=False), C.rows_of(C.run_baseline(zero(spark, 5, 3), c)))


_WORKED = "(0, 0, 0), (0, 1, 0), (0, 3, 0), (1, 2, 0), (1, 4, 0), (1, 5, 0), (2, 6, 0)"


@query(f"SELECT section, ord FROM (VALUES {_WORKED}) v(section, ord, x)")
def worked_example_plan(spark, sf_dir):
    p = T.plan_blocks(W.worked_example(), 3, restore_order=False)
    return spark.createDataFrame([(i, s.ord) for i, b in enumerate(p.blocks) for s in b.steps], "section int, ord int")


@query("SELECT * FROM (VALUES (0, 0), (0, 1), (0, 4), (0, 6), (1, 3), (2, 2), (2, 5)) v(section, ord)")
def plan_sections(spark, sf_dir):
    """The same circuit with one slot spared when qubits are chosen."""
    p = T.plan_blocks(W.worked_example(), 3, resident_cap=2, restore_order=False)
    return spark.createDataFrame([(i, s.ord) for i, b in enumerate(p.blocks) for s in b.steps], "section int, ord int")


@query("SELECT * FROM (VALUES (0, 0), (0, 1), (0, 3), (1, 2), (1, 3), (1, 4), (2, 0), (2, 2), (2, 3)) v(section, qubit)")
def resident_choice(spark, sf_dir):
    p = T.plan_blocks(W.worked_example(), 3, restore_order=False)
    return spark.createDataFrame([(i, q) for i, b in enumerate(p.blocks) for q in b.resident], "section int, qubit int")


@query("SELECT * FROM (VALUES (0, 1), (1, 2), (2, 1)) v(remap, swaps)")
def remap_pairs(spark, sf_dir):
    p = T.plan_blocks(W.worked_example(), 3, restore_order=False)
    return spark.createDataFrame([(i, len(r.swaps)) for i, r in enumerate(p.remaps)], "remap int, swaps int")


@query("SELECT 0 AS disordered, 0 AS missing")
def retire_order_check(spark, sf_dir):
    """Over variants of a volume circuit: gates out of order on a qubit, and gates missing from the plan."""
    c = W.quantum_volume(spark, sf_dir, 7, 2)
    bad = gone = 0
    for chooser in T.CHOOSERS:
        for cap in (3, 4):
            p = T.plan_blocks(c, 4, resident_cap=cap, chooser=chooser)
            order = [s.ord for x in p.sections for s in x.steps]
            gone += len(set(range(len(c.gates))) - set(order))
            for q in range(c.n):
                own = [k for k in order if q in c.gates[k].qubits]
                bad += own != sorted(own)
    return spark.createDataFrame([(bad, gone)], "disordered int, missing int")


@query(O.MISMATCHES)
def global_fallback(spark, sf_dir):
    """Chunks of one qubit: two-qubit gates run over chunks."""
    c = W.brickwork(4, 2)
    return mismatches(blocked(spark, c, 1), blocked(spark, c, 4))


@query(O.MISMATCHES)
def restore_order(spark, sf_dir):
    """Restoring by a last remap and undoing the layout on reading agree."""
    c = W.brickwork(6, 3)
    return mismatches(blocked(spark, c, 3), blocked(spark, c, 3, restore_order=False))


_VARIANTS = {"plain": {}, "diagonal_free": {"diagonal_free": True}, "control_free": {"control_free": True}, "commuting": {"commute_diagonal": True, "diagonal_free": True}, "spare_slot": {"resident_cap": 3}, "unfused": {"fuse_remaps": False}, "budget": {"max_swaps": 2}}


def _planned(name: str, c: Circuit, nc: int, **o):
    p = T.plan_blocks(c, nc, idle_first=False, restore_order=False, **o)
    return name, len(p.blocks), len(p.remaps), p.n_swaps, sum(len(s.steps) for s in p.sections)


_PLANNED = "sections int, remaps int, swaps int, gates int"


@query("SELECT * FROM (VALUES ('plain', 2, 1, 4, 9), ('diagonal_free', 2, 1, 4, 9), ('control_free', 2, 2, 3, 9), ('commuting', 2, 1, 4, 9), ('spare_slot', 3, 2, 4, 9), ('unfused', 2, 4, 4, 9), ('budget', 3, 2, 4, 9)) v(variant, sections, remaps, swaps, gates)")
def rewriter_variants(spark, sf_dir):
    """Sections, remaps and swaps of three chains of cx on two halves of eight qubits, in chunks of four, as derived by hand.

    Plainly the lower half runs, four pairs are swapped, and the upper half runs. Without controls only targets need be inside: 5 comes in beside 1, 2, 3, then 6 and 7.
    With a slot spared, or two swaps at a time, the upper half comes in two goes.
    """
    return spark.createDataFrame([_planned(v, W.two_halves(8), 4, **o) for v, o in _VARIANTS.items()], f"variant string, {_PLANNED}")


@query("SELECT c AS chooser, 2 AS sections, 1 AS remaps, 4 AS swaps, 9 AS gates FROM (VALUES " + ", ".join(f"('{c}')" for c in T.CHOOSERS) + ") v(c)")
def chooser_comparison(spark, sf_dir):
    """Every chooser finds the two sections of the two halves: the lower one's six gates, one remap of four pairs, the upper one's three."""
    return spark.createDataFrame([_planned(ch, W.two_halves(8), 4, chooser=ch) for ch in T.CHOOSERS], f"chooser string, {_PLANNED}")


@query("SELECT CAST(b AS INT) AS budget, r AS restored, CAST(b AS INT) AS largest, 0::BIGINT AS lost FROM (VALUES (2), (3), (4)) v(b), (VALUES (true), (false)) w(r)")
def swap_budget(spark, sf_dir):
    """The largest remap of a volume circuit's plan, with and without the restoring remaps, and gates that the plan lost."""
    c, rows = W.quantum_volume(spark, sf_dir, 8), []
    for b in (2, 3, 4):
        for r in (True, False):
            p = T.plan_blocks(c, 4, max_swaps=b, restore_order=r)
            rows.append((b, r, max(len(x.swaps) for x in p.remaps), len(c.gates) - sum(len(x.steps) for x in p.sections)))
    return spark.createDataFrame(rows, "budget int, restored boolean, largest int, lost long")


@query(f"SELECT l_suppkey, 'two_halves' AS circuit, section::BIGINT AS section, (section * n)::BIGINT AS swaps, ((2 - section) * (n - 1))::BIGINT AS gates FROM {O.LINE_REGISTERS}, range(2) t(section) WHERE n > 1")
def block_stats_qv(spark, sf_dir):
    """Gates of each section, and swaps before it, of chains on two registers of each supplier's lines, in chunks of one of them."""
    return each_register(line_registers(spark, sf_dir), lambda n: _sections("two_halves", W.two_halves(2 * n), n), _STATS)


_STATS = "circuit string, section long, swaps long, gates long"


def _sections(name: str, c: Circuit, nc: int, **o) -> list[tuple]:
    rows, swaps = [], 0
    for s in T.plan_blocks(c, nc, restore_order=False, idle_first=False, **o).sections:
        if s.op == "block":
            rows.append((name, len({x[1] for x in rows}), swaps, len(s.steps)))
        swaps = len(s.swaps) if s.op == "remap" else 0
    return rows


def each_register(registers, result, kind: str):
    """result(size) -> rows, for every register of a table of key, size (long), where its row lies."""
    import functools

    import pyarrow as pa

    key, size = registers.columns
    types = {"long": pa.int64(), "string": pa.string()}
    fields = [(key, "long"), *(tuple(x.split(" ")) for x in kind.split(", "))]

    def run(batches):
        rows_of = functools.lru_cache(maxsize=4096)(result)
        for b in batches:
            rows = [(k, *x) for k, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) for x in rows_of(v)]
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in rows], types[t]) for i, (_, t) in enumerate(fields)], [name for name, _ in fields])

    return registers.mapInArrow(run, f"{key} long, {kind}")


@query(f"""WITH g AS (SELECT l_suppkey, n, q, CASE WHEN q >= n // 2 THEN 0 ELSE 1 END AS section FROM {O.LINE_REGISTERS}, range(60) t(q) WHERE q < n)
    SELECT l_suppkey, 'fourier' AS circuit, section::BIGINT AS section, (n // 2)::BIGINT AS swaps, sum(q + 1)::BIGINT AS gates FROM g GROUP BY l_suppkey, section, n""")
def block_stats_qft(spark, sf_dir):
    """Fourier circuits of the registers of each supplier's lines, in chunks of half their qubits, diagonal gates free: a Hadamard and q phases for each qubit q, the upper half first."""
    return each_register(line_registers(spark, sf_dir), lambda n: _sections("fourier", W.qft(n, with_swaps=False), (n + 1) // 2, diagonal_free=True), _STATS)


_FEED = """SELECT user_id, CASE event_type WHEN 'view' THEN 'h' WHEN 'click' THEN 'u3' WHEN 'purchase' THEN 'cx' WHEN 'error' THEN 'u1' ELSE 'swap' END AS kind,
    CAST(json_extract(props, '$.k') AS BIGINT) % 6 AS q0, (CAST(json_extract(props, '$.k') AS BIGINT) + 1 + user_id % 5) % 6 AS q1 FROM events"""


def each_circuit(gates, n: int, result, kind: str):
    """result(circuit) -> rows, for every circuit of a gate table, where its gates meet. A circuit is small; no circuit reaches the driver."""
    import pyarrow as pa
    from pyspark.sql.types import _parse_datatype_string

    names = _parse_datatype_string(f"circuit_id long, {kind}").names

    def run(key, t):
        rows = t.sort_by("ord").to_pylist()
        c = Circuit(n, tuple(Gate(r["kind"], tuple(r["qubits"]), tuple(r["params"])) for r in rows))
        got = [(key[0].as_py(), *x) for x in result(c)]
        return pa.table({name: [x[i] for x in got] for i, name in enumerate(names)})

    return gates.groupBy("circuit_id").applyInArrow(run, f"circuit_id long, {kind}")


@query(f"SELECT user_id AS circuit_id, kind, count(*) AS gates FROM ({_FEED}) GROUP BY ALL")
def block_stats_events(spark, sf_dir):
    """Every user's circuit is planned, and the gates in its sections are counted by kind."""

    def kinds(c):
        count = {}
        for b in T.plan_blocks(c, 3, restore_order=False).blocks:
            for s in b.steps:
                count[s.gate.kind] = count.get(s.gate.kind, 0) + 1
        return list(count.items())

    return each_circuit(W.events_gates(spark, sf_dir), 6, kinds, "kind string, gates long")


# exchanges

_ANGLE = (0.7, 0.3, 1.1)
_CUST9 = O.amps(O.u3(O.CUSTOMER, 7, *_ANGLE))

for _s in C.STRATEGIES:
    def _run(spark, sf_dir, strategy=_s):
        r = encoded_customer(spark, sf_dir, 5)
        return amps(C.rows_of(C.Register(C.apply_global(r.df, Gate("u3", (7,), _ANGLE), (7,), r.n, r.nc, strategy), r.n, r.nc)))

    query(_CUST9, f"exchange_{_s}")(_run)


@query(O.MISMATCHES)
def exchange_strategies_agree(spark, sf_dir):
    r = encoded_customer(spark, sf_dir, 5)
    g = Gate("cx", (6, 7))
    out = [C.rows_of(C.Register(C.apply_global(r.df, g, (6, 7), r.n, r.nc, s), r.n, r.nc)) for s in C.STRATEGIES]
    parts = [mismatches(out[0], x) for x in out[1:]]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).agg(F.sum("mismatches").cast("long").alias("mismatches"))


@query("SELECT i AS chunk, xor(i, 1 << k) AS partner, k + 3 AS qubit FROM range(8) a(i), range(3) b(k)")
def chunk_partner_pairs(spark, sf_dir):
    c = spark.range(8).withColumnRenamed("id", "chunk").crossJoin(spark.range(3).withColumnRenamed("id", "k"))
    return c.select("chunk", F.expr("chunk ^ shiftleft(1L, cast(k as int))").alias("partner"), (F.col("k") + 3).alias("qubit"))


@query("""WITH k AS (SELECT CASE event_type WHEN 'view' THEN 'h' WHEN 'click' THEN 'u3' WHEN 'purchase' THEN 'cx' WHEN 'error' THEN 'u1' ELSE 'swap' END AS kind,
    CAST(json_extract(props, '$.k') AS BIGINT) % 6 AS q0, (CAST(json_extract(props, '$.k') AS BIGINT) + 1 + user_id % 5) % 6 AS q1 FROM events),
    t AS (SELECT kind, CASE kind WHEN 'u1' THEN -1 WHEN 'cx' THEN q1 WHEN 'swap' THEN greatest(q0, q1) ELSE q0 END AS top FROM k)
    SELECT kind, CASE WHEN top < 3 THEN 'in_chunk' WHEN top < 4 THEN 'in_space' ELSE 'cross_space' END AS locality, count(*) AS gates FROM t GROUP BY ALL""")
def gate_locality_events(spark, sf_dir):
    """Locality of every gate of the feed for six qubits, chunks of three and four spaces."""
    g = W.events_gates(spark, sf_dir)
    top = F.when(F.col("kind") == "u1", -1).when(F.col("kind") == "cx", F.element_at("qubits", -1)).otherwise(F.array_max("qubits"))
    where = F.when(top < 3, "in_chunk").when(top < 4, "in_space").otherwise("cross_space")
    return g.groupBy("kind", where.alias("locality")).agg(F.count(F.lit(1)).alias("gates"))


@query("SELECT * FROM (VALUES ('in_chunk', 6), ('in_space', 2), ('cross_space', 2)) v(locality, targets)")
def locality_histogram(spark, sf_dir):
    rows = [(classify(Gate("h", (q,)), 10, 6, 4),) for q in range(10)]
    return spark.createDataFrame(rows, "locality string").groupBy("locality").agg(F.count(F.lit(1)).alias("targets"))


def _perm_sql(swaps) -> str:
    masks = " | ".join(f"(1 << {x})" for s in swaps for x in s)
    moves = " | ".join(f"(((idx >> {a}) & 1) << {b}) | (((idx >> {b}) & 1) << {a})" for a, b in swaps)
    return f"(SELECT (idx & ~({masks})) | {moves} AS idx, re, im FROM {O.CUSTOMER})"


def _remapped(spark, sf_dir, swaps):
    r = encoded_customer(spark, sf_dir, 5)
    perm = T.swaps_as_perm(r.n, swaps)
    return S.to_rows(C.run_remap(r.df, perm, r.n, r.nc), r.nc)


for _n, _w in (("remap_low_high", ((1, 6),)), ("remap_high_high", ((5, 7),)), ("remap_low_low", ((1, 3),)), ("remap_fused", ((0, 6), (2, 5), (4, 7)))):
    query(O.amps(_perm_sql(_w)), _n)(lambda s, d, w=_w: amps(_remapped(s, d, w)))


@query(O.MISMATCHES)
def fused_remap_equals_swaps(spark, sf_dir):
    r = encoded_customer(spark, sf_dir, 5)
    one = C.run_remap(r.df, T.swaps_as_perm(r.n, ((0, 6), (2, 5), (6, 7))), r.n, r.nc)
    df = r.df
    for s in ((0, 6), (2, 5), (6, 7)):
        df = C.run_remap(df, T.swaps_as_perm(r.n, (s,)), r.n, r.nc)
    return mismatches(S.to_rows(one, r.nc), S.to_rows(df, r.nc))


@query(f"SELECT 1 AS first_exchanges, 0 AS block_exchanges, {O.size_of('customer')} AS amplitudes, 1000000::BIGINT AS norm_u6")
def block_has_no_exchange(spark, sf_dir):
    """Exchanges that a remap of the customer register and the block after it add to the physical plan, and what running both gives."""
    r = encoded_customer(spark, sf_dir, 5)
    p = T.plan_blocks(W.brickwork(r.n, 1), r.nc, idle_first=False)
    count = lambda df: df._jdf.queryExecution().executedPlan().toString().count("Exchange ")
    remap = C.run_remap(r.df, p.remaps[0].perm, r.n, r.nc)
    block = C.run_block(remap, p.blocks[1].steps, r.nc)
    counts = [F.lit(count(remap) - count(r.df)).alias("first_exchanges"), F.lit(count(block) - count(remap)).alias("block_exchanges")]
    norm = F.sum(F.col("re") * F.col("re") + F.col("im") * F.col("im"))
    return S.to_rows(block, r.nc).agg(F.count(F.lit(1)).alias("amplitudes"), u6(norm).alias("norm_u6")).select(*counts, "amplitudes", "norm_u6")


