"""Measurement, sampling, expectations, noise, and other register classes."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.bits import bit, u6
from ..functions.gates import Circuit, Gate
from ..operators import batch as B
from ..operators import measure as M
from ..operators import rows as R
from ..operators import states as S
from ..sources import workloads as W
from . import oracle as O
from . import query
from .states import amps, customer, orders, table

_P = f"(SELECT idx, re*re + im*im AS p FROM {O.ORDERS})"


@query(f"SELECT idx, {O.u6('p')} AS p_u6 FROM {_P}")
def probabilities(spark, sf_dir):
    return M.probabilities(orders(spark, sf_dir)[0]).select("idx", u6("p").alias("p_u6"))


@query(f"SELECT ((idx >> 1) & 1) + 2*((idx >> 4) & 1) AS value, {O.u6('sum(p)')} AS p_u6 FROM {_P} GROUP BY 1")
def marginals(spark, sf_dir):
    return M.marginals(orders(spark, sf_dir)[0], [1, 4]).select("value", u6("p").alias("p_u6"))


@query(f"SELECT coalesce(x, -1) AS b0, coalesce(y, -1) AS b1, {O.u6('sum(p)')} AS p_u6 FROM (SELECT idx & 1 AS x, (idx >> 1) & 1 AS y, p FROM {_P}) GROUP BY ROLLUP (x, y)")
def marginal_rollup(spark, sf_dir):
    a = M.probabilities(orders(spark, sf_dir)[0]).withColumns({"b0": bit("idx", 0), "b1": bit("idx", 1)})
    return a.rollup("b0", "b1").agg(u6(F.sum("p")).alias("p_u6")).fillna(-1, ["b0", "b1"])


@query(f"SELECT CAST(q AS INT) AS qubit, {O.u6('sum(p) FILTER ((idx >> q) & 1 = 1)')} AS p1_u6 FROM {_P}, range(10) t(q) GROUP BY q")
def qubit_p1(spark, sf_dir):
    return M.qubit_p1(orders(spark, sf_dir)[0], 10).select("qubit", u6("p1").alias("p1_u6"))


_W = f"(SELECT idx, CAST(floor(p*1e9 + 0.5001) AS BIGINT) AS w FROM {_P})"
_SHOTS = f"""WITH w AS (SELECT idx, w, sum(w) OVER (ORDER BY idx) AS hi FROM {_W}), tot AS (SELECT sum(w) AS total FROM w)
    SELECT s AS shot, idx AS outcome FROM (SELECT s, CAST((s * 2654435761) % total AS HUGEINT) AS draw FROM range(200) t(s), tot) JOIN w ON draw >= hi - w AND draw < hi"""


@query(_SHOTS)
def sample_shots(spark, sf_dir):
    a, n = orders(spark, sf_dir)
    return M.sample_shots(a, 200, n)


@query(_SHOTS)
def sample_shots_two_level(spark, sf_dir):
    return M.sample_shots(orders(spark, sf_dir)[0], 200, 6)


@query(f"SELECT outcome, count(*) AS shots FROM ({_SHOTS}) GROUP BY 1")
def counts_map_exploded(spark, sf_dir):
    """Counts of outcomes gathered in a map, filtered and exploded again."""
    c = M.outcome_counts(M.sample_shots(orders(spark, sf_dir)[0], 200, 6))
    m = c.agg(F.map_from_entries(F.collect_list(F.struct("outcome", "shots"))).alias("m"))
    return m.select(F.explode(F.map_filter("m", lambda k, v: v > 0)).alias("outcome", "shots"))


@query(f"SELECT idx, CAST(round(p*1e6) AS BIGINT) AS p_u6 FROM {_P} ORDER BY p DESC, idx LIMIT 25")
def topk_outcomes(spark, sf_dir):
    return M.probabilities(orders(spark, sf_dir)[0]).orderBy(F.desc("p"), "idx").limit(25).select("idx", F.round(F.col("p") * 1e6).cast("long").alias("p_u6"))


@query(f"SELECT idx, {O.u6(f're/sqrt((SELECT sum(re*re) FROM {O.CUSTOMER} WHERE (idx >> 2) & 1 = 1))')} AS re_u6 FROM {O.CUSTOMER} WHERE (idx >> 2) & 1 = 1")
def collapse_renormalise(spark, sf_dir):
    return M.collapse(customer(spark, sf_dir)[0], 2, 1).select("idx", u6("re").alias("re_u6"))


@query(f"SELECT {O.u6('sum(re*re*CASE WHEN bit_count(idx & 11) % 2 = 0 THEN 1 ELSE -1 END)')} AS value_u6 FROM {O.CUSTOMER}")
def expect_z(spark, sf_dir):
    return M.expect_pauli(customer(spark, sf_dir)[0], 0, 11).select(u6("value").alias("value_u6"))


@query(f"SELECT {O.u6('sum(a.re*b.re*CASE WHEN bit_count(a.idx & 4) % 2 = 0 THEN 1 ELSE -1 END)')} AS value_u6 FROM {O.CUSTOMER} a JOIN {O.CUSTOMER} b ON b.idx = xor(a.idx, 3::BIGINT)")
def expect_x(spark, sf_dir):
    return M.expect_pauli(customer(spark, sf_dir)[0], 3, 4).select(u6("value").alias("value_u6"))




@query("SELECT doc_id AS circuit_id, bin AS idx, CAST(floor(sqrt(c / sum(c) OVER (PARTITION BY doc_id)) * 1e6 + 0.5001) AS BIGINT) AS re_u6 FROM (SELECT doc_id, CAST(ascii(ch) % 256 AS BIGINT) AS bin, count(*) AS c FROM (SELECT doc_id, unnest(string_split(text, '')) AS ch FROM documents) WHERE ch <> '' GROUP BY ALL)")
def doc_byte_register(spark, sf_dir):
    return _histogram(table(spark, sf_dir, "documents"), "doc_id", "text").select("circuit_id", "idx", u6("re").alias("re_u6"))


@query("SELECT page_id AS circuit_id, bin AS idx, CAST(floor(sqrt(c / sum(c) OVER (PARTITION BY page_id)) * 1e6 + 0.5001) AS BIGINT) AS re_u6 FROM (SELECT page_id, CAST(ascii(ch) % 256 AS BIGINT) AS bin, count(*) AS c FROM (SELECT page_id, unnest(string_split(html, '')) AS ch FROM pages) WHERE ch <> '' GROUP BY ALL)")
def page_byte_register(spark, sf_dir):
    return _histogram(table(spark, sf_dir, "pages"), "page_id", "html").select("circuit_id", "idx", u6("re").alias("re_u6"))


def _histogram(t, key, text):
    """A register of eight qubits for each text: roots of the shares of its code points mod 256. Counted inside the row, so nothing is shuffled but counts."""
    ch = t.select(F.col(key).alias("circuit_id"), F.explode(F.split(F.coalesce(F.col(text), F.lit("")), "")).alias("ch")).where("ch <> ''")
    c = ch.groupBy("circuit_id", (F.ascii("ch") % 256).cast("long").alias("idx")).agg(F.count(F.lit(1)).alias("c"))
    total = c.groupBy("circuit_id").agg(F.sum("c").alias("t"))
    return c.join(total, "circuit_id").select("circuit_id", "idx", F.sqrt(F.col("c") / F.col("t")).alias("re"))


_EN = "(SELECT vec_id, label, i, CAST(embedding[i+1] AS DOUBLE) / sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE)*CAST(x AS DOUBLE)))) AS re FROM embeddings, range(64) t(i))"


@query(f"WITH e AS {_EN} SELECT a.vec_id AS a, b.vec_id AS b, {O.u6('pow(sum(a.re*b.re), 2)')} AS overlap_u6 FROM e a JOIN e b ON a.i = b.i AND a.vec_id % 20 = 0 AND b.vec_id <> a.vec_id AND b.label = a.label GROUP BY ALL")
def overlap_embeddings(spark, sf_dir):
    """Squared overlap of every twentieth embedding with the others of its label."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"))
    n = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    e = e.select("vec_id", "label", F.transform("v", lambda x: x / n).alias("v"))
    q = e.where("vec_id % 20 = 0").select(F.col("vec_id").alias("a"), "label", F.col("v").alias("w"))
    j = q.join(e, "label").where("a <> vec_id")
    dot = F.aggregate(F.zip_with("v", "w", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return j.select("a", F.col("vec_id").alias("b"), u6(dot * dot).alias("overlap_u6"))


@query(f"SELECT vec_id, {O.u6('sum(re*re)')} AS norm_u6 FROM {_EN} GROUP BY vec_id")
def array_norms(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    n = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    return e.select("vec_id", u6(n / n).alias("norm_u6"))


# noise

_NOISE = W.brickwork(3, 2)


def _noise_sql(shots: int, rate: float) -> str:
    g = O.gates(_NOISE)
    return f"""WITH RECURSIVE g0 AS ({g}), sh AS (SELECT s FROM range({shots}) t(s)),
      own AS (SELECT s AS circuit_id, step*2 AS ord, kind, t, c, theta, phi, lam FROM g0, sh),
      h AS (SELECT s, step, t, (s*7919 + step*104729 + 17) % 10007 AS h FROM g0, sh),
      err AS (SELECT s AS circuit_id, step*2 + 1 AS ord, CASE h % 3 WHEN 2 THEN 'u1' ELSE 'u3' END AS kind, t, t AS c, CASE h % 3 WHEN 2 THEN 0.0 ELSE pi() END AS theta,
        CASE h % 3 WHEN 1 THEN pi()/2 ELSE 0.0 END AS phi, CASE h % 3 WHEN 1 THEN pi()/2 ELSE pi() END AS lam FROM h WHERE h < {rate} * 10007),
      allg AS (SELECT * FROM own UNION ALL SELECT * FROM err),"""


def _noise_loop(shots: int, rate: float, tail: str) -> str:
    ctes = _noise_sql(shots, rate).removeprefix("WITH RECURSIVE ")
    ids = f"SELECT s AS circuit_id FROM range({shots}) t(s)"
    init = f"(SELECT circuit_id, i AS idx, CASE WHEN i = 0 THEN 1.0 ELSE 0.0 END AS re, 0.0 AS im FROM ({ids}), range(8) t(i))"
    gates = "SELECT circuit_id, row_number() OVER (PARTITION BY circuit_id ORDER BY ord) - 1 AS step, kind, t, c, theta, phi, lam FROM allg"
    return O.batch_loop(init, gates, tail, ctes)


def _noisy(spark, shots, rate):
    return B.amplitudes(B.run_batch(M.noisy_gates(W.gate_table(_NOISE, spark), shots, rate), 3))


@query(_noise_loop(40, 0.1, O.amps("fin", "circuit_id, idx")))
def noise_trajectories(spark, sf_dir):
    return amps(_noisy(spark, 40, 0.1), "circuit_id", "idx")


@query(_noise_loop(40, 0.1, f"SELECT idx, {O.u6('avg(re*re + im*im)')} AS p_u6 FROM fin GROUP BY idx"))
def noise_average(spark, sf_dir):
    return _noisy(spark, 40, 0.1).groupBy("idx").agg(u6(F.avg(M.p())).alias("p_u6"))


@query("SELECT 0::BIGINT AS noisy_remaps")
def noise_skips_remaps(spark, sf_dir):
    """Error gates at rate 1 are as many as gates: remaps of the rewritten circuit get none."""
    from ..plans.transpile import plan_blocks

    p = plan_blocks(_NOISE, 2)
    c = Circuit(3, tuple(x.gate for s in p.sections for x in s.steps))
    g = M.noisy_gates(W.gate_table(c, spark), 1, 1.1)
    return g.agg((F.count(F.lit(1)) - 2 * len(_NOISE.gates)).alias("noisy_remaps"))


@query(f"WITH p AS {_P} SELECT idx, {O.u6('sum(p)')} AS p_u6 FROM (SELECT idx, p * CASE WHEN (idx >> 2) & 1 = 1 THEN 0.95 ELSE 0.98 END AS p FROM p UNION ALL SELECT xor(idx, 4::BIGINT), p * CASE WHEN (idx >> 2) & 1 = 1 THEN 0.05 ELSE 0.02 END FROM p) GROUP BY idx")
def readout_error(spark, sf_dir):
    return M.with_readout_error(M.probabilities(orders(spark, sf_dir)[0]), 2, 0.02, 0.05).select("idx", u6("p").alias("p_u6"))


# unitary and density registers: twice the qubits, the column's or bra's index on top

_C3 = W.brickwork(3, 1)
_IDENT = "(SELECT i AS idx, CASE WHEN i % 8 = i // 8 THEN 1.0 ELSE 0.0 END AS re, 0.0 AS im FROM range(64) t(i))"


def _identity(spark):
    return spark.range(64).select(F.col("id").alias("idx"), F.when(F.col("id") % 8 == F.floor(F.col("id") / 8), 1.0).otherwise(0.0).alias("re"), F.lit(0.0).alias("im"))


@query(O.loop(_IDENT, O.gates(_C3)))
def unitary_of_circuit(spark, sf_dir):
    return amps(R.run_gates(_identity(spark), Circuit(6, _C3.gates)))


def _conjugate(c: Circuit, by: int) -> tuple[Gate, ...]:
    """The gates with complex-conjugate matrices on qubits moved up."""
    out = []
    for g in c.gates:
        p = (g.params[0], -g.params[1], -g.params[2]) if g.kind == "u3" else tuple(-x for x in g.params)
        out.append(Gate(g.kind, tuple(q + by for q in g.qubits), p))
    return tuple(out)


@query("SELECT 1000000::BIGINT AS purity_u6, 1000000::BIGINT AS trace_u6")
def density_purity(spark, sf_dir):
    """The density matrix of a pure state after a circuit: purity and trace stay 1."""
    d = R.run_gates(S.zero_state(spark, 6), Circuit(6, _C3.gates + _conjugate(_C3, 3)))
    trace = F.sum(F.when(F.col("idx") % 8 == F.floor(F.col("idx") / 8), F.col("re")).otherwise(0.0))
    return d.agg(u6(F.sum(M.p())).alias("purity_u6"), u6(trace).alias("trace_u6"))


@query(f"WITH p AS {_P}, m AS (SELECT median(p) AS med FROM p) SELECT {O.u6('sum(p)')} AS share_u6 FROM p, m WHERE p > med")
def heavy_output_share(spark, sf_dir):
    """Mass of the outcomes above the median probability."""
    a = M.probabilities(orders(spark, sf_dir)[0])
    return a.where(F.col("p") > M.quantile(a, "p", 0.5)).agg(u6(F.sum("p")).alias("share_u6"))


