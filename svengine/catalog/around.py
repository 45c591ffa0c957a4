"""Operators around the methods: scripts, joins, windows, sets, dates, sampling, recursion, SQL."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.bits import u6
from ..operators import measure as M
from ..operators import rows as R
from ..operators import states as S
from ..sources import qasm, volumes
from ..sources import workloads as W
from ..sqlsurface import register_sql
from . import oracle as O
from . import query
from .reading import _histogram
from .states import customer, mismatches, orders, supplier, table


@query(O.MISMATCHES)
def qasm_roundtrip(spark, sf_dir):
    """A script read through the data source gives the same state as the circuit it was written from."""
    c = W.brickwork(5, 2)
    spark.dataSource.register(qasm.GateScript)
    g = spark.read.format("gatescript").option("script", qasm.emit(c)).load()
    return mismatches(R.run_gates(S.zero_state(spark, 5), W.circuit_from_df(g, 5)), R.run_gates(S.zero_state(spark, 5), c))


@query("SELECT 0::BIGINT AS mismatches")
def gates_json_roundtrip(spark, sf_dir):
    g = W.events_gates(spark, sf_dir)
    back = g.select(F.to_json(F.struct("*")).alias("j")).select(F.from_json("j", W.GATES).alias("g")).select("g.*")
    key = lambda d: d.select("circuit_id", "ord", "kind", "qubits", F.transform("params", lambda x: F.round(x, 9)).alias("params"))
    return key(g).exceptAll(key(back)).agg(F.count(F.lit(1)).alias("mismatches"))


@query(f"SELECT idx, {O.u6('re')} AS re_u6 FROM {O.ORDERS} WHERE re*re > 0.00008")
def filter_heavy_amplitudes(spark, sf_dir):
    return orders(spark, sf_dir)[0].where("re*re > 0.00008").select("idx", u6("re").alias("re_u6"))


_KIND = "CASE event_type WHEN 'view' THEN 'h' WHEN 'click' THEN 'u3' WHEN 'purchase' THEN 'cx' WHEN 'error' THEN 'u1' ELSE 'swap' END"


@query(f"""SELECT a.event_id, coalesce((SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'click' AND b.event_id < a.event_id), -1) AS last_click FROM events a WHERE a.event_type = 'purchase'""")
def asof_last_gate(spark, sf_dir):
    """For every purchase the user's last click before it: one window instead of a join."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_click", last).where("event_type = 'purchase'").select("event_id", F.coalesce("last_click", F.lit(-1)).alias("last_click"))


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def semi_labelled_docs(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def anti_unlabelled_docs(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id", "lang")


_DEP = ", ".join(f"({k}, {list(g.qubits)})" for k, g in enumerate(W.worked_example().gates))


@query(f"WITH g(ord, qubits) AS (VALUES {_DEP}) SELECT CAST(a.ord AS BIGINT) AS before, CAST(b.ord AS BIGINT) AS after FROM g a JOIN g b ON a.ord < b.ord AND list_has_any(a.qubits, b.qubits)")
def gate_dependencies(spark, sf_dir):
    g = W.gate_table(W.worked_example(), spark).select("ord", "qubits")
    q = g.select(F.col("ord").alias("o"), F.explode("qubits").alias("q"))
    # equal qubits make the join an equi-join; distinct, as two gates may share two qubits
    b = q.select(F.col("o").alias("after"), "q")
    return q.join(b, "q").where("o < after").select(F.col("o").alias("before"), "after").distinct()


@query(f"WITH g(ord, qubits) AS (VALUES {_DEP}) SELECT CAST(ord AS BIGINT) AS ord FROM g b WHERE NOT EXISTS (SELECT 1 FROM g a WHERE a.ord < b.ord AND list_has_any(a.qubits, b.qubits))")
def front_layer_gates(spark, sf_dir):
    """Gates that no earlier gate on one of their qubits holds back: a correlated NOT EXISTS, which becomes an anti-join on ord."""
    q = W.gate_table(W.worked_example(), spark).select("ord", F.explode("qubits").alias("q"))
    held = "SELECT 1 FROM {q} a JOIN {q} o ON a.q = o.q AND a.ord < o.ord WHERE o.ord = b.ord"
    return spark.sql(f"SELECT DISTINCT b.ord FROM {{q}} b WHERE NOT EXISTS ({held})", q=q)


@query("SELECT 4 AS depth")
def circuit_depth(spark, sf_dir):
    """The longest chain of dependent gates in the worked example, by a recursive query."""
    W.gate_table(W.worked_example(), spark).select("ord", F.explode("qubits").alias("q")).createOrReplaceTempView("worked_qubits")
    spark.sql("SELECT DISTINCT a.ord AS a, b.ord AS b FROM worked_qubits a JOIN worked_qubits b ON a.q = b.q AND a.ord < b.ord").createOrReplaceTempView("worked_edges")
    return spark.sql("WITH RECURSIVE lv(ord, level) AS (SELECT DISTINCT ord, 1 FROM worked_qubits UNION ALL SELECT e.b, l.level + 1 FROM lv l JOIN worked_edges e ON e.a = l.ord) SELECT max(level) AS depth FROM lv")


@query("SELECT count(DISTINCT CAST(json_extract(props, '$.k') AS BIGINT) % 6) AS qubits, count(DISTINCT user_id) AS circuits FROM events")
def distinct_qubits_used(spark, sf_dir):
    g = W.events_gates(spark, sf_dir)
    return g.agg(F.countDistinct(F.element_at("qubits", 1)).alias("qubits"), F.countDistinct("circuit_id").alias("circuits"))


@query("SELECT count(DISTINCT l_partkey) AS parts, true AS within FROM lineitem")
def approx_distinct_parts(spark, sf_dir):
    """Distinct part keys, and whether the sketch's number, asked for with a deviation of 1 %, lies within 5 % of it."""
    t = table(spark, sf_dir, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.01).alias("near"))
    return t.select("parts", (F.abs(F.col("near") - F.col("parts")) <= F.col("parts") * 0.05).alias("within"))


@query(f"SELECT q0, count(*) FILTER (kind = 'h') AS h, count(*) FILTER (kind = 'u3') AS u3, count(*) FILTER (kind = 'cx') AS cx FROM (SELECT {_KIND} AS kind, CAST(json_extract(props, '$.k') AS BIGINT) % 6 AS q0 FROM events) GROUP BY q0")
def gate_kind_pivot(spark, sf_dir):
    g = W.events_gates(spark, sf_dir).select("kind", F.element_at("qubits", 1).cast("long").alias("q0"))
    return g.groupBy("q0").pivot("kind", ["h", "u3", "cx"]).agg(F.count(F.lit(1))).fillna(0)


@query("SELECT event_id, CAST(event_id - lag(event_id, 1, event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS BIGINT) AS gap, CAST(lead(event_id, 1, -1) OVER (PARTITION BY user_id ORDER BY event_id) AS BIGINT) AS next_gate FROM events")
def gate_gaps(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id")
    e = table(spark, sf_dir, "events")
    return e.select("event_id", (F.col("event_id") - F.coalesce(F.lag("event_id").over(w), F.col("event_id"))).alias("gap"), F.coalesce(F.lead("event_id").over(w), F.lit(-1).cast("long")).alias("next_gate"))


_SP = f"(SELECT idx, re*re AS p FROM {O.SUPPLIER})"


@query(f"SELECT idx, rank() OVER (ORDER BY round(p*1e6) DESC) AS rnk, dense_rank() OVER (ORDER BY round(p*1e6) DESC) AS dense, ntile(4) OVER (ORDER BY round(p*1e6) DESC, idx) AS tile FROM {_SP}")
def outcome_ranks(spark, sf_dir):
    """Ranks of all outcomes without a window over all of them: over the distinct rounded probabilities (a million at most), over runs of 256 indices with the same one, then in each run."""
    p = M.probabilities(supplier(spark, sf_dir)[0]).select("idx", F.round(F.col("p") * 1e6).alias("r"), F.shiftright("idx", 8).alias("run"))
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    kinds = p.groupBy("r").agg(F.count(F.lit(1)).alias("n"))
    by = Window.orderBy(F.desc("r"))
    kinds = kinds.select("r", F.coalesce(F.sum("n").over(before(by)), F.lit(0)).alias("above"), F.row_number().over(by).alias("dense"), F.sum("n").over(Window.partitionBy()).alias("total"))
    runs = p.groupBy("r", "run").agg(F.count(F.lit(1)).alias("n"))
    runs = runs.select("r", "run", F.coalesce(F.sum("n").over(before(Window.partitionBy("r").orderBy("run"))), F.lit(0)).alias("earlier"))
    out = p.withColumn("k", F.row_number().over(Window.partitionBy("r", "run").orderBy("idx")) - 1).join(runs, ["r", "run"]).join(kinds, "r")
    out = out.withColumns({"at": F.col("above") + F.col("earlier") + F.col("k"), "size": F.expr("total div 4"), "more": F.expr("total % 4")})
    tile = F.expr("if(at < more * (size + 1), at div (size + 1), more + (at - more * (size + 1)) div greatest(size, 1)) + 1")
    return out.select("idx", (F.col("above") + 1).cast("long").alias("rnk"), F.col("dense").cast("long").alias("dense"), tile.cast("long").alias("tile"))


@query(f"SELECT idx, CAST(sum(CAST(floor(p*1e9 + 0.5001) AS BIGINT)) OVER (ORDER BY idx) AS BIGINT) AS mass FROM (SELECT idx, re*re + im*im AS p FROM {O.ORDERS})")
def cumulative_mass(spark, sf_dir):
    """Running mass in two levels: runs of 256 indices, then inside each."""
    w = M.billionths(orders(spark, sf_dir)[0]).withColumn("run", F.shiftright("idx", 8))
    runs = w.groupBy("run").agg(F.sum("w").alias("m")).withColumn("before", F.coalesce(F.sum("m").over(Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    inner = F.sum("w").over(Window.partitionBy("run").orderBy("idx"))
    return w.withColumn("inner", inner).join(runs, "run").select("idx", (F.col("before") + F.col("inner")).alias("mass"))


@query("SELECT label, vec_id FROM (SELECT label, vec_id, row_number() OVER (PARTITION BY label ORDER BY round(abs(CAST(embedding[1] AS DOUBLE))*1e6) DESC, vec_id) AS r FROM embeddings) WHERE r <= 3")
def topk_per_label(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").withColumn("a", F.round(F.abs(F.element_at("embedding", 1).cast("double")) * 1e6))
    w = Window.partitionBy("label").orderBy(F.desc("a"), "vec_id")
    return e.withColumn("r", F.row_number().over(w)).where("r <= 3").select("label", "vec_id")


_A, _B = f"SELECT idx FROM {O.CUSTOMER} WHERE re <> 0", f"SELECT idx FROM {O.SUPPLIER} WHERE re <> 0"
for _n, _op, _f in (("support_union", "UNION", lambda a, b: a.union(b).distinct()), ("support_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("support_except", "EXCEPT", lambda a, b: a.subtract(b))):
    query(f"{_A} {_op} {_B}", _n)(lambda s, d, f=_f: f(customer(s, d)[0].where("re <> 0").select("idx"), supplier(s, d)[0].where("re <> 0").select("idx")))


@query(f"SELECT idx, '|' || lpad(bin(idx), n, '0') || '>' AS label FROM {O.ORDERS}, (SELECT CAST(greatest(1, ceil(log2(count(*)))) AS INT) AS n FROM orders)")
def bitstring_labels(spark, sf_dir):
    """A label for every index of the orders register, as long as it has qubits."""
    a, n = orders(spark, sf_dir)
    return a.select("idx", F.format_string("|%s>", F.lpad(F.bin("idx"), n, "0")).alias("label"))


_LINES = [f"{k},{x}" for k, x in enumerate(qasm.emit(W.worked_example()).split("\n")[2:-1])]


@query("SELECT * FROM (VALUES " + ", ".join(f"({k}, '{g.kind}', {g.qubits[0]})" for k, g in enumerate(W.worked_example().gates)) + ") v(ord, kind, q0)")
def parse_gate_lines(spark, sf_dir):
    """Script lines parsed with string functions."""
    t = spark.createDataFrame([(x,) for x in _LINES], "line string")
    return t.select(F.split("line", ",")[0].cast("int").alias("ord"), F.regexp_extract("line", r",([a-z]\w*)", 1).alias("kind"), F.regexp_extract("line", r"\[(\d+)\]", 1).cast("int").alias("q0"))


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS gates, count(DISTINCT user_id) AS circuits FROM events GROUP BY 1")
def circuits_per_day(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count(F.lit(1)).alias("gates"), F.countDistinct("user_id").alias("circuits"))


@query(f"SELECT o_orderkey AS circuit_id, {O.u6('cos(pi()*dayofyear(o_orderdate)/366)')} AS c_u6, {O.u6('sin(pi()*dayofyear(o_orderdate)/366)')} AS s_u6 FROM orders")
def date_angle_encode(spark, sf_dir):
    a = F.lit(math.pi) * F.dayofyear("o_orderdate") / 366
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("circuit_id"), u6(F.cos(a)).alias("c_u6"), u6(F.sin(a)).alias("s_u6"))


@query(f"SELECT idx, {O.u6('sqrt(re*re + im*im)')} AS r_u6, {O.u6('atan2(im, re)')} AS phase_u6 FROM {O.u3(O.ORDERS, 2, 0.7, 0.3, 1.1)} WHERE re <> 0 OR im <> 0")
def amplitude_polar(spark, sf_dir):
    """Radius and phase of the orders register's amplitudes after a gate that turns phases; zeros have no phase."""
    a = R.apply_u3(orders(spark, sf_dir)[0], 2, 0.7, 0.3, 1.1).where("re <> 0 or im <> 0")
    return a.select("idx", u6(F.sqrt(M.p())).alias("r_u6"), u6(F.atan2("im", "re")).alias("phase_u6"))


@query(f"SELECT o_orderkey AS idx, xor(o_orderkey, 5::BIGINT) AS flipped, CAST(bit_count(o_orderkey) AS INT) AS ones, (o_orderkey >> 2) & 1 AS bit2, (o_orderkey << 1) & ({O.size_of('orders')} - 1) AS shifted FROM orders")
def bit_ops_states(spark, sf_dir):
    """Bit operations on the indices that orders have in their register."""
    t = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("idx"))
    last, x = 2 ** S.qubits_for(t.count()) - 1, F.col("idx")
    return t.select("idx", x.bitwiseXOR(F.lit(5)).alias("flipped"), F.bit_count("idx").cast("int").alias("ones"), F.shiftright("idx", 2).bitwiseAND(F.lit(1)).alias("bit2"), F.shiftleft("idx", 1).bitwiseAND(F.lit(last)).alias("shifted"))


@query("SELECT o_orderkey FROM orders WHERE (o_orderkey * 7919 + 17) % 10007 < 500")
def hash_sample_orders(spark, sf_dir):
    """A sampling operator: rows whose hash falls below the rate."""
    return table(spark, sf_dir, "orders").where("(o_orderkey * 7919 + 17) % 10007 < 500").select("o_orderkey")


_Q6 = W.qft(6)


@query("SELECT * FROM (VALUES " + ", ".join(f"({k}, '{g.kind}', {g.qubits[0]})" for k, g in enumerate(_Q6.gates)) + ") v(ord, kind, q0)")
def udtf_qft_gates(spark, sf_dir):
    register_sql(spark)
    return spark.sql("SELECT cast(ord AS int) AS ord, kind, q0 FROM qft_gates(6)")


@query(f"SELECT count(*) AS outcomes, {O.u6('sum(re*re)')} AS mass_u6 FROM {O.ORDERS}")
def sql_surface(spark, sf_dir):
    register_sql(spark, {"orders_register": orders(spark, sf_dir)[0]})
    return spark.sql("SELECT count(*) AS outcomes, CAST(floor(sum(p) * 1e6 + 0.5001) AS BIGINT) AS mass_u6 FROM orders_register_p")


@query("SELECT 0::BIGINT AS differing_chunks")
def cogroup_compare(spark, sf_dir):
    """Two packed registers compared chunk by chunk where they meet."""
    import numpy as np
    import pyarrow as pa

    a = S.to_chunks(orders(spark, sf_dir)[0], 7)

    def differ(key, x, y):
        u, v = (np.frombuffer(t["amp"][0].as_py(), "<c16") for t in (x, y))
        return pa.table({"chunk": pa.array([key[0].as_py()], pa.int64()), "differs": pa.array([int(np.abs(u - v).max() > 1e-12)], pa.int64())})

    b = S.to_chunks(S.to_rows(a, 7), 7)
    return a.groupBy("chunk").cogroup(b.groupBy("chunk")).applyInArrow(differ, "chunk long, differs long").agg(F.sum("differs").alias("differing_chunks"))


_BINS = "SELECT {k} AS k, CAST(ascii(ch) % 256 AS BIGINT) AS bin, count(*) AS c FROM (SELECT {k}, unnest(string_split(text, '')) AS ch FROM {t}) WHERE ch <> '' GROUP BY ALL"
_HIST = "SELECT k, bin, sqrt(c / sum(c) OVER (PARTITION BY k)) AS re FROM ({})"


@query(f"WITH d AS ({_HIST.format(_BINS.format(k='doc_id', t='documents'))}), b AS ({_HIST.format(_BINS.format(k='item_id', t='benchmark'))}), q AS (SELECT d.k, b.k AS item, sum(d.re*b.re) AS o FROM d JOIN b ON d.bin = b.bin WHERE d.k % 20 = 0 GROUP BY ALL) SELECT k AS doc_id, CAST(floor(max(o*o)*1e6 + 0.5001) AS BIGINT) AS best_u6 FROM q GROUP BY k")
def overlap_docs_benchmark(spark, sf_dir):
    """Every twentieth document's largest squared overlap with a benchmark item's register (256 bins each, all items)."""
    d = _histogram(table(spark, sf_dir, "documents").where("doc_id % 20 = 0"), "doc_id", "text")
    b = _histogram(table(spark, sf_dir, "benchmark"), "item_id", "text").select(F.col("circuit_id").alias("item"), "idx", F.col("re").alias("r"))
    o = d.join(b, "idx").groupBy("circuit_id", "item").agg(F.sum(F.col("re") * F.col("r")).alias("o"))
    return o.groupBy(F.col("circuit_id").alias("doc_id")).agg(u6(F.max(F.col("o") * F.col("o"))).alias("best_u6"))


@query(f"WITH d AS ({_HIST.format(_BINS.format(k='doc_id', t='documents'))}) SELECT quality, {O.u6('avg(z)')} AS z_u6 FROM (SELECT k, sum(re*re*CASE WHEN bin & 32 = 0 THEN 1 ELSE -1 END) AS z FROM d GROUP BY k) JOIN labels ON doc_id = k GROUP BY quality")
def expect_labels(spark, sf_dir):
    """Mean expectation of Z on qubit 5 of the documents' registers, by quality label."""
    d = _histogram(table(spark, sf_dir, "documents"), "doc_id", "text").withColumn("im", F.lit(0.0))
    z = d.groupBy(F.col("circuit_id").alias("doc_id")).agg(F.sum(M.p() * F.when(F.col("idx").bitwiseAND(F.lit(32)) == 0, 1.0).otherwise(-1.0)).alias("z"))
    return z.join(table(spark, sf_dir, "labels"), "doc_id").groupBy("quality").agg(u6(F.avg("z")).alias("z_u6"))


#: The pair block's steps, written out: step, kind, side.
_STEPS = "(VALUES (0, 'u3', 0), (1, 'u3', 1), (2, 'cx', 0), (3, 'u3', 0), (4, 'u3', 1), (5, 'cx', 1), (6, 'u3', 0), (7, 'u3', 1), (8, 'cx', 0), (9, 'u3', 0), (10, 'u3', 1)) s(step, kind, side)"


@query(
    "WITH placed AS (SELECT layer, q, row_number() OVER (PARTITION BY layer ORDER BY (q * 7919 + layer * 104729 + 31) % 10007, q) - 1 AS at FROM range(10) l(layer), range(8) r(q)), "
    f"g AS (SELECT c.circuit_id, a.layer * 44 + a.at // 2 * 11 + step AS ord, kind, a.q AS q0, CASE WHEN kind = 'cx' THEN b.q ELSE -1 END AS q1 FROM (SELECT unnest(range(count(*))) AS circuit_id FROM nation) c, placed a, placed b, {_STEPS} "
    "WHERE a.layer = b.layer AND a.at // 2 = b.at // 2 AND a.at <> b.at AND a.at % 2 = side) "
    "SELECT circuit_id::BIGINT AS circuit_id, ord::BIGINT AS ord, kind, q0::INT AS q0, q1::INT AS q1, CASE WHEN kind = 'u3' THEN round(1e6 * pi() * ((ord * 37 + circuit_id * 11) % 50 + 1) / 50)::BIGINT ELSE 0 END AS theta_u6, "
    "CASE WHEN kind = 'u3' THEN round(1e6 * 2 * pi() * (ord * 53 % 1009) / 1009)::BIGINT ELSE 0 END AS phi_u6, CASE WHEN kind = 'u3' THEN round(1e6 * 2 * pi() * ((ord * 29 + circuit_id) % 1013) / 1013)::BIGINT ELSE 0 END AS lam_u6 FROM g"
)
def volume_source_gates(spark, sf_dir):
    """A volume circuit of eight qubits and ten layers for each nation, generated in partitions by the data source."""
    spark.dataSource.register(volumes.VolumeCircuits)
    g = spark.read.format("volumecircuits").option("n", 8).option("depth", 10).option("circuits", table(spark, sf_dir, "nation").count()).load()
    at = lambda c, i, other: F.coalesce(F.get(c, F.lit(i)), F.lit(other))
    angle = lambda i: F.round(at("params", i, 0.0) * 1e6).cast("long")
    return g.select("circuit_id", "ord", "kind", at("qubits", 0, -1).alias("q0"), at("qubits", 1, -1).alias("q1"), angle(0).alias("theta_u6"), angle(1).alias("phi_u6"), angle(2).alias("lam_u6"))
