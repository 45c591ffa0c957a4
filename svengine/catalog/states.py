"""Registers and encoders."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.bits import u6
from ..operators import states as S
from . import oracle as O
from . import query


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def amps(df: DataFrame, *keys: str) -> DataFrame:
    return df.select(*(keys or ("idx",)), u6("re").alias("re_u6"), u6("im").alias("im_u6"))


def encoded(spark, sf_dir, name, key, value) -> tuple[DataFrame, int]:
    t = table(spark, sf_dir, name)
    n = S.qubits_for(t.count())
    return S.amplitude_encode(t, key, value, n), n


orders = lambda s, d: encoded(s, d, "orders", "o_orderkey", "o_totalprice")
customer = lambda s, d: encoded(s, d, "customer", "c_custkey", "c_acctbal")
part = lambda s, d: encoded(s, d, "part", "p_partkey", "p_retailprice")
supplier = lambda s, d: encoded(s, d, "supplier", "s_suppkey", "s_acctbal")
nation = lambda s, d: encoded(s, d, "nation", "n_nationkey", F.col("n_nationkey") + 1)
region = lambda s, d: encoded(s, d, "region", "r_regionkey", F.col("r_regionkey") + 1)


def line_registers(spark, sf_dir) -> DataFrame:
    """l_suppkey, n: the qubits of the register of each supplier's lines."""
    rows = table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))
    return rows.select("l_suppkey", F.length(F.bin(F.col("n") - 1)).cast("long").alias("n"))


for _name, _get, _sql in (("orders", orders, O.ORDERS), ("customer", customer, O.CUSTOMER), ("part", part, O.PART), ("supplier", supplier, O.SUPPLIER), ("nation", nation, O.NATION)):
    query(O.amps(_sql), f"encode_{_name}")(lambda s, d, get=_get: amps(get(s, d)[0]))

_RANK = f"(SELECT row_number() OVER (ORDER BY {O.LINE_ORDER}) - 1 AS idx, * FROM lineitem)"


@query(O.amps(O.encoded(_RANK, "idx", "l_extendedprice")))
def encode_lineitem(spark, sf_dir):
    t = S.dense_index(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate"), O.LINE_ORDER.split(", "))
    return amps(S.amplitude_encode(t, "idx", "l_extendedprice", S.qubits_for(t.count()), checked=False))


@query(f"SELECT idx, l_orderkey, l_linenumber, l_partkey FROM {_RANK}")
def rank_lineitem(spark, sf_dir):
    t = table(spark, sf_dir, "lineitem").select(*O.LINE_ORDER.split(", "))
    return S.dense_index(t, O.LINE_ORDER.split(", ")).select("idx", "l_orderkey", "l_linenumber", "l_partkey")


@query(O.amps(O.basis(6)))
def zero_state_rows(spark, sf_dir):
    return amps(S.zero_state(spark, 6))


@query(O.amps(O.basis(8)))
def zero_state_chunks(spark, sf_dir):
    return amps(S.to_rows(S.zero_state(spark, 8, 5, "chunks"), 5))


@query(f"SELECT i AS idx, CASE WHEN i = j THEN 1000000 ELSE 0 END::BIGINT AS re_u6, 0::BIGINT AS im_u6 FROM (SELECT unnest(range({O.size_of('orders')})) AS i), (SELECT o_orderkey AS j FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 1)")
def basis_state(spark, sf_dir):
    """The basis register of the dearest order, among as many qubits as the orders need."""
    t = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    return amps(S.basis_state(spark, S.qubits_for(t.count()), t.orderBy(F.desc("o_totalprice"), "o_orderkey").first()[0]))


@query(O.amps("(SELECT i AS idx, sqrt(1/1024.0) AS re, 0.0 AS im FROM range(1024) t(i))"))
def uniform_state(spark, sf_dir):
    return amps(S.uniform_state(spark, 10))


@query(O.amps(f"(SELECT a.idx*32 + b.idx AS idx, a.re*b.re AS re, 0.0 AS im FROM {O.REGION} a, {O.NATION} b)"))
def tensor_region_nation(spark, sf_dir):
    return amps(S.tensor(region(spark, sf_dir)[0], nation(spark, sf_dir)[0], 5))


@query(f"SELECT idx >> 6 AS chunk, idx & 63 AS off, {O.u6('re')} AS re_u6 FROM {O.ORDERS}")
def chunk_split(spark, sf_dir):
    return S.with_chunk(orders(spark, sf_dir)[0], 6).select("chunk", "off", u6("re").alias("re_u6"))


@query(O.MISMATCHES)
def chunk_roundtrip(spark, sf_dir):
    a = orders(spark, sf_dir)[0]
    return mismatches(a, S.to_rows(S.to_chunks(a, 6), 6))


def mismatches(a: DataFrame, b: DataFrame, tolerance: float = 1e-9) -> DataFrame:
    """Indices that only one side has or whose amplitudes differ."""
    y = b.select("idx", F.col("re").alias("r"), F.col("im").alias("i"))
    j = a.join(y, "idx", "full")
    far = (F.abs(F.col("re") - F.col("r")) > tolerance) | (F.abs(F.col("im") - F.col("i")) > tolerance) | F.col("re").isNull() | F.col("r").isNull()
    return j.agg(F.coalesce(F.sum(F.when(far, 1).otherwise(0)), F.lit(0)).cast("long").alias("mismatches"))


@query("SELECT i AS chunk, i * 64 AS first_idx FROM range(16) t(i)")
def chunk_bases(spark, sf_dir):
    return spark.range(16).select(F.col("id").alias("chunk"), S.chunk_base("id", 6).alias("first_idx"))


@query("SELECT i AS chunk, i * 4 // 32 AS space FROM range(32) t(i)")
def chunk_to_space(spark, sf_dir):
    return spark.range(32).select(F.col("id").alias("chunk"), S.assign_contiguous("id", 32, 4).alias("space"))


@query(f"SELECT idx >> 3 AS chunk, (idx >> 3) * 8 AS first_idx, {O.u6('sum(re*re)')} AS mass_u6 FROM {O.NATION} GROUP BY ALL")
def four_space_split(spark, sf_dir):
    a = S.with_chunk(nation(spark, sf_dir)[0], 3)
    return a.groupBy("chunk").agg(u6(F.sum(F.col("re") * F.col("re"))).alias("mass_u6")).withColumn("first_idx", S.chunk_base("chunk", 3))


@query("SELECT CAST(n_nationkey AS BIGINT) AS circuit_id, CAST(n_nationkey % 32 AS BIGINT) AS idx, 1000000::BIGINT AS re_u6 FROM nation")
def basis_encode_nation(spark, sf_dir):
    return S.basis_encode(table(spark, sf_dir, "nation"), "n_nationkey", 5).select("circuit_id", "idx", u6("re").alias("re_u6"))


_AE = """(SELECT p_partkey AS circuit_id, i AS idx, (CASE WHEN i & 1 = 1 THEN sin(p_size/50.0) ELSE cos(p_size/50.0) END) * (CASE WHEN (i >> 1) & 1 = 1 THEN sin(p_retailprice/2000) ELSE cos(p_retailprice/2000) END) AS re FROM part, range(4) t(i))"""


@query(f"SELECT circuit_id, idx, {O.u6('re')} AS re_u6 FROM {_AE}")
def angle_encode_part(spark, sf_dir):
    angles = [F.col("p_size") / 25.0, F.col("p_retailprice") / 1000.0]
    return S.angle_encode(table(spark, sf_dir, "part"), "p_partkey", angles).select("circuit_id", "idx", u6("re").alias("re_u6"))


@query(f"SELECT i AS idx, o_orderkey IS NULL AS padded FROM (SELECT unnest(range({O.size_of('orders')})) AS i) LEFT JOIN orders ON o_orderkey = i")
def outer_pad_orders(spark, sf_dir):
    t = table(spark, sf_dir, "orders").select("o_orderkey")
    all_ = spark.range(2 ** S.qubits_for(t.count())).withColumnRenamed("id", "idx")
    return all_.join(t, F.col("idx") == F.col("o_orderkey"), "left").select("idx", F.col("o_orderkey").isNull().alias("padded"))


@query("SELECT l_orderkey, sum(l_quantity) AS quantity FROM lineitem WHERE l_extendedprice > 1000 AND l_returnflag = 'R' GROUP BY l_orderkey")
def scan_prune_lineitem(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where("l_extendedprice > 1000 and l_returnflag = 'R'").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("quantity"))
