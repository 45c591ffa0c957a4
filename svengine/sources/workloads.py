"""Circuit builders: the random-volume and Fourier families, verification circuits, and circuits read from the given tables."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.gates import Circuit, Gate

#: One entangling pair block: (kind, side) with four pairs of u3 around three alternating cx, fixed values.
PAIR_BLOCK = (("u3", 0), ("u3", 1), ("cx", 0), ("u3", 0), ("u3", 1), ("cx", 1), ("u3", 0), ("u3", 1), ("cx", 0), ("u3", 0), ("u3", 1))
LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate"]


def line_angles(spark: SparkSession, sf_dir: str, rows: int) -> list[tuple[float, float, float]]:
    """theta, phi, lambda of the first `rows` lineitem rows in key order (a top-k: as many rows as the circuit has u3 gates)."""
    t = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select(*LINE_KEY, "l_quantity").orderBy(*LINE_KEY).limit(rows)
    t = t.select(*LINE_KEY, (F.lit(math.pi) * F.col("l_quantity") / 50).alias("a"), (2 * math.pi * ((F.col("l_partkey") * 37) % 1009) / 1009).alias("b"), (2 * math.pi * ((F.col("l_suppkey") * 53 + F.col("l_linenumber") * 11) % 1013) / 1013).alias("c"))
    return [(r["a"], r["b"], r["c"]) for r in t.orderBy(*LINE_KEY).collect()]


def paired(n: int, layer: int) -> list[list[int]]:
    """The qubit pairs of a layer, by a hash."""
    order = sorted(range(n), key=lambda q: ((q * 7919 + layer * 104729 + 31) % 10007, q))
    return [order[2 * i : 2 * i + 2] for i in range(n // 2)]


def quantum_volume(spark: SparkSession, sf_dir: str, n: int, depth: int = 10) -> Circuit:
    """Each layer pairs the qubits by a hash of part keys and gives every pair a block; angles come from lineitem."""
    angles = iter(line_angles(spark, sf_dir, 8 * (n // 2) * depth))
    gates = []
    for layer in range(depth):
        for pair in paired(n, layer):
            for kind, side in PAIR_BLOCK:
                gates.append(Gate("u3", (pair[side],), next(angles)) if kind == "u3" else Gate("cx", (pair[side], pair[1 - side])))
    return Circuit(n, tuple(gates))


def qft(n: int, with_swaps: bool = True) -> Circuit:
    gates = []
    for q in reversed(range(n)):
        gates.append(Gate("h", (q,)))
        gates.extend(Gate("cp", (r, q), (math.pi / 2 ** (q - r),)) for r in reversed(range(q)))
    if with_swaps:
        gates.extend(Gate("swap", (i, n - 1 - i)) for i in range(n // 2))
    return Circuit(n, tuple(gates))


def ghz(n: int) -> Circuit:
    return Circuit(n, (Gate("h", (0,)), *(Gate("cx", (q, q + 1)) for q in range(n - 1))))


def hadamards(n: int) -> Circuit:
    return Circuit(n, tuple(Gate("h", (q,)) for q in range(n)))


def bernstein_vazirani(n: int, secret: int) -> Circuit:
    """n qubits and a helper at position n; the result is |secret> on the n qubits."""
    return Circuit(n + 1, (Gate("x", (n,)), *(Gate("h", (q,)) for q in range(n + 1)), *(Gate("cx", (q, n)) for q in range(n) if secret >> q & 1), *(Gate("h", (q,)) for q in range(n + 1)), Gate("x", (n,))))


def grover_step(n: int, marked: int) -> Circuit:
    """One iteration: flip the marked phase, then reflect about the mean (diagonal and h gates)."""
    size, all_ = 2**n, tuple(range(n))
    flip = Gate("diagonal", all_, (), tuple(-1.0 if i == marked else 1.0 for i in range(size)))
    zero = Gate("diagonal", all_, (), tuple(1.0 if i == 0 else -1.0 for i in range(size)))
    h = hadamards(n).gates
    return Circuit(n, (*h, flip, *h, zero, *h))


def brickwork(n: int, depth: int, angle: float = 0.3) -> Circuit:
    gates = []
    for layer in range(depth):
        gates.extend(Gate("u3", (q,), (angle * (q + 1), angle * layer, 0.1)) for q in range(n))
        gates.extend(Gate("cx", (q, q + 1)) for q in range(layer % 2, n - 1, 2))
    return Circuit(n, tuple(gates))


def w_state(n: int) -> Circuit:
    """Equal amplitudes on the n indices with one bit: the excitation of qubit 0 is handed on in shares, by a controlled rotation (two half ones around cx) and a cx."""
    gates = [Gate("x", (0,))]
    for q in range(n - 1):
        half = math.acos(math.sqrt(1 / (n - q)))
        gates += [Gate("ry", (q + 1,), (half,)), Gate("cx", (q, q + 1)), Gate("ry", (q + 1,), (-half,)), Gate("cx", (q, q + 1)), Gate("cx", (q + 1, q))]
    return Circuit(n, tuple(gates))


def two_halves(n: int) -> Circuit:
    """Chains of cx in the lower half, in the upper half, and in the lower half again: the last ones wait for nothing in the upper half."""
    chain = lambda lo: tuple(Gate("cx", (q, q + 1)) for q in range(lo, lo + n // 2 - 1))
    return Circuit(n, (*chain(0), *chain(n // 2), *chain(0)))


def worked_example() -> Circuit:
    """Five qubits, seven gates; for chunks of three qubits it takes three sections and four swaps."""
    return Circuit(5, (Gate("u3", (0,), (0.3, 0.4, 0.5)), Gate("cx", (0, 1)), Gate("u1", (4,), (0.7,)), Gate("cx", (1, 3)), Gate("u3", (2,), (1.0, 0.2, 0.3)), Gate("cx", (3, 4)), Gate("cx", (2, 0))))


GATES = "circuit_id long, ord long, kind string, qubits array<int>, params array<double>"


def gate_table(c: Circuit, spark: SparkSession, circuit_id: int = 0) -> DataFrame:
    return spark.createDataFrame([(circuit_id, k, g.kind, list(g.qubits), [float(x) for x in g.params]) for k, g in enumerate(c.gates)], GATES)


def circuit_from_df(gates: DataFrame, n: int) -> Circuit:
    """One circuit's gates, ordered; a circuit is a short list on the driver."""
    return Circuit(n, tuple(Gate(r["kind"], tuple(r["qubits"]), tuple(r["params"])) for r in gates.orderBy("ord").collect()))


def circuit_from_rows(df: DataFrame, circuit: str, order: list[str], kind, qubits, params) -> DataFrame:
    """A gate from each row: rows of a circuit are numbered by `order`. A circuit is small (at most some hundred rows)."""
    w = Window.partitionBy(circuit).orderBy(*order)
    return df.select(F.col(circuit).cast("long").alias("circuit_id"), (F.row_number().over(w) - 1).cast("long").alias("ord"), kind.alias("kind"), qubits.alias("qubits"), params.alias("params"))


def events_gates(spark: SparkSession, sf_dir: str, n: int = 6) -> DataFrame:
    """A circuit for each user: view h, click u3, purchase cx, error u1, signup swap."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    q0 = (F.col("k") % n).cast("int")
    q1 = ((F.col("k") + 1 + F.col("user_id") % (n - 1)) % n).cast("int")
    theta, phi = F.col("value") / 500 * math.pi, F.col("k") * math.pi / 50
    t = F.col("event_type")
    kind = F.when(t == "view", "h").when(t == "click", "u3").when(t == "purchase", "cx").when(t == "error", "u1").otherwise("swap")
    qubits = F.when(t.isin("purchase", "signup"), F.array(q0, q1)).otherwise(F.array(q0))
    params = F.when(t == "click", F.array(theta, phi, F.lit(0.0))).when(t == "error", F.array(theta)).otherwise(F.array().cast("array<double>"))
    return circuit_from_rows(e, "user_id", ["event_id"], kind, qubits, params)


def orders_gates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A circuit of four qubits for each order: returned lines cx, accepted u3, others u1."""
    l = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    q0 = (F.col("l_partkey") % 4).cast("int")
    q1 = ((q0 + 1 + F.col("l_suppkey") % 3) % 4).cast("int")
    theta, phi, lam = math.pi * F.col("l_discount") * 10, math.pi * F.col("l_tax") * 10, math.pi * F.col("l_quantity") / 50
    f = F.col("l_returnflag")
    kind = F.when(f == "R", "cx").when(f == "A", "u3").otherwise("u1")
    qubits = F.when(f == "R", F.array(q0, q1)).otherwise(F.array(q0))
    params = F.when(f == "R", F.array().cast("array<double>")).when(f == "A", F.array(theta, phi, lam)).otherwise(F.array(lam))
    return circuit_from_rows(l, "l_orderkey", LINE_KEY, kind, qubits, params)


def conversation_gates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A circuit of three qubits for each conversation: system h, user u3, assistant cx; angles from the text's length."""
    c = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    q0 = (F.col("turn") % 3).cast("int")
    angle = F.radians((F.coalesce(F.char_length("text"), F.lit(0)) % 360).cast("double"))
    kind = F.when(F.col("role") == "system", "h").when(F.col("role") == "user", "u3").otherwise("cx")
    qubits = F.when(F.col("role").isin("system", "user"), F.array(q0)).otherwise(F.array(q0, ((q0 + 1) % 3).cast("int")))
    params = F.when(F.col("role") == "user", F.array(angle, F.lit(0.0), F.lit(0.0))).otherwise(F.array().cast("array<double>"))
    return circuit_from_rows(c, "conv_id", ["turn"], kind, qubits, params)
