"""Packing into fixed-length sequences by cutting-stock column generation.

A document (its ids and an end id) is cut into whole sequences and a rest. Lengths fall into classes of WIDTH tokens, rounded
up, so the histogram has at most length / WIDTH rows at any input size. Over it a linear program minimises the number of
sequences; columns are patterns (so many pieces of each class in one sequence), and a knapsack by dynamic programming prices them:
a pattern enters while its value at the dual prices exceeds 1. Multiplicities are rounded down, and the program is solved again
for what is left of each class (a bounded number of pieces), until nothing is. Pieces are ranked in their class, and the rank alone gives pattern, sequence and
place, so assigning is a join with the pattern table, and offsets are sums within sequences.

Null text: empty, one piece that holds the end id. Rows with the same doc_id, and rows without one, are packed as separate documents. An empty table gives
no rows; other columns are ignored; a text of any length is cut into as many pieces as it needs.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common, tokens

LENGTH, WIDTH, END = 2048, 8, 1
#: Columns that may enter before the program is taken as it is, and the gap to the bound by prices at which it is good enough; any
#: basis gives a complete packing.
COLUMNS, GAP = 3000, 5e-4
#: Share of the fractional sequences that is rounded up before the program is solved again.
DIVE = 0.25

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def pieces(docs: DataFrame, length: int = LENGTH, end: int = END, path: str = tokens.DEFAULT) -> DataFrame:
    """One row for each piece of each document: cuts at multiples of length."""
    end_id = np.array([end], "<u4").tobytes()

    def run(batches):
        c = tokens.codec(path)
        for b in batches:
            cols = [[], [], [], [], []]
            for doc, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = c.encode(t.as_py() or "") + end_id
                n = len(ids) // 4
                for at in range(0, n, length):
                    part = ids[4 * at : 4 * (at + length)]
                    for col, v in zip(cols, (doc, at, len(part) // 4, zlib.crc32(part), n), strict=True):
                        col.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in cols], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECES)


def best_pattern(prices: np.ndarray, sizes: np.ndarray, room: int) -> tuple[float, np.ndarray]:
    """Knapsack with any number of each size (ascending): the most valuable pattern and its value."""
    value, taken = np.zeros(room + 1), np.full(room + 1, -1)
    fits = np.searchsorted(sizes, np.arange(room + 1), side="right").tolist()
    for w in range(1, room + 1):
        value[w] = value[w - 1]
        if fits[w]:
            gain = value[w - sizes[: fits[w]]] + prices[: fits[w]]
            k = int(gain.argmax())
            if gain[k] > value[w] + 1e-12:
                value[w], taken[w] = gain[k], k
    out, w = np.zeros(len(sizes), np.int64), room
    while w > 0:
        if taken[w] < 0:
            w -= 1
        else:
            out[taken[w]] += 1
            w -= sizes[taken[w]]
    return float(value[room]), out


def _inverse(a: np.ndarray) -> np.ndarray:
    """Gauss-Jordan with row pivots, in this thread only: a linear-algebra library's own threads can hang in a driver process."""
    n = len(a)
    w = np.hstack([a, np.eye(n)])
    for k in range(n):
        p = k + int(np.abs(w[k:, k]).argmax())
        w[[k, p]] = w[[p, k]]
        w[k] /= w[k, k]
        w -= np.where(np.arange(n) == k, 0.0, w[:, k])[:, None] * w[k]
    return w[:, n:]


def _start(sizes: np.ndarray, left: np.ndarray, room: int) -> tuple[np.ndarray, np.ndarray]:
    """A first basis: patterns of the largest sizes that fit, each used, in fractions, until one of its sizes is used up.

    The pattern that uses a size up is that size's column. Later patterns don't hold the size, so the basis is triangular in this order.
    """
    rest, open_ = left.astype(float), np.ones(len(sizes), bool)
    basis, x = np.zeros((len(sizes), len(sizes))), np.zeros(len(sizes))
    while open_.any():
        pattern, free = np.zeros(len(sizes)), room
        for k in np.flatnonzero(open_)[::-1].tolist():
            pattern[k] = min(int(np.ceil(rest[k] - 1e-9)), free // int(sizes[k]))
            free -= int(pattern[k]) * int(sizes[k])
        used = np.flatnonzero(pattern)
        times = rest[used] / pattern[used]
        k = int(used[times.argmin()])
        basis[:, k], x[k] = pattern, max(times.min(), 0.0)
        rest = np.maximum(rest - x[k] * pattern, 0)
        rest[k], open_[k] = 0, False
        pattern[:] = 0
        for z in np.flatnonzero(open_ & (rest <= 1e-9)).tolist():  # used up at the same time: a column of its own that isn't used
            basis[z, z], open_[z], rest[z] = 1, False, 0
    return basis, x


def _program(sizes: np.ndarray, left: np.ndarray, room: int, columns: int) -> tuple[np.ndarray, np.ndarray]:
    """A basis of patterns (columns) and how often each is used, by column generation; every demand is covered, in fractions."""
    basis, x = _start(sizes, left, room)
    inverse = _inverse(basis)
    bound = float((sizes * left).sum()) / room
    for k in range(columns):
        prices = inverse.sum(0)  # every column costs one sequence
        value, pattern = best_pattern(prices, sizes, room)
        bound = max(bound, float((prices * left).sum()) / value)
        if value <= 1 + 1e-7 or x.sum() <= max(bound * (1 + GAP), np.ceil(bound - 1e-6) - 0.5):
            break
        used = np.flatnonzero(pattern)
        step = (inverse[:, used] * pattern[used]).sum(1)  # small sums: threads of a linear-algebra library would only wait for each other
        up = step > 1e-9
        ratio = np.full(len(sizes), np.inf)
        ratio[up] = x[up] / step[up]
        out = int(ratio.argmin())
        basis[:, out] = pattern
        x = np.maximum(x - ratio[out] * step, 0)
        x[out] = ratio[out]
        row = inverse[out] / step[out]
        inverse -= step[:, None] * row
        inverse[out] = row
        if k % 500 == 499:  # against rounding
            inverse = _inverse(basis)
            x = np.maximum((inverse * left).sum(1), 0)
    return np.rint(basis).astype(np.int64), x


def _topped_up(pattern: np.ndarray, left: np.ndarray, sizes: np.ndarray, room: int) -> np.ndarray:
    """The pattern without pieces that aren't left, and with the largest ones that still fit."""
    pattern = np.minimum(pattern, left)
    free = room - int((pattern * sizes).sum())
    for k in range(len(sizes) - 1, -1, -1):
        more = min(int(left[k] - pattern[k]), free // int(sizes[k]))
        pattern[k] += more
        free -= more * int(sizes[k])
    return pattern


def stock_patterns(demand: dict[int, int], room: int, columns: int = COLUMNS) -> list[tuple[dict[int, int], int]]:
    """Patterns (pieces by size) and multiplicities that cover demand (pieces by size) exactly, in few sequences.

    The program is solved, the whole parts of its multiplicities are taken, and the program is solved again for what is left. Once no
    multiplicity reaches one, those nearest to one are taken once, as far as their pieces last, for a share of DIVE of the sequences.
    """
    sizes = np.array(sorted(s for s, n in demand.items() if n > 0), np.int64)
    left = np.array([demand[int(s)] for s in sizes], np.int64)
    found = []

    def take(pattern, most):
        used = pattern > 0
        times = min(most, int((left[used] // pattern[used]).min()))
        if times > 0:
            found.append(({int(s): int(n) for s, n in zip(sizes, pattern, strict=True) if n}, times))
            left[:] -= times * pattern
        return max(times, 0)

    while len(sizes):
        basis, x = _program(sizes, left, room, columns)
        order = np.argsort(-x, kind="stable").tolist()
        whole = sum(take(_topped_up(basis[:, k], left, sizes, room), int(x[k] + 1e-9)) for k in order if x[k] >= 1 - 1e-9)
        if not whole:
            goal = max(1, int(x.sum() * DIVE))
            for k in sorted(order, key=lambda k: -(x[k] % 1)):
                if goal > 0 and (basis[:, k] <= left).all():
                    goal -= take(_topped_up(basis[:, k], left, sizes, room), 1)
            if goal == max(1, int(x.sum() * DIVE)):
                take(_topped_up(basis[:, order[0]], left, sizes, room), 1)
        stay = left > 0
        sizes, left = sizes[stay], left[stay]
    return found


def slots(patterns: list[tuple[dict[int, int], int]]) -> list[tuple[int, int, int, int, int]]:
    """(class, first rank, rank after the last, pieces in a sequence, first sequence) of each pattern's share of each class."""
    rank, sequence, out = {}, 0, []
    for pattern, times in patterns:
        for size, n in pattern.items():
            lo = rank.get(size, 0)
            rank[size] = lo + n * times
            out.append((size, lo, lo + n * times, n, sequence))
        sequence += times
    return out


def pack(docs: DataFrame, length: int = LENGTH, end: int = END, width: int = WIDTH, path: str = tokens.DEFAULT) -> DataFrame:
    """The pieces with sequence_id and offset."""
    spark = docs.sparkSession
    rows = common.written(pieces(docs, length, end, path).withColumn("class", F.ceil(F.col("length") / width).cast("int")), "pack-pieces")
    demand = {r["class"]: r["count"] for r in rows.groupBy("class").count().collect()}
    # a few rows for each of at most length / width patterns
    plan = spark.createDataFrame(slots(stock_patterns(demand, length // width)), "class int, lo long, hi long, each long, base long")
    at = common.ranked(rows, ["class"], ["doc_id", "start", "ids_crc32"])
    placed = at.join(F.broadcast(plan), "class").where("rank >= lo and rank < hi").withColumn("sequence_id", F.expr("base + (rank - lo) div each"))
    before = Window.partitionBy("sequence_id").orderBy(F.desc("class"), "rank").rowsBetween(Window.unboundedPreceding, -1)
    return placed.withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0)).cast("long")).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(common.table(spark, sf_dir, "documents"))
