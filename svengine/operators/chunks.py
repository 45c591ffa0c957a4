"""The packed executors: sections on every chunk alone, remaps as one shuffle, and the per-gate baselines with their exchanges."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import permuted
from ..functions.gates import Circuit, Gate, apply_dense, diagonal_of
from ..functions.shared import complete, drop, written
from ..plans.transpile import Plan, Section, Step
from .states import CHUNK, WIDTH

PART = "chunk long, slot long, amp binary"
#: Sections (or exchanges) after which a register is written to the shared folder, so that plans and lineage stay short.
CUT = 8
STRATEGIES = ("pair", "copy", "slice", "coresident")


@dataclass
class Register:
    """Packed chunks of 2**nc amplitudes; layout: position of each qubit."""

    df: DataFrame
    n: int
    nc: int
    layout: tuple[int, ...] = ()
    precision: str = "double"
    #: Whether the state is the same in every layout (the zero register), so that a start layout costs nothing.
    symmetric: bool = False

    def __post_init__(self):
        self.layout = self.layout or tuple(range(self.n))


def _apply_in_chunk(a: np.ndarray, g: Gate, at: tuple[int, ...], nc: int, chunk: int) -> np.ndarray:
    """A gate on one chunk. Diagonal entries and controls at positions beyond the chunk are read off the chunk's number."""
    high = [i for i, p in enumerate(at) if p >= nc]
    if not high:
        return apply_dense(a, g, at)
    if g.is_diagonal:
        d = diagonal_of(g).reshape((2,) * len(at))  # axis j is qubit len(at) - 1 - j
        pick = tuple(((chunk >> (at[i] - nc)) & 1) if i in high else slice(None) for i in reversed(range(len(at))))
        low = [i for i in range(len(at)) if i not in high]
        d = d[pick]
        if not low:
            a *= d
            return a
        return apply_dense(a, Gate("diagonal", tuple(range(len(low))), (), tuple(np.ravel(d))), tuple(at[i] for i in low))
    if not g.controls or len(at) - 1 in high:
        raise ValueError(f"{g.kind} on positions {at} doesn't fit into chunks of {nc} qubits")
    if all((chunk >> (at[i] - nc)) & 1 for i in high):
        rest = [i for i in range(len(at)) if i not in high]
        kind = {1: "x", 2: "cx", 3: "ccx"}[len(rest)]
        return apply_dense(a, Gate(kind, tuple(range(len(rest)))), tuple(at[i] for i in rest))
    return a


def run_block(df: DataFrame, steps: tuple[Step, ...], nc: int, precision: str = "double") -> DataFrame:
    """All gates of a section in one pass over each chunk: a narrow map."""
    dtype, _ = WIDTH[precision]

    def block(batches):
        for b in batches:
            for c, amp in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                a = np.frombuffer(amp.as_buffer(), dtype).copy()
                for s in steps:
                    a = _apply_in_chunk(a, s.gate, s.at, nc, c)
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.int64()), pa.array([a.astype(dtype, copy=False).tobytes()], pa.binary())], ["chunk", "amp"])

    return df.mapInArrow(block, CHUNK)


def run_remap(df: DataFrame, perm: tuple[int, ...], n: int, nc: int, precision: str = "double") -> DataFrame:
    """Move position k to perm[k]. Positions that stay on their side of nc cost no exchange: chunk numbers change by projection,
    offsets inside the chunk. With s positions going out each chunk is cut into 2^s slices and one shuffle deals them."""
    dtype, _ = WIDTH[precision]
    out = sorted(p for p in range(nc) if perm[p] >= nc)  # leave the chunk
    stay = sorted((p for p in range(nc) if perm[p] < nc), key=lambda p: perm[p])
    come = sorted((p for p in range(nc, n) if perm[p] < nc), key=lambda p: perm[p])
    keep = [p for p in range(nc, n) if perm[p] >= nc]
    high = [0] * (n - nc)  # where each kept chunk bit goes; the others are cleared first
    for p in keep:
        high[p - nc] = perm[p] - nc
    if not out:
        number = permuted("chunk", high) if n > nc else F.col("chunk")
        if all(perm[p] == p for p in range(nc)):
            return df.select(number.alias("chunk"), "amp")
    axis = lambda p: nc - 1 - p  # noqa: E731  of position p in a chunk's tensor

    def cut(batches):
        for b in batches:
            for c, amp in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                t = np.frombuffer(amp.as_buffer(), dtype).reshape((2,) * nc)
                t = np.transpose(t, [axis(p) for p in reversed(out)] + [axis(p) for p in reversed(stay)]).reshape(2 ** len(out), -1)
                base = sum(((c >> (p - nc)) & 1) << (perm[p] - nc) for p in keep)
                slot = sum(((c >> (p - nc)) & 1) << i for i, p in enumerate(come))
                to = [base + sum(((v >> i) & 1) << (perm[p] - nc) for i, p in enumerate(out)) for v in range(len(t))]
                yield pa.RecordBatch.from_arrays([pa.array(to, pa.int64()), pa.array([slot] * len(t), pa.int64()), pa.array([x.tobytes() for x in t], pa.binary())], ["chunk", "slot", "amp"])

    def joined(slots, parts):
        t = np.stack([np.frombuffer(p, dtype) for _, p in sorted(zip(slots, parts, strict=True))]).reshape((2,) * nc)
        # axes: incoming positions from the highest slot bit down, then those that stayed, highest new position first
        order = [perm[p] for p in reversed(come)] + [perm[p] for p in reversed(stay)]
        return np.transpose(t, [order.index(p) for p in reversed(range(nc))]).reshape(-1)

    def gather(key, t):
        a = joined(t["slot"].to_pylist(), t["amp"].to_pylist())
        return pa.table({"chunk": pa.array([key[0].as_py()], pa.int64()), "amp": pa.array([a.tobytes()], pa.binary())})

    if not out:
        def inside(batches):
            for b in cut(batches):
                parts = [np.ascontiguousarray(joined([0], [x])).tobytes() for x in b.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(parts, pa.binary())], ["chunk", "amp"])

        return df.mapInArrow(inside, CHUNK)
    return df.mapInArrow(cut, PART).groupBy("chunk").applyInArrow(gather, CHUNK)


def _pair(g: Gate, at, nc: int, chunks: dict[int, np.ndarray]) -> dict[int, np.ndarray]:
    """A gate on the chunks of one group, which differ in the bits of its positions beyond nc."""
    high = sorted(p for p in at if p >= nc)
    ids = sorted(chunks)
    whole = np.concatenate([chunks[c] for c in ids])  # position nc + i is the i-th of `high`
    where = tuple(nc + high.index(p) if p >= nc else p for p in at)
    whole = apply_dense(whole, g, where)
    return dict(zip(ids, np.split(whole, len(ids)), strict=True))


def apply_global(df: DataFrame, g: Gate, at: tuple[int, ...], n: int, nc: int, strategy: str = "pair", precision: str = "double", slice_bits: int = 1, space_bits: int = 1) -> DataFrame:
    """A gate that mixes chunks, by exchange.

    pair: the chunks of a group meet in one task. copy: each chunk is sent to every member of its group, and each computes its own
    part (the memory of two registers). slice: as pair, on slices of chunks. coresident: groups are made by space, so that a register
    that is partitioned by space needs no exchange; a gate on the space's own bits is done as pair.
    """
    dtype, _ = WIDTH[precision]
    high = [p - nc for p in at if p >= nc]
    mask = sum(1 << p for p in high)
    group = F.col("chunk").bitwiseAND(F.lit(~mask))
    put = lambda got: pa.table({"chunk": pa.array(list(got), pa.int64()), "amp": pa.array([a.tobytes() for a in got.values()], pa.binary())})
    read = lambda t, k="amp": {c: np.frombuffer(a, dtype) for c, a in zip(t["chunk"].to_pylist(), t[k].to_pylist(), strict=True)}

    if strategy == "copy":
        flips = F.array(*[F.col("chunk").bitwiseXOR(F.lit(sum(1 << p for i, p in enumerate(high) if v >> i & 1))) for v in range(2 ** len(high))])

        def own(key, t):
            mine = key[0].as_py()
            return put({mine: _pair(g, at, nc, read(t))[mine]})

        return df.withColumn("goal", F.explode(flips)).groupBy("goal").applyInArrow(own, CHUNK)
    if strategy == "slice":
        low = sorted(p for p in at if p < nc)
        free = [p for p in reversed(range(nc)) if p not in low][:slice_bits]
        axes = [nc - 1 - p for p in free]
        rest = [a for a in range(nc) if a not in axes]
        left = nc - len(free)
        order = [p for p in reversed(range(nc)) if p not in free]
        inner = tuple(left - 1 - order.index(p) if p < nc else p - len(free) for p in at)

        def cut(batches):
            for b in batches:
                for c, amp in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                    t = np.transpose(np.frombuffer(amp.as_buffer(), dtype).reshape((2,) * nc), axes + rest).reshape(2 ** len(free), -1)
                    yield pa.RecordBatch.from_arrays([pa.array([c] * len(t), pa.int64()), pa.array(range(len(t)), pa.int64()), pa.array([x.tobytes() for x in t], pa.binary())], ["chunk", "slot", "amp"])

        def work(key, t):
            got = _pair(g, inner, left, read(t))
            return pa.table({"chunk": pa.array(list(got), pa.int64()), "slot": pa.array([key[1].as_py()] * len(got), pa.int64()), "amp": pa.array([a.tobytes() for a in got.values()], pa.binary())})

        def gather(key, t):
            x = np.stack([np.frombuffer(a, dtype) for _, a in sorted(zip(t["slot"].to_pylist(), t["amp"].to_pylist(), strict=True))]).reshape((2,) * nc)
            return put({key[0].as_py(): np.transpose(x, np.argsort(axes + rest)).reshape(-1)})

        sliced = df.mapInArrow(cut, PART).groupBy(group.alias("group"), "slot").applyInArrow(work, PART)
        return sliced.groupBy("chunk").applyInArrow(gather, CHUNK)

    def meet(key, t):
        return put(_pair(g, at, nc, read(t)))

    if strategy == "coresident" and max(high) < n - nc - space_bits:
        return df.withColumn("space", F.shiftright("chunk", n - nc - space_bits)).repartition("space").groupBy("space", group.alias("group")).applyInArrow(meet, CHUNK)
    if strategy not in ("pair", "coresident"):
        raise ValueError(f"unknown strategy {strategy}")
    return df.groupBy(group.alias("group")).applyInArrow(meet, CHUNK)


def run_section(r: Register, s: Section, strategy: str = "pair") -> Register:
    if s.op == "remap":
        return Register(run_remap(r.df, s.perm, r.n, r.nc, r.precision), r.n, r.nc, s.after, r.precision)
    if s.op == "block":
        return Register(run_block(r.df, s.steps, r.nc, r.precision), r.n, r.nc, r.layout, r.precision)
    x = s.steps[0]
    return Register(apply_global(r.df, x.gate, x.at, r.n, r.nc, strategy, r.precision), r.n, r.nc, r.layout, r.precision)


def run_blocked(r: Register, p: Plan, cut: int = CUT, folder: str | None = None, space_bits: int = 0) -> Register:
    """The plan, section by section. Every `cut` sections the register is written to the shared folder; the last two generations are kept.

    folder: where generations go, by section. A run that finds complete ones there goes on after the latest. space_bits: generations are
    partitioned by space, the chunk number's top bits.
    """
    spark, kept, first = r.df.sparkSession, [], 0
    at = lambda k: f"{folder.rstrip('/')}/after-{k:06d}"
    done = [k for k in range(len(p.sections)) if folder and complete(spark, at(k))]
    if done:
        df = spark.read.parquet(at(done[-1])).select("chunk", "amp")
        r, first = Register(df, r.n, r.nc, p.sections[done[-1]].after, r.precision), done[-1] + 1
    elif p.start != r.layout:
        df = r.df if r.symmetric else run_remap(r.df, p.start, r.n, r.nc, r.precision)
        r = Register(df, r.n, r.nc, p.start, r.precision)
    for k in range(first, len(p.sections)):
        r = run_section(r, p.sections[k])
        if k % cut == cut - 1 and (folder or k + 1 < len(p.sections)):
            df = r.df.withColumn("space", F.shiftright("chunk", r.n - r.nc - space_bits)) if space_bits else r.df
            df = written(df, path=at(k) if folder else None, by="space" if space_bits else None)
            kept.append(df)
            r = Register(df.select("chunk", "amp"), r.n, r.nc, r.layout, r.precision)
            if len(kept) > 2:
                drop(kept.pop(0))
    return Register(r.df, r.n, r.nc, p.end, r.precision)


def run_baseline(r: Register, c: Circuit, strategy: str = "pair", cut: int = CUT) -> Register:
    """Gate by gate without rewriting: an exchange whenever a gate mixes chunks. Gates in between run in one pass."""
    df, run, exchanges, kept = r.df, [], 0, []
    for k, g in enumerate(c.gates):
        if max([*g.written, -1]) < r.nc:
            run.append(Step(k, g, g.qubits))
            continue
        if run:
            df, run = run_block(df, tuple(run), r.nc, r.precision), []
        df = apply_global(df, g, g.qubits, r.n, r.nc, strategy, r.precision)
        exchanges += 1
        if exchanges % cut == 0:
            df = written(df)
            kept.append(df)
            if len(kept) > 2:
                drop(kept.pop(0))
    if run:
        df = run_block(df, tuple(run), r.nc, r.precision)
    return Register(df, r.n, r.nc, r.layout, r.precision)


def rows_of(r: Register) -> DataFrame:
    """Amplitudes under logical indices; a layout that wasn't restored is undone by a projection."""
    from .states import to_rows

    df = to_rows(r.df, r.nc, r.precision)
    if r.layout != tuple(range(r.n)):
        back = [0] * r.n
        for q, p in enumerate(r.layout):
            back[p] = q
        df = df.withColumn("idx", permuted("idx", back))
    return df
