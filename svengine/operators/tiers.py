"""Registers over two tiers: chunks with low numbers stay with the executors, the others lie in the slow tier, a Parquet table of their own in the shared folder.

run_tiered() fetches the slow chunks for a section, runs all of it, and writes them back; fast chunks flow on to the next exchange without being
written. run_in_place() is what it is compared with: no rewriting, and every gate is computed on the slow chunks where they lie, a pass over the slow tier each.
An exchange deals all chunks and writes both tiers, which cuts lineage: a lost executor costs the work since the last exchange.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.gates import Circuit
from ..functions.shared import drop, written
from ..plans.transpile import Plan, Step
from .chunks import Register, apply_global, run_block, run_remap, run_section


@dataclass
class Tiers:
    """A register's two parts and the slow chunks that were fetched and written, by occasion."""

    table: DataFrame
    fast: DataFrame
    slow: DataFrame
    fast_chunks: int
    nc: int
    precision: str
    #: Steps that the fast part hasn't run yet: one pass before the next exchange takes them all.
    waiting: tuple[Step, ...] = ()
    moved: dict[str, int] = field(default_factory=dict)

    @classmethod
    def split(cls, df: DataFrame, fast_chunks: int, nc: int, precision: str) -> Tiers:
        t = written(df.withColumn("slow", F.col("chunk") >= fast_chunks), "tiers", by="slow")
        return cls(t, t.where("not slow").select("chunk", "amp"), t.where("slow").select("chunk", "amp"), fast_chunks, nc, precision)

    def whole(self) -> DataFrame:
        return run_block(self.fast, self.waiting, self.nc, self.precision).unionByName(self.slow)

    def close(self) -> None:
        """Delete the tables, once nothing reads them any more."""
        drop(self.table)
        if hasattr(self.slow, "shared_path"):
            drop(self.slow)

    def _count(self, occasion: str, *parts: DataFrame) -> None:
        self.moved[occasion] = self.moved.get(occasion, 0) + sum(p.count() for p in parts)  # from the files' footers

    def run(self, steps: tuple[Step, ...], occasion: str) -> None:
        """Steps inside chunks: later on the fast chunks, now on the slow ones, with a fetch and a write."""
        old = self.slow
        self.waiting += steps
        self.slow = written(run_block(old, steps, self.nc, self.precision), "slow-tier")
        self._count(occasion, old, self.slow)
        if hasattr(old, "shared_path"):
            drop(old)

    def exchanged(self, df: DataFrame, occasion: str) -> Tiers:
        """df, all chunks after an exchange, split again."""
        out = Tiers.split(df, self.fast_chunks, self.nc, self.precision)
        out.moved = self.moved
        out._count(occasion, self.slow, out.slow)
        self.close()
        return out


def run_tiered(r: Register, p: Plan, fast_chunks: int) -> tuple[Register, dict[str, int]]:
    """The plan with the first fast_chunks chunks in the fast tier. Also the slow chunks that were moved: by 'sections' and by 'exchanges'."""
    df = r.df if r.symmetric or p.start == r.layout else run_remap(r.df, p.start, r.n, r.nc, r.precision)
    t, layout = Tiers.split(df, fast_chunks, r.nc, r.precision), p.start
    for s in p.sections:
        if s.op == "block":
            t.run(s.steps, "sections")
        else:
            out = run_section(Register(t.whole(), r.n, r.nc, layout, r.precision), s)
            t, layout = t.exchanged(out.df, "exchanges"), out.layout
    return Register(t.whole(), r.n, r.nc, p.end, r.precision), t.moved


def run_in_place(r: Register, c: Circuit, fast_chunks: int) -> tuple[Register, dict[str, int]]:
    """Gate by gate. A gate inside chunks is a pass over the slow tier of its own ('in_place'); others are pair exchanges of all chunks."""
    t = Tiers.split(r.df, fast_chunks, r.nc, r.precision)
    for k, g in enumerate(c.gates):
        if max([*g.written, -1]) < r.nc:
            t.run((Step(k, g, g.qubits),), "in_place")
        else:
            t = t.exchanged(apply_global(t.whole(), g, g.qubits, r.n, r.nc, "pair", r.precision), "exchanges")
    return Register(t.whole(), r.n, r.nc, r.layout, r.precision), t.moved
