"""Random-volume circuits as a Spark data source, generated where they are read."""

from __future__ import annotations

import math

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .workloads import GATES, PAIR_BLOCK, paired


def angles(circuit: int, k: int) -> list[float]:
    """theta, phi, lambda of a circuit's k-th gate, by rule, so that every layer can be generated alone."""
    return [math.pi * ((k * 37 + circuit * 11) % 50 + 1) / 50, 2 * math.pi * (k * 53 % 1009) / 1009, 2 * math.pi * ((k * 29 + circuit) % 1013) / 1013]


class Units(InputPartition):
    """Layers lo to hi (excluded), counted through all circuits."""

    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, n: int, depth: int, circuits: int, parts: int):
        self.n, self.depth, self.units, self.parts = n, depth, depth * circuits, parts

    def partitions(self):
        parts = max(1, min(self.parts, self.units))
        return [Units(self.units * p // parts, self.units * (p + 1) // parts) for p in range(parts)]

    def read(self, partition):
        gates = self.n // 2 * len(PAIR_BLOCK)
        for unit in range(partition.lo, partition.hi):
            circuit, layer = divmod(unit, self.depth)
            k = layer * gates
            for pair in paired(self.n, layer):
                for kind, side in PAIR_BLOCK:
                    yield (circuit, k, kind, [pair[side]] if kind == "u3" else [pair[side], pair[1 - side]], angles(circuit, k) if kind == "u3" else [])
                    k += 1


class VolumeCircuits(DataSource):
    """spark.read.format('volumecircuits').option('n', 8).option('depth', 10).option('circuits', 25).option('parts', 8).load(): a row for each gate.

    Each partition generates its own layers, so neither driver nor one task holds the gates of all circuits. Fewer than two qubits, no layer
    or no circuit give no rows.
    """

    @classmethod
    def name(cls):
        return "volumecircuits"

    def schema(self):
        return GATES

    def reader(self, schema):
        return _Reader(*(int(self.options.get(k, v)) for k, v in (("n", 8), ("depth", 10), ("circuits", 1), ("parts", 8))))
