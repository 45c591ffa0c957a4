"""Gate scripts (a subset of OpenQASM 2: qreg, u1, u2, u3, cx, the named gates, barrier) as text and as a Spark data source."""

from __future__ import annotations

import ast
import math
import re

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.gates import KINDS, Circuit, Gate

_LINE = re.compile(r"\s*([a-z]\w*)\s*(?:\(([^)]*)\))?\s*([^;]*)")
_QUBIT = re.compile(r"\[(\d+)\]")


def number(text: str) -> float:
    """An angle: numbers, pi and arithmetic."""

    def value(e):
        if isinstance(e, ast.Constant) and isinstance(e.value, (int, float)):
            return float(e.value)
        if isinstance(e, ast.Name) and e.id == "pi":
            return math.pi
        if isinstance(e, ast.UnaryOp) and isinstance(e.op, ast.USub):
            return -value(e.operand)
        if isinstance(e, ast.BinOp):
            a, b = value(e.left), value(e.right)
            return {ast.Add: lambda: a + b, ast.Sub: lambda: a - b, ast.Mult: lambda: a * b, ast.Div: lambda: a / b}[type(e.op)]()
        raise ValueError(f"not an angle: {text}")

    return value(ast.parse(text.strip(), mode="eval").body)


def parse_line(line: str) -> Gate | int | None:
    """A gate, the size of a register, or nothing."""
    line = line.split("//")[0].strip()
    m = _LINE.match(line)
    if not m or m[1] in ("barrier", "creg", "include", "measure") or line.startswith("OPENQASM"):
        return None
    qubits = tuple(int(q) for q in _QUBIT.findall(m[3]))
    if m[1] == "qreg":
        return qubits[0]
    if m[1] not in KINDS:
        raise ValueError(f"unknown gate in: {line}")
    return Gate(m[1], qubits, tuple(number(x) for x in m[2].split(",")) if m[2] else ())


def parse(text: str) -> Circuit:
    got = [parse_line(x) for x in text.replace("\n", " ").split(";")]
    n = next((x for x in got if isinstance(x, int)), 0)
    return Circuit(n, tuple(g for g in got if isinstance(g, Gate)))


def emit(c: Circuit) -> str:
    lines = ["OPENQASM 2.0;", f"qreg q[{c.n}];"]
    for g in c.gates:
        angles = f"({','.join(repr(float(x)) for x in g.params)})" if g.params else ""
        lines.append(f"{g.kind}{angles} {','.join(f'q[{q}]' for q in g.qubits)};")
    return "\n".join(lines) + "\n"


class _Reader(DataSourceReader):
    def __init__(self, script: str):
        self.script = script

    def partitions(self):
        return [InputPartition(0)]

    def read(self, partition):
        for k, g in enumerate(parse(self.script).gates):
            yield (0, k, g.kind, list(g.qubits), [float(x) for x in g.params])


class GateScript(DataSource):
    """spark.read.format('gatescript').option('script', text).load(): a row for each gate, in order. A script is one small text."""

    @classmethod
    def name(cls):
        return "gatescript"

    def schema(self):
        return "circuit_id long, ord long, kind string, qubits array<int>, params array<double>"

    def reader(self, schema):
        return _Reader(self.options.get("script", ""))
