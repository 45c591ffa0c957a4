"""Gates and circuits: matrices, classes, inverses, lowering to a universal set."""

from __future__ import annotations

import cmath
import math
from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np

PI = math.pi
#: kind: (qubits, angles). Controls come first in the qubits.
KINDS = {
    "id": (1, 0), "x": (1, 0), "y": (1, 0), "z": (1, 0), "h": (1, 0), "s": (1, 0), "sdg": (1, 0), "t": (1, 0), "tdg": (1, 0),
    "rx": (1, 1), "ry": (1, 1), "rz": (1, 1), "u1": (1, 1), "u2": (1, 2), "u3": (1, 3),
    "cx": (2, 0), "cz": (2, 0), "cp": (2, 1), "crz": (2, 1), "swap": (2, 0), "ccx": (3, 0),
}
DIAGONAL = {"id", "z", "s", "sdg", "t", "tdg", "rz", "u1", "cz", "cp", "crz", "diagonal"}


@dataclass(frozen=True)
class Gate:
    """kind on qubits (0-based) with angles; 'unitary' and 'diagonal' carry their entries."""

    kind: str
    qubits: tuple[int, ...]
    params: tuple[float, ...] = ()
    matrix: tuple | None = field(default=None, compare=False)

    def __post_init__(self):
        if len(set(self.qubits)) != len(self.qubits):
            raise ValueError(f"{self.kind}: a qubit is named twice: {self.qubits}")
        if min(self.qubits, default=0) < 0:
            raise ValueError(f"{self.kind}: negative qubit")
        if self.kind in ("unitary", "diagonal"):
            size = 2 ** len(self.qubits)
            if np.shape(self.matrix) != ((size, size) if self.kind == "unitary" else (size,)):
                raise ValueError(f"{self.kind}: {size} rows of entries are needed")
        elif self.kind not in KINDS:
            raise ValueError(f"unknown gate {self.kind}")
        elif (len(self.qubits), len(self.params)) != KINDS[self.kind]:
            raise ValueError(f"{self.kind} takes {KINDS[self.kind][0]} qubits and {KINDS[self.kind][1]} angles")

    @property
    def is_diagonal(self) -> bool:
        return self.kind in DIAGONAL

    @property
    def controls(self) -> tuple[int, ...]:
        return self.qubits[:-1] if self.kind in ("cx", "ccx") else ()

    @property
    def written(self) -> tuple[int, ...]:
        """Qubits whose partner amplitudes the gate mixes."""
        if self.is_diagonal:
            return ()
        return self.qubits[-1:] if self.controls else self.qubits

    def on(self, qubits: Iterable[int]) -> Gate:
        return Gate(self.kind, tuple(qubits), self.params, self.matrix)


@dataclass(frozen=True)
class Circuit:
    n: int
    gates: tuple[Gate, ...]

    def __post_init__(self):
        for g in self.gates:
            if max(g.qubits) >= self.n:
                raise ValueError(f"{g.kind} on qubit {max(g.qubits)} of {self.n}")


def as_u3(kind: str, params=()) -> tuple[float, float, float]:
    """Angles of a one-qubit gate (rz and its like up to a global phase)."""
    p = params
    table = {
        "id": (0, 0, 0), "x": (PI, 0, PI), "y": (PI, PI / 2, PI / 2), "z": (0, 0, PI), "h": (PI / 2, 0, PI), "s": (0, 0, PI / 2), "sdg": (0, 0, -PI / 2),
        "t": (0, 0, PI / 4), "tdg": (0, 0, -PI / 4),
    }
    if kind in table:
        return table[kind]
    return {"rx": lambda: (p[0], -PI / 2, PI / 2), "ry": lambda: (p[0], 0, 0), "rz": lambda: (0, 0, p[0]), "u1": lambda: (0, 0, p[0]), "u2": lambda: (PI / 2, *p), "u3": lambda: tuple(p)}[kind]()


def u3_matrix(theta: float, phi: float, lam: float) -> np.ndarray:
    c, s = math.cos(theta / 2), math.sin(theta / 2)
    return np.array([[c, -cmath.exp(1j * lam) * s], [cmath.exp(1j * phi) * s, cmath.exp(1j * (phi + lam)) * c]])


def diagonal_of(g: Gate) -> np.ndarray:
    """Entries of a diagonal gate; the first qubit is the lowest bit."""
    if g.kind == "diagonal":
        return np.asarray(g.matrix, complex)
    if g.kind == "rz":
        return np.exp(np.array([-0.5j, 0.5j]) * g.params[0])
    if g.kind == "crz":
        return np.array([1, np.exp(-0.5j * g.params[0]), 1, np.exp(0.5j * g.params[0])])
    if g.kind in ("cz", "cp"):
        return np.array([1, 1, 1, np.exp(1j * (PI if g.kind == "cz" else g.params[0]))])
    return np.array([1, np.exp(1j * as_u3(g.kind, g.params)[2])])


def matrix_of(g: Gate) -> np.ndarray:
    """Full matrix; the first qubit is the lowest bit of its index."""
    if g.kind == "unitary":
        return np.asarray(g.matrix, complex)
    if g.is_diagonal:
        return np.diag(diagonal_of(g))
    if len(g.qubits) == 1:
        return u3_matrix(*as_u3(g.kind, g.params))
    size = 2 ** len(g.qubits)
    out = np.zeros((size, size), complex)
    for i in range(size):
        if g.kind == "swap":
            j = (i & 1) << 1 | i >> 1
        else:
            j = i ^ (size // 2) if i % (size // 2) == size // 2 - 1 else i
        out[j, i] = 1
    return out


def inverse(c: Circuit) -> Circuit:
    back = []
    for g in reversed(c.gates):
        if g.kind in ("u3", "u2"):
            t, p, l = as_u3(g.kind, g.params)
            back.append(Gate("u3", g.qubits, (-t, -l, -p)))
        elif g.kind == "unitary":
            back.append(Gate("unitary", g.qubits, (), tuple(map(tuple, matrix_of(g).conj().T))))
        elif g.kind == "diagonal":
            back.append(Gate("diagonal", g.qubits, (), tuple(np.conj(diagonal_of(g)))))
        elif g.params:
            back.append(Gate(g.kind, g.qubits, tuple(-x for x in g.params)))
        else:
            back.append(Gate({"s": "sdg", "sdg": "s", "t": "tdg", "tdg": "t"}.get(g.kind, g.kind), g.qubits))
    return Circuit(c.n, tuple(back))


def decompose(c: Circuit) -> Circuit:
    """The circuit in u3, u1 and cx (up to a global phase for rz and crz)."""
    out: list[Gate] = []

    def put(g: Gate):
        q, p = g.qubits, g.params
        if g.kind in ("u3", "u1", "cx"):
            out.append(g)
        elif g.kind == "swap":
            for a, b in ((0, 1), (1, 0), (0, 1)):
                out.append(Gate("cx", (q[a], q[b])))
        elif g.kind in ("cp", "cz"):
            l = p[0] if p else PI
            out.extend([Gate("u1", q[:1], (l / 2,)), Gate("cx", q), Gate("u1", q[1:], (-l / 2,)), Gate("cx", q), Gate("u1", q[1:], (l / 2,))])
        elif g.kind == "crz":
            out.extend([Gate("u1", q[1:], (p[0] / 2,)), Gate("cx", q), Gate("u1", q[1:], (-p[0] / 2,)), Gate("cx", q)])
        elif g.kind == "ccx":
            a, b, t = q
            for x in (Gate("h", (t,)), Gate("cp", (b, t), (PI / 2,)), Gate("cx", (a, b)), Gate("cp", (b, t), (-PI / 2,)), Gate("cx", (a, b)), Gate("cp", (a, t), (PI / 2,)), Gate("h", (t,))):
                put(x)
        elif len(q) == 1 and g.kind in KINDS:
            t, f, l = as_u3(g.kind, p)
            out.append(Gate("u1", q, (l,)) if g.is_diagonal else Gate("u3", q, (t, f, l)))
        else:
            raise ValueError(f"{g.kind} has no lowering here")

    for g in c.gates:
        put(g)
    return Circuit(c.n, tuple(out))


def apply_dense(state: np.ndarray, g: Gate, where: tuple[int, ...] | None = None) -> np.ndarray:
    """A gate on a dense vector; where: positions of its qubits. The kernel of packed chunks."""
    n = int(len(state)).bit_length() - 1
    q = where if where is not None else g.qubits
    if len(q) == 1 and not g.is_diagonal:
        m, v = matrix_of(g), state.reshape(-1, 2, 1 << q[0])
        a, b = v[:, 0, :].copy(), v[:, 1, :]
        v[:, 0, :] = m[0, 0] * a + m[0, 1] * b
        v[:, 1, :] = m[1, 0] * a + m[1, 1] * b
        return state
    axes = [n - 1 - x for x in q]
    t = np.moveaxis(state.reshape((2,) * n), axes[::-1], range(len(q)))
    if g.is_diagonal:
        t *= diagonal_of(g).reshape((2,) * len(q) + (1,) * (n - len(q)))
    elif g.kind == "cx":
        t[0, 1], t[1, 1] = t[1, 1].copy(), t[0, 1].copy()
    else:
        shape = t.shape
        t[...] = (matrix_of(g) @ t.reshape(2 ** len(q), -1)).reshape(shape)
    return state


def simulate(c: Circuit, start: np.ndarray | None = None) -> np.ndarray:
    """Directly, on one dense vector: the check for everything distributed."""
    s = np.zeros(2**c.n, complex) if start is None else start.astype(complex).copy()
    if start is None:
        s[0] = 1
    for g in c.gates:
        s = apply_dense(s, g)
    return s


def fuse(gates: list[Gate], most: int = 5) -> list[Gate]:
    """Runs of neighbouring gates as one unitary while they touch at most `most` qubits."""
    out: list[Gate] = []
    run: list[Gate] = []

    def close():
        if len(run) > 1:
            qs = sorted({q for g in run for q in g.qubits})
            at = {q: i for i, q in enumerate(qs)}
            cols = np.stack([simulate(Circuit(len(qs), tuple(g.on(at[q] for q in g.qubits) for g in run)), e) for e in np.eye(2 ** len(qs), dtype=complex)], 1)
            out.append(Gate("unitary", tuple(qs), (), tuple(map(tuple, cols))))
        else:
            out.extend(run)
        run.clear()

    for g in gates:
        if len({q for x in [*run, g] for q in x.qubits}) > most:
            close()
        run.append(g)
    close()
    return out
