"""The circuit rewriter: sections that every chunk executes alone, with qubit remaps between them.

Positions 0..nc-1 are inside a chunk. plan_blocks() repeats: choose the qubits that shall be inside, remap them there, and retire every gate that
can run there without overtaking a deferred gate on one of its qubits. It works on the gate list on the driver.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

from ..functions.gates import Circuit, Gate

CHOOSERS = ("first_multi", "most_gates", "lookahead", "furthest_next_use")


@dataclass(frozen=True)
class Step:
    """A gate with its place in the input and the positions of its qubits."""

    ord: int
    gate: Gate
    at: tuple[int, ...]


@dataclass(frozen=True)
class Section:
    """op: 'block' (each chunk alone), 'remap' (perm: new position of each position) or 'global' (one wide gate over chunks)."""

    op: str
    steps: tuple[Step, ...] = ()
    perm: tuple[int, ...] = ()
    swaps: tuple[tuple[int, int], ...] = ()
    before: tuple[int, ...] = ()
    after: tuple[int, ...] = ()
    resident: tuple[int, ...] = ()


@dataclass(frozen=True)
class Plan:
    n: int
    nc: int
    sections: tuple[Section, ...]
    start: tuple[int, ...]
    end: tuple[int, ...]

    @property
    def blocks(self) -> list[Section]:
        return [s for s in self.sections if s.op == "block"]

    @property
    def remaps(self) -> list[Section]:
        return [s for s in self.sections if s.op == "remap"]

    @property
    def n_swaps(self) -> int:
        return sum(len(s.swaps) for s in self.remaps)


def reorder_idle(c: Circuit) -> list[int]:
    """Position of each qubit: updated ones first, then those that no gate updates, both ascending."""
    busy = {q for g in c.gates for q in g.written}
    order = [q for q in range(c.n) if q in busy] + [q for q in range(c.n) if q not in busy]
    at = [0] * c.n
    for p, q in enumerate(order):
        at[q] = p
    return at


def swaps_as_perm(n: int, swaps) -> tuple[int, ...]:
    perm = list(range(n))
    for a, b in swaps:
        perm = [b if p == a else a if p == b else p for p in perm]
    return tuple(perm)


@functools.lru_cache(maxsize=256)
def plan_blocks(
    c: Circuit, nc: int, *, resident_cap: int | None = None, chooser: str = "first_multi", window: int = 8, diagonal_free: bool = False, control_free: bool = False,
    commute_diagonal: bool = False, idle_first: bool = True, fuse_remaps: bool = True, max_swaps: int | None = None, restore_order: bool = True,
) -> Plan:
    """Plan of c for chunks of nc qubits. Planned once for each circuit and options (the cache is the ahead-of-time form)."""
    if chooser not in CHOOSERS:
        raise ValueError(f"unknown chooser {chooser}")
    nc = min(nc, c.n)
    if nc < 1:
        raise ValueError("a chunk needs a qubit")
    cap = min(resident_cap or nc, nc)
    most_in = min(x for x in (max_swaps, cap, nc) if x is not None)

    def needs(g: Gate) -> tuple[int, ...]:
        """Qubits that must be inside a chunk."""
        if diagonal_free and g.is_diagonal:
            return ()
        if control_free and g.controls:
            return g.written
        return g.qubits

    wide = lambda g: len(needs(g)) > min(cap, max(1, most_in))
    pos = reorder_idle(c) if idle_first else list(range(c.n))
    start, sections = tuple(pos), []
    pending = list(enumerate(c.gates))

    def inside() -> list[int]:
        return sorted(q for q in range(c.n) if pos[q] < nc)

    def next_use(q: int) -> int:
        return next((k for k, (_, g) in enumerate(pending) if q in needs(g)), len(pending))

    def grown(chosen: list[int], g: Gate) -> list[int] | None:
        """chosen with g's qubits, if they fit."""
        new = chosen + [q for q in needs(g) if q not in chosen]
        return new if len(new) <= cap and sum(pos[q] >= nc for q in new) <= most_in else None

    def choose(gates) -> list[int]:
        out: list[int] = []
        for many in (True, False):
            for _, g in gates:
                if (len(needs(g)) > 1) == many and needs(g) and not wide(g) and len(out) < cap:
                    out = grown(out, g) or out
        return out

    def filled(chosen: list[int]) -> list[int]:
        spare = [q for q in inside() if q not in chosen]
        spare.sort(key=(lambda q: (next_use(q), q)) if chooser == "furthest_next_use" else (lambda q: q))
        return sorted(chosen + spare[: nc - len(chosen)])

    def sweep(resident: list[int]):
        """(retired, deferred) of the pending gates."""
        hold, hold_diagonal, done, later = set(), set(), [], []
        for k, g in pending:
            free = not hold.intersection(g.qubits) and (not hold_diagonal.intersection(g.qubits) or commute_diagonal and g.is_diagonal)
            if free and not wide(g) and set(needs(g)) <= set(resident):
                done.append((k, g))
            else:
                (hold_diagonal if g.is_diagonal else hold).update(g.qubits)
                later.append((k, g))
        return done, later

    def reachable():
        """Pending gates that aren't behind a wide one."""
        behind, out = set(), []
        for k, g in pending:
            if wide(g) or behind.intersection(g.qubits):
                behind.update(g.qubits)
            else:
                out.append((k, g))
        return out

    def candidates() -> list[list[int]]:
        ahead = reachable()
        if chooser == "most_gates":
            first = next((g for _, g in ahead if len(needs(g)) > 1 and not wide(g)), None)
            count = lambda q: -sum(q in needs(g) for _, g in ahead)
            out = list(needs(first)) if first else []
            for q in sorted(range(c.n), key=lambda q: (count(q), q)):
                if q not in out and len(out) < cap and count(q) < 0 and sum(pos[x] >= nc for x in [*out, q]) <= most_in:
                    out.append(q)
            return [out]
        if chooser == "lookahead":
            starts = [k for k, (_, g) in enumerate(ahead) if len(needs(g)) > 1 and not wide(g)][:window]
            return [choose(ahead), *(choose([ahead[k], *ahead[:k], *ahead[k + 1 :]]) for k in starts[1:])]
        return [choose(ahead)]

    def remap(swaps) -> None:
        nonlocal pos
        for group in [swaps] if fuse_remaps else [[s] for s in swaps]:
            perm, before = swaps_as_perm(c.n, group), tuple(pos)
            pos = [perm[p] for p in pos]
            sections.append(Section("remap", perm=perm, swaps=tuple(group), before=before, after=tuple(pos)))

    while pending:
        blocked: set[int] = set()
        for k, g in pending:  # a wide gate runs over chunks once nothing is before it
            if wide(g) and not blocked.intersection(g.qubits):
                sections.append(Section("global", (Step(k, g, tuple(pos[q] for q in g.qubits)),), before=tuple(pos), after=tuple(pos)))
                pending.remove((k, g))
                break
            blocked.update(g.qubits)
        else:
            best = None
            head = grown([], pending[0][1]) or []
            for chosen in [*candidates(), head]:  # the head alone always retires
                if chosen is head and best is not None:
                    break
                resident = filled(chosen)
                done, later = sweep(resident)
                moved = sum(pos[q] >= nc for q in resident)
                if done and (best is None or (len(done), -moved) > best[0]):
                    best = ((len(done), -moved), resident, done, later)
            _, resident, done, later = best
            incoming = sorted((q for q in resident if pos[q] >= nc), key=lambda q: pos[q])
            outgoing = sorted((q for q in inside() if q not in resident), key=lambda q: pos[q])
            swaps = [(pos[o], pos[i]) for o, i in zip(outgoing, incoming, strict=False)]
            if swaps:
                remap(swaps)
            sections.append(Section("block", tuple(Step(k, g, tuple(pos[q] for q in g.qubits)) for k, g in done), before=tuple(pos), after=tuple(pos), resident=tuple(resident)))
            pending = later
    if restore_order and pos != list(range(c.n)):
        swaps, now = [], list(pos)
        for q in range(c.n):
            if now[q] != q:
                other = now.index(q)
                swaps.append((min(now[q], q), max(now[q], q)))
                now[other], now[q] = now[q], q
        # the budget holds here, too: the permutation goes in rounds of so many swaps
        for k in range(0, len(swaps), max_swaps or len(swaps)):
            remap(swaps[k : k + (max_swaps or len(swaps))])
    return Plan(c.n, nc, tuple(sections), start, tuple(pos))


def stats(p: Plan) -> dict[str, int]:
    gates = [len(s.steps) for s in p.blocks]
    return {"gates": sum(len(s.steps) for s in p.sections), "sections": len(gates), "global_gates": sum(s.op == "global" for s in p.sections), "remaps": len(p.remaps), "swaps": p.n_swaps, "least_gates": min(gates, default=0), "most_gates": max(gates, default=0)}
