"""Index algebra: bit k of an index is qubit k; a layout gives the position of each qubit."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def bit(c, k: int) -> Column:
    return F.shiftright(col(c), k).bitwiseAND(F.lit(1))


def u6(c) -> Column:
    """A double as whole millionths; the offset keeps exact ties on one side under rounding noise."""
    return F.floor(col(c) * 1e6 + 0.5001).cast("long")


def permuted(c, perm: list[int]) -> Column:
    """The index whose bit perm[k] is bit k of c. Bits that move equally far move together."""
    masks: dict[int, int] = {}
    for k, to in enumerate(perm):
        masks[to - k] = masks.get(to - k, 0) | 1 << k
    out = F.lit(0).cast("long")
    for by, mask in masks.items():
        part = col(c).bitwiseAND(F.lit(mask))
        out = out.bitwiseOR(F.shiftleft(part, by) if by >= 0 else F.shiftright(part, -by))
    return out


def permute_index(idx: int, perm: list[int]) -> int:
    return sum(((idx >> k) & 1) << to for k, to in enumerate(perm))
