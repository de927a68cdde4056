"""Symbol classes: symbols that no set of the pattern tells apart share a column of every table."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np

from .pattern import TOP


def sets_of(tree) -> set:
    """All symbol sets of a syntax tree."""
    if tree[0] == "set":
        return {tree[1]}
    parts = tree[1] if tree[0] in ("cat", "alt") else (tree[1],)
    return set().union(*map(sets_of, parts)) if parts else set()


@dataclass(frozen=True)
class SymbolClasses:
    """starts[i] opens an interval of symbols whose class is ids[i]; k classes in all."""

    unit: str
    starts: tuple[int, ...]
    ids: tuple[int, ...]

    @property
    def k(self) -> int:
        return max(self.ids) + 1

    @cached_property
    def table(self) -> np.ndarray:
        """Class by symbol."""
        ends = np.array([*self.starts[1:], TOP[self.unit] + 1])
        kind = np.uint8 if self.k < 256 else np.uint16
        return np.repeat(np.array(self.ids, kind), ends - np.array(self.starts))

    def rows(self) -> list[tuple[int, int, int]]:
        """(lo, hi, class) of every interval."""
        ends = [*self.starts[1:], TOP[self.unit] + 1]
        return [(a, b - 1, c) for a, b, c in zip(self.starts, ends, self.ids, strict=True)]

    def holds(self, ranges) -> int:
        """Bit mask of the classes inside a symbol set."""
        mask = 0
        for a, c in zip(self.starts, self.ids, strict=True):
            if any(lo <= a <= hi for lo, hi in ranges):
                mask |= 1 << c
        return mask


def from_sets(sets, unit: str = "codepoint") -> SymbolClasses:
    """The coarsest classes that respect all the sets, numbered by first symbol; symbols in no set come last."""
    edges = sorted({0} | {e for s in sets for lo, hi in s for e in (lo, hi + 1) if e <= TOP[unit]})
    ordered = sorted(sets)
    inside = [tuple(i for i, s in enumerate(ordered) if any(lo <= a <= hi for lo, hi in s)) for a in edges]
    kinds = sorted(dict.fromkeys(inside), key=lambda x: not x)
    return SymbolClasses(unit, tuple(edges), tuple(kinds.index(x) for x in inside))


def from_tree(tree, unit: str = "codepoint") -> SymbolClasses:
    return from_sets(sets_of(tree), unit)
