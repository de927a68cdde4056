"""Epsilon-free automata from syntax trees: a state for every symbol occurrence, and a start. Sets are bit masks."""

from __future__ import annotations

from dataclasses import dataclass

from .alphabet import SymbolClasses, from_tree
from .pattern import Unsupported


def bits(mask: int):
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


@dataclass(frozen=True)
class Nfa:
    """step[q][c] is the set of successors of state q under class c."""

    step: tuple[tuple[int, ...], ...]
    initial: int
    final: int
    classes: SymbolClasses

    @property
    def size(self) -> int:
        return len(self.step)

    def move(self, states: int, c: int) -> int:
        out = 0
        for q in bits(states):
            out |= self.step[q][c]
        return out

    def run(self, symbols) -> int:
        """The states reached from the initial ones over class ids."""
        states = self.initial
        for c in symbols:
            states = self.move(states, c)
        return states

    def accepts(self, symbols) -> bool:
        return bool(self.run(symbols) & self.final)

    def edges(self) -> list[tuple[int, int, int]]:
        return [(q, c, t) for q, row in enumerate(self.step) for c, to in enumerate(row) for t in bits(to)]


class _Positions:
    """Nullable, first, last and follow of every part, in one walk over the tree."""

    def __init__(self, classes: SymbolClasses, most: int):
        self.classes, self.most = classes, most
        self.follow: list[int] = [0]
        self.masks: list[int] = [0]

    def walk(self, tree) -> tuple[bool, int, int]:
        kind = tree[0]
        if kind == "set":
            if len(self.follow) > self.most:
                raise Unsupported("too many positions")
            self.follow.append(0)
            self.masks.append(self.classes.holds(tree[1]))
            bit = 1 << (len(self.follow) - 1)
            return False, bit, bit
        if kind == "alt":
            parts = [self.walk(p) for p in tree[1]]
            first = last = 0
            for _, f, t in parts:
                first, last = first | f, last | t
            return any(n for n, _, _ in parts), first, last
        if kind == "cat":
            return self.chain(self.walk(p) for p in tree[1])
        _, part, least, most = tree
        if most is None:
            whole = self.chain([*(self.walk(part) for _ in range(max(least - 1, 0))), self.loop(part)])
            return (True, *whole[1:]) if least == 0 else whole
        needed = [self.walk(part) for _ in range(least)]
        spare = [(True, *self.walk(part)[1:]) for _ in range(most - least)]
        return self.chain(needed + spare)

    def chain(self, parts) -> tuple[bool, int, int]:
        nullable, first, last = True, 0, 0
        for n, f, t in parts:
            for q in bits(last):
                self.follow[q] |= f
            first = first | f if nullable else first
            last = t | last if n else t
            nullable = nullable and n
        return nullable, first, last

    def loop(self, part) -> tuple[bool, int, int]:
        n, first, last = self.walk(part)
        for q in bits(last):
            self.follow[q] |= first
        return n, first, last


def position_nfa(tree, unit: str = "codepoint", most: int = 20_000) -> Nfa:
    """The position automaton of a syntax tree."""
    classes = from_tree(tree, unit)
    walk = _Positions(classes, most)
    nullable, first, last = walk.walk(tree)
    walk.follow[0] = first
    holders = [sum(1 << q for q, m in enumerate(walk.masks) if m >> c & 1) for c in range(classes.k)]
    step = tuple(tuple(f & h for h in holders) for f in walk.follow)
    return Nfa(step, 1, last | (1 if nullable else 0), classes)
