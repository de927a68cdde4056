"""Deterministic automata: subset determinisation (eager and lazy), minimisation, completion, equivalence."""

from __future__ import annotations

from collections import deque
from dataclasses import dataclass

import numpy as np

from .alphabet import SymbolClasses, from_sets
from .nfa import Nfa, bits


class TooLarge(ValueError):
    """An automaton passed its cap of states."""


@dataclass(frozen=True, eq=False)
class Dfa:
    """delta[q, c] is the successor; state 0 is initial; the automaton is complete."""

    delta: np.ndarray
    final: np.ndarray
    classes: SymbolClasses

    @property
    def size(self) -> int:
        return len(self.delta)

    @property
    def sink(self) -> int | None:
        """The state from which nothing is accepted, if there is one (minimal automata have one at most)."""
        own = np.arange(self.size)[:, None]
        dead = np.flatnonzero((self.delta == own).all(axis=1) & ~self.final)
        return int(dead[0]) if len(dead) else None

    @property
    def live(self) -> int:
        return self.size - (self.sink is not None)

    def run(self, symbols, start: int = 0) -> int:
        q = start
        for c in symbols:
            q = int(self.delta[q, c])
        return q

    def accepts(self, symbols) -> bool:
        return bool(self.final[self.run(symbols)])

    def lengths(self) -> tuple[int, int | None]:
        """Least and greatest length of an accepted word (None: no bound); least is -1 for the empty language."""
        useful = self.final.copy()
        while True:
            more = useful | useful[self.delta].any(axis=1)
            if (more == useful).all():
                break
            useful = more
        level, seen, least, most, n = np.zeros(self.size, bool), set(), -1, None, 0
        level[0] = useful[0]
        while level.any():
            if (level & self.final).any():
                least, most = (n if least < 0 else least), n
            if n > self.size:
                return least, None
            step = np.zeros(self.size, bool)
            step[self.delta[level].ravel()] = True
            level, n = step & useful, n + 1
            seen.add(n)
        return least, most


def determinize(nfa: Nfa, most: int = 100_000) -> Dfa:
    """Reachable state sets, breadth first, from the initial set. The empty set serves as sink."""
    ids, rows, queue = {nfa.initial: 0}, [], deque([nfa.initial])
    k = nfa.classes.k
    while queue:
        states = queue.popleft()
        row = [0] * k
        for q in bits(states):
            step = nfa.step[q]
            for c in range(k):
                row[c] |= step[c]
        for to in row:
            if to not in ids:
                if len(ids) >= most:
                    raise TooLarge(f"more than {most} states")
                ids[to] = len(ids)
                queue.append(to)
        rows.append([ids[to] for to in row])
    final = np.array([bool(s & nfa.final) for s in ids])
    return Dfa(np.array(rows, np.int32), final, nfa.classes)


class LazySubset:
    """Subset construction on demand: state sets get numbers as words meet them."""

    def __init__(self, nfa: Nfa):
        self.nfa, self.ids, self.sets = nfa, {nfa.initial: 0}, [nfa.initial]
        self.delta: dict[tuple[int, int], int] = {}

    def step(self, q: int, c: int) -> int:
        if (q, c) not in self.delta:
            to = self.nfa.move(self.sets[q], c)
            if to not in self.ids:
                self.ids[to] = len(self.sets)
                self.sets.append(to)
            self.delta[q, c] = self.ids[to]
        return self.delta[q, c]

    def accepts(self, symbols) -> bool:
        q = 0
        for c in symbols:
            q = self.step(q, c)
        return bool(self.sets[q] & self.nfa.final)


def _breadth_first(delta: np.ndarray, final: np.ndarray, start: int, classes: SymbolClasses) -> Dfa:
    order, seen = [start], {start: 0}
    for q in order:
        for to in delta[q].tolist():
            if to not in seen:
                seen[to] = len(order)
                order.append(to)
    rename = np.zeros(len(delta), np.int32)
    rename[order] = np.arange(len(order))
    return Dfa(rename[delta[order]].astype(np.int32), final[order], classes)


#: Cells of a table up to which blocks are split one by one, and beyond which all rows are compared in numpy, round by round.
FEW_CELLS = 20_000


def _split_one_by_one(dfa: Dfa) -> np.ndarray:
    """Blocks of equivalent states: a block splits the others by what leads into it; of two halves the smaller goes on."""
    back: list[list[list[int]]] = []
    for column in dfa.delta.T.tolist():
        into: list[list[int]] = [[] for _ in range(dfa.size)]
        for q, to in enumerate(column):
            into[to].append(q)
        back.append(into)
    accepting = set(np.flatnonzero(dfa.final).tolist())
    blocks = [b for b in (accepting, set(range(dfa.size)) - accepting) if b]
    block = np.zeros(dfa.size, np.int64)
    if len(blocks) == 2:
        block[list(blocks[1])] = 1
    of, waiting = block.tolist(), set(range(len(blocks)))
    while waiting:
        members = list(blocks[waiting.pop()])
        for into in back:
            met: dict[int, list[int]] = {}
            for q in members:
                for r in into[q]:
                    met.setdefault(of[r], []).append(r)
            for i, inside in met.items():
                if len(inside) == len(blocks[i]):
                    continue
                new, j = set(inside), len(blocks)
                blocks[i] -= new
                blocks.append(new)
                for r in new:
                    of[r] = j
                waiting.add(j if i in waiting or len(new) <= len(blocks[i]) else i)
    return np.array(of)


def minimize(dfa: Dfa) -> Dfa:
    """The smallest automaton of the same language, its states in breadth-first order."""
    block = _split_one_by_one(dfa) if dfa.delta.size <= FEW_CELLS else _split_by_rounds(dfa)
    one = np.zeros(int(block.max()) + 1, np.int64)
    one[block] = np.arange(dfa.size)
    return _breadth_first(block[dfa.delta[one]], dfa.final[one], int(block[0]), dfa.classes)


def _split_by_rounds(dfa: Dfa) -> np.ndarray:
    """Blocks of equivalent states by rounds: blocks split while their members' successors lie in different blocks.

    Rows of successor blocks are told apart by a random weighted sum; the last partition is checked entry by entry, and
    refined exactly in the (unheard of) case that two sums met.
    """
    weights = np.random.default_rng(3).integers(0, 1 << 64, (dfa.classes.k + 1, 1), dtype=np.uint64) | np.uint64(1)
    marks = np.random.default_rng(4).integers(0, 1 << 64, dfa.size + 1, dtype=np.uint64)

    def summed(block: np.ndarray) -> np.ndarray:
        return np.unique(marks[block[dfa.delta]] @ weights[1:, 0] + marks[block] * weights[0, 0], return_inverse=True)[1]

    def exact(block: np.ndarray) -> np.ndarray:
        return np.unique(np.column_stack([block, block[dfa.delta]]), axis=0, return_inverse=True)[1].ravel()

    for refine in (summed, exact):
        block, n = dfa.final.astype(np.int64), 0
        while (m := int(block.max(initial=0)) + 1) != n:
            block, n = refine(block), m
        one = np.zeros(n, np.int64)
        one[block] = np.arange(dfa.size)
        if (block[dfa.delta] == block[dfa.delta[one]][block]).all() and (dfa.final == dfa.final[one][block]).all():
            break
    return block


def complete(delta: np.ndarray, final: np.ndarray, classes: SymbolClasses) -> Dfa:
    """A total automaton from one that marks missing successors with -1."""
    if (delta >= 0).all():
        return Dfa(delta.astype(np.int32), final, classes)
    sink = len(delta)
    whole = np.vstack([np.where(delta < 0, sink, delta), np.full((1, delta.shape[1]), sink)])
    return Dfa(whole.astype(np.int32), np.append(final, False), classes)


def _ranges_by_class(classes: SymbolClasses) -> list[tuple]:
    return [tuple((lo, hi) for lo, hi, c in classes.rows() if c == i) for i in range(classes.k)]


def equivalent(a: Dfa, b: Dfa) -> tuple[bool, list[int] | None]:
    """Whether two automata accept the same words; if not, a shortest word (as symbols) that tells them apart."""
    both = from_sets({*_ranges_by_class(a.classes), *_ranges_by_class(b.classes)}, a.classes.unit)
    symbols = [next(lo for lo, _, c in both.rows() if c == i) for i in range(both.k)]
    pairs = [(int(a.classes.table[s]), int(b.classes.table[s]), s) for s in symbols]
    seen: dict[tuple[int, int], tuple | None] = {(0, 0): None}
    queue = deque([(0, 0)])
    while queue:
        p, q = here = queue.popleft()
        if a.final[p] != b.final[q]:
            word = []
            while seen[here] is not None:
                here, s = seen[here]
                word.append(s)
            return False, word[::-1]
        for x, y, s in pairs:
            to = int(a.delta[p, x]), int(b.delta[q, y])
            if to not in seen:
                seen[to] = (p, q), s
                queue.append(to)
    return True, None
