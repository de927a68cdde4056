"""Map automata: deterministic machines whose states are maps over another automaton's states.

Over a complete deterministic automaton a map is a vector of successors, one for each state; over a nondeterministic
one it is a relation, a bit mask for each state. Reading a symbol composes the map with that symbol's own map, so a
word leads from the identity to the map of the whole word, and the map of a word cut anywhere is the composition of
the maps of its pieces, in order.
"""

from __future__ import annotations

from collections import deque
from dataclasses import dataclass, field

import numpy as np

from .dfa import Dfa, TooLarge
from .nfa import Nfa, bits


def compose_fun(f: np.ndarray, g: np.ndarray) -> np.ndarray:
    """First f, then g."""
    return g[f]


def compose_rel(f: tuple[int, ...], g: tuple[int, ...]) -> tuple[int, ...]:
    """First f, then g: the boolean matrix product of bit-mask rows."""
    out = []
    for row in f:
        to = 0
        for q in bits(row):
            to |= g[q]
        out.append(to)
    return tuple(out)


def end_states(image: tuple[int, ...], initial: int) -> int:
    """The states a relation map leads to from the initial ones."""
    out = 0
    for q in bits(initial):
        out |= image[q]
    return out


#: Images are kept whole up to this number of cells (8 MB at most); beyond it they are rebuilt from parents on demand.
KEEP_CELLS = 1 << 21


@dataclass(eq=False)
class MapAutomaton:
    """delta[m, c] is the next map; map 0 is the identity; parent and via tell how each map was first reached."""

    base: Dfa | Nfa
    delta: np.ndarray
    final: np.ndarray
    parent: np.ndarray
    via: np.ndarray
    images: np.ndarray | list | None = field(default=None, repr=False)

    @property
    def size(self) -> int:
        return len(self.delta)

    @property
    def functional(self) -> bool:
        return isinstance(self.base, Dfa)

    def image(self, m: int):
        if self.images is not None:
            return self.images[m]
        path = []
        while m:
            path.append(int(self.via[m]))
            m = int(self.parent[m])
        image = np.arange(self.base.size)
        for c in reversed(path):
            image = self.base.delta[image, c]
        return image

    @property
    def dead(self) -> int | None:
        """The map that sends every state to the sink (or to nothing), if it occurs: it absorbs all that follows."""
        loops = np.flatnonzero((self.delta == np.arange(self.size)[:, None]).all(axis=1) & ~self.final)
        sink = self.base.sink if self.functional else None
        for m in loops.tolist():
            image = self.image(m)
            if (sink is not None and (np.asarray(image) == sink).all()) if self.functional else not any(image):
                return m
        return None

    @property
    def live(self) -> int:
        return self.size - (self.dead is not None)

    def run(self, symbols, start: int = 0) -> int:
        m = start
        for c in symbols:
            m = int(self.delta[m, c])
        return m

    def accepts(self, symbols) -> bool:
        return bool(self.final[self.run(symbols)])


def _images(delta: np.ndarray, parents: np.ndarray, vias: np.ndarray, levels: list[int]) -> np.ndarray:
    """All images, level by level: a map's image is its parent's, moved by one symbol."""
    out = np.empty((len(parents), len(delta)), np.uint16 if len(delta) < 1 << 16 else np.int32)
    out[0] = np.arange(len(delta))
    for lo, hi in zip(levels[1:], levels[2:], strict=False):
        out[lo:hi] = delta[out[parents[lo:hi]], vias[lo:hi, None]]
    return out


def close_functions(dfa: Dfa, most: int = 1_100_000, cells: int = 1 << 20) -> MapAutomaton:
    """All maps reachable over a complete deterministic automaton, level by level.

    A map is held as its distinct states, each with the summed random weights of the states that lead there, so what has
    merged is moved once. The fingerprint of a map (128 bits) is the sum of these weights times random words of the
    states: it tells maps apart, and that of every next map follows from the same entries, without making its image.
    Only the frontier's entries are held.
    """
    d, k = dfa.size, dfa.classes.k
    delta = dfa.delta
    rng = np.random.default_rng(1)
    words, own = rng.integers(0, 1 << 64, d, dtype=np.uint64) | np.uint64(1), rng.integers(0, 1 << 64, (2, d), dtype=np.uint64)
    moved = np.ascontiguousarray(words[delta.T])  # the word of each state's successor, by class
    begin, state, weight, first = np.zeros(1, np.int64), np.arange(d), own, np.zeros(1, np.int64)
    ids = {tuple(int((w * words).sum(dtype=np.uint64)) for w in own): 0}
    edges, parents, vias, starts, levels = [], [0], [0], [first], [0, 1]
    while len(begin):
        ends = np.append(begin[1:], len(state))
        each = max(1, cells // (k * max(1, int((ends - begin).max()))))
        base, row, fresh = levels[-2], np.empty((len(begin), k), np.int64), []
        for lo in range(0, len(begin), each):
            hi = min(lo + each, len(begin))
            part = slice(begin[lo], ends[hi - 1])
            next_words = moved[:, state[part]]
            low, high = (np.add.reduceat(next_words * w[part], begin[lo:hi] - begin[lo], axis=1).T.ravel() for w in weight)
            _, at, back = np.unique(low, return_index=True, return_inverse=True)
            if (high[at][back] != high).any():
                _, at, back = np.unique(np.stack([low, high]), axis=1, return_index=True, return_inverse=True)
            numbers, order = np.empty(len(at), np.int64), np.argsort(at)
            where = at[order]
            for j, i, mark in zip(order.tolist(), where.tolist(), zip(low[where].tolist(), high[where].tolist(), strict=True), strict=True):
                m = ids.get(mark)
                if m is None:
                    m = ids[mark] = len(parents)
                    fresh.append(lo * k + i)
                    parents.append(base + lo + i // k)
                    vias.append(i % k)
                numbers[j] = m
            row[lo:hi] = numbers[back.ravel()].reshape(-1, k)
            if len(parents) > most:
                raise TooLarge(f"more than {most} maps")
        edges.append(row)
        levels.append(len(parents))
        at, by = np.divmod(np.array(fresh, np.int64), k)
        first = delta[first[at], by].astype(np.int64)
        starts.append(first)
        size = (ends - begin)[at]
        name = np.repeat(np.arange(len(at)), size)
        entry = np.arange(len(name)) - np.repeat(np.cumsum(size) - size, size) + begin[at][name]
        key = name * d + delta[state[entry], by[name]]
        order = np.argsort(key, kind="stable")
        key = key[order]
        cut = np.flatnonzero(np.concatenate([np.ones(min(1, len(key)), bool), key[1:] != key[:-1]]))
        weight = np.add.reduceat(weight[:, entry[order]], cut, axis=1) if len(cut) else weight[:, :0]
        state = key[cut] % d
        begin = np.flatnonzero(np.concatenate([np.ones(min(1, len(cut)), bool), np.diff(key[cut] // d) > 0]))
    parents, vias = np.array(parents, np.int32), np.array(vias, np.uint16)
    kept = len(parents) * d <= KEEP_CELLS
    return MapAutomaton(dfa, np.concatenate(edges).astype(np.int32), dfa.final[np.concatenate(starts)], parents, vias, _images(delta, parents, vias, levels) if kept else None)


def close_relations(nfa: Nfa, most: int = 100_000) -> MapAutomaton:
    """All relation maps reachable over a nondeterministic automaton."""
    k = nfa.classes.k
    moved: dict[tuple[int, int], int] = {}

    def move(states: int, c: int) -> int:
        if (states, c) not in moved:
            moved[states, c] = nfa.move(states, c)
        return moved[states, c]

    start = tuple(1 << q for q in range(nfa.size))
    ids, rows, parents, vias, queue = {start: 0}, [], [0], [0], deque([start])
    while queue:
        image = queue.popleft()
        row = []
        for c in range(k):
            to = tuple(move(r, c) for r in image)
            if to not in ids:
                if len(ids) >= most:
                    raise TooLarge(f"more than {most} maps")
                ids[to] = len(ids)
                parents.append(len(rows))
                vias.append(c)
                queue.append(to)
            row.append(ids[to])
        rows.append(row)
    final = np.array([bool(end_states(m, nfa.initial) & nfa.final) for m in ids])
    return MapAutomaton(nfa, np.array(rows, np.int32), final, np.array(parents), np.array(vias), list(ids))


def compose_table(auto: MapAutomaton, most_cells: int = 16_000_000) -> np.ndarray:
    """table[f, g]: the number of the map "first f, then g", for all pairs."""
    if auto.size**2 > most_cells:
        raise TooLarge("composition table")
    # column g follows column parent(g) by one symbol
    table = np.empty((auto.size, auto.size), np.int32)
    table[:, 0] = np.arange(auto.size)
    for g in range(1, auto.size):
        table[:, g] = auto.delta[table[:, auto.parent[g]], auto.via[g]]
    return table


class LazyMaps:
    """Maps made only as words meet them, remembered within one worker; numbers mean nothing outside it.

    Over a deterministic automaton an image is a vector of states. Over a nondeterministic one it is a boolean matrix,
    so that no deterministic automaton is ever made: what is never met costs nothing, however many maps or subsets
    there are.
    """

    def __init__(self, base: Dfa | Nfa, keep: int = 65_536):
        self.base, self.keep, self.made, self.flushes = base, keep, 0, 0
        if isinstance(base, Dfa):
            self._first = np.arange(base.size, dtype=np.int32)
            self._advance = lambda image, c: base.delta[image, c]
        else:
            self._first = np.eye(base.size, dtype=bool)
            rows = np.zeros((base.classes.k, base.size, base.size), np.float32)
            for q, c, to in base.edges():
                rows[c, q, to] = 1
            self._advance = lambda image, c: image.astype(np.float32) @ rows[c] > 0
        self._start([self._first])

    def _start(self, images: list[np.ndarray]) -> None:
        self.images, self.ids = images, {x.tobytes(): i for i, x in enumerate(images)}
        self.delta = np.full((max(64, 2 * len(images)), self.base.classes.k), -1, np.int32)
        self.made += len(images)

    def identity(self) -> int:
        known = self.ids.get(self._first.tobytes())
        return self._add(self._first) if known is None else known

    def listed(self, m: int) -> list[int]:
        """An image as a list of states, or of bit masks."""
        image = self.images[m]
        if image.ndim == 1:
            return image.tolist()
        return [int.from_bytes(row.tobytes(), "little") for row in np.packbits(image, axis=1, bitorder="little")]

    def _add(self, image: np.ndarray) -> int:
        self.ids[image.tobytes()] = len(self.images)
        self.images.append(image)
        self.made += 1
        if len(self.images) > len(self.delta):
            self.delta = np.concatenate([self.delta, np.full_like(self.delta, -1)])
        return len(self.images) - 1

    def make_room(self, maps: np.ndarray, more: int) -> np.ndarray:
        """Forget all but the given maps if ``more`` new ones might not fit; returns their present numbers."""
        if len(self.images) + more <= self.keep:
            return maps
        used, renamed = np.unique(maps, return_inverse=True)
        self._start([self.images[m] for m in used])
        self.flushes += 1
        return renamed.ravel().astype(np.int32)

    def step(self, maps: np.ndarray, classes: np.ndarray) -> np.ndarray:
        """Next maps of many lanes at once."""
        out = self.delta[maps, classes]
        missing = np.flatnonzero(out < 0)
        if len(missing):
            for m, c in np.unique(np.stack([maps[missing], classes[missing]]), axis=1).T.tolist():
                image = self._advance(self.images[m], c)
                known = self.ids.get(image.tobytes())
                self.delta[m, c] = self._add(image) if known is None else known
            out = self.delta[maps, classes]
        return out
