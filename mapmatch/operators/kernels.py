"""Batch kernels: many words or chunks stepped together over one table, in numpy.

A batch is a flat array of class ids with the start and length of every lane. Lanes are sorted by length, so a step
touches only the lanes that still have symbols; lanes whose state can never change again are dropped.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa

from ..automata.dfa import Dfa, LazySubset
from ..automata.maps import LazyMaps, MapAutomaton, compose_rel
from ..automata.nfa import Nfa


@dataclass
class Lanes:
    """Class ids of all lanes, one after another; valid marks words that are not null."""

    classes: np.ndarray
    start: np.ndarray
    length: np.ndarray
    valid: np.ndarray

    def __len__(self) -> int:
        return len(self.start)

    def symbols(self) -> int:
        return int(self.length.sum())


def _buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and bytes of a string or binary column, whatever its slice and offset width."""
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return at, np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)


def lanes_of(column: pa.Array, table: np.ndarray, unit: str) -> Lanes:
    """The class ids of a column of words. table: class by symbol."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    valid = np.ones(len(column), bool) if column.null_count == 0 else np.asarray(column.is_valid())
    if len(column) == 0:
        return Lanes(np.zeros(0, table.dtype), np.zeros(0, np.int64), np.zeros(0, np.int64), valid)
    at, data = _buffers(column)
    data = data[at[0] : at[-1]]
    at = at - at[0]
    if unit == "codepoint" and len(data) and data.max() > 0x7F:
        heads = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
        at = heads[at]
        codes = np.frombuffer(data.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32)
        classes = table[codes]
    else:
        classes = table[data]
    length = np.where(valid, np.diff(at), 0)
    return Lanes(classes, at[:-1], length, valid)


def _lockstep(lanes: Lanes, state: np.ndarray, step) -> np.ndarray:
    """Run step(state, classes) over all lanes; state's first axis is the lane."""
    order = np.argsort(-lanes.length, kind="stable")
    start, length = lanes.start[order], lanes.length[order]
    state = state[order]
    for t in range(int(length.max(initial=0))):
        active = int(np.searchsorted(-length, -t))
        state[:active] = step(state[:active], lanes.classes[start[:active] + t])
    back = np.empty_like(state)
    back[order] = state
    return back


#: Cells of a table that steps over several symbols at once; symbols of a block.
WIDE_CELLS, _BLOCK = 1 << 18, 256


class Steps:
    """A transition table over runs of ``m`` symbols, m as large as keeps the table small: one lookup takes m symbols.

    Entries are the row offsets of the next state, so a step is a sum and a gather.
    """

    def __init__(self, delta: np.ndarray, cells: int = WIDE_CELLS):
        n, k = delta.shape
        self.k, self.m, wide = k, 1, np.asarray(delta, np.int64)
        while self.m < 8 and n * wide.shape[1] * k <= cells and wide.shape[1] * k <= 1 << 16:
            wide = wide[delta].reshape(n, -1)  # first one symbol, then a run
            self.m += 1
        self.columns = wide.shape[1]
        self.flat = np.ascontiguousarray(wide * self.columns, np.intp).ravel()
        self.single = None if self.m == 1 else np.asarray(delta, np.intp).ravel()
        self.done = (delta == np.arange(n)[:, None]).all(axis=1)

    def runs(self, symbols: np.ndarray) -> np.ndarray:
        """Numbers of runs of m symbols; symbols by time, then lane, a multiple of m rows."""
        if self.m == 1:
            return symbols
        kind = np.uint8 if self.columns <= 256 else np.uint16
        out = symbols[:: self.m].astype(kind)
        for i in range(1, self.m):
            np.multiply(out, kind(self.k), out=out)
            np.add(out, symbols[i :: self.m], out=out, casting="unsafe")
        return out


_STEPS: dict[int, tuple[np.ndarray, Steps]] = {}


def steps_of(delta: np.ndarray) -> Steps:
    """The prepared table of a transition table; the last few are kept."""
    held = _STEPS.get(id(delta))
    if held is None:
        while len(_STEPS) >= 4:
            _STEPS.pop(next(iter(_STEPS)))
        held = _STEPS[id(delta)] = (delta, Steps(delta))
    return held[1]


def walk_table(lanes: Lanes, delta: np.ndarray, start: int | np.ndarray = 0) -> np.ndarray:
    """End states of all lanes: one lookup a symbol or less, over a deterministic automaton or a map automaton.

    Symbols are laid out by time in blocks, so that a step reads one contiguous row of them.
    """
    table = steps_of(delta)
    m, width = table.m, table.columns
    order = np.argsort(-lanes.length, kind="stable")
    length, at = lanes.length[order], lanes.start[order].astype(np.intp)
    state = np.full(len(lanes), start, np.intp) if np.isscalar(start) else np.asarray(start, np.intp)[order]
    out, name = np.empty(len(lanes), np.int32), order
    t = 0
    while active := int(np.searchsorted(-length, -t)):
        steps = min(int(length[active - 1]) - t, _BLOCK)
        rows = np.lib.stride_tricks.sliding_window_view(lanes.classes, steps)[at[:active]]
        symbols = np.ascontiguousarray(rows.T)
        s, whole = state[:active] * width, steps - steps % m
        cell = np.empty(active, np.intp)
        if whole:
            for run in table.runs(symbols[:whole]):
                np.add(s, run, out=cell)
                np.take(table.flat, cell, out=s, mode="clip")
        s //= width
        for row in symbols[whole:]:
            np.take(table.single, s * table.k + row, out=s, mode="clip")
        state[:active] = s
        at[:active] += steps
        t += steps
        stay = table.done[s]
        if stay.mean() > 0.25:
            gone = np.concatenate([np.flatnonzero(stay), np.arange(active, len(state))])
            out[name[gone]] = state[gone]
            keep = np.flatnonzero(~stay)
            state, length, at, name = state[keep], length[keep], at[keep], name[keep]
    out[name] = state
    return out


def walk_all_states(lanes: Lanes, dfa: Dfa) -> np.ndarray:
    """Speculation: every lane carries the destination of each state, so D lookups where a map takes one. Returns images.

    Steps go over the same wide tables as those of ``walk_table``, so that the two compare.
    """
    table, d = steps_of(dfa.delta), dfa.size
    order = np.argsort(-lanes.length, kind="stable")
    length, at = lanes.length[order], lanes.start[order].astype(np.intp)
    state = np.broadcast_to(np.arange(d, dtype=np.intp), (len(lanes), d)).copy()
    t = 0
    while active := int(np.searchsorted(-length, -t)):
        steps = min(int(length[active - 1]) - t, _BLOCK)
        symbols = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(lanes.classes, steps)[at[:active] + t].T)
        whole = steps - steps % table.m
        s, cell = state[:active], np.empty((active, d), np.intp)
        if whole:
            s *= table.columns
            for run in table.runs(symbols[:whole]):
                np.add(s, run[:, None], out=cell)
                np.take(table.flat, cell, out=s, mode="clip")
            s //= table.columns
        for row in symbols[whole:]:
            np.take(table.single, s * table.k + row[:, None], out=s, mode="clip")
        t += steps
    back = np.empty((len(lanes), d), np.int32)
    back[order] = state
    return back


def walk_merged_states(lanes: Lanes, dfa: Dfa, every: int = 8) -> tuple[np.ndarray, int]:
    """Speculation that advances only distinct destinations. Returns images and the lookups made.

    All lanes' destinations lie in one array; every few symbols those that have met within a lane become one.
    """
    d, k = dfa.size, dfa.classes.k
    flat, n = np.asarray(dfa.delta, np.int64).ravel(), len(lanes)
    lane, label = np.repeat(np.arange(n), d), np.tile(np.arange(d, dtype=np.int64), n)
    where, lookups = np.arange(n * d), 0
    left = lanes.length.copy()
    for t in range(int(lanes.length.max(initial=0))):
        live = np.flatnonzero(t < left[lane])
        of = lane[live]
        label[live] = flat[label[live] * k + lanes.classes[lanes.start[of] + t]]
        lookups += len(live)
        if t % every == every - 1:
            pairs, back = np.unique(lane * d + label, return_inverse=True)
            where, lane, label = back.ravel()[where], pairs // d, pairs % d
    return label[where].reshape(n, d).astype(np.int32), lookups


def walk_lazy(lanes: Lanes, lazy: LazyMaps) -> np.ndarray:
    """The numbers, in ``lazy``, of all lanes' maps, made on demand."""
    order = np.argsort(-lanes.length, kind="stable")
    start, length = lanes.start[order], lanes.length[order]
    state = np.full(len(order), lazy.identity(), np.int32)
    for t in range(int(length.max(initial=0))):
        active = int(np.searchsorted(-length, -t))
        state = lazy.make_room(state, active)
        state[:active] = lazy.step(state[:active], lanes.classes[start[:active] + t])
    back = np.empty_like(state)
    back[order] = state
    return back


def walk_lazy_subsets(lanes: Lanes, lazy: LazySubset, keep: int = 1 << 18) -> np.ndarray:
    """Whether each lane is accepted, by subsets made on demand; beyond ``keep`` of them they are forgotten and made anew."""

    def step(state: np.ndarray, classes: np.ndarray) -> np.ndarray:
        pairs, back = np.unique(state * lazy.nfa.classes.k + classes, return_inverse=True)
        return np.array([lazy.step(*divmod(x, lazy.nfa.classes.k)) for x in pairs.tolist()], np.int64)[back.ravel()]

    out = np.zeros(len(lanes), bool)
    for lo in range(0, len(lanes), 1024):  # subsets are forgotten between groups of lanes
        some = Lanes(lanes.classes, lanes.start[lo : lo + 1024], lanes.length[lo : lo + 1024], lanes.valid[lo : lo + 1024])
        if len(lazy.sets) > keep:
            lazy.__init__(lazy.nfa)
        ends = _lockstep(some, np.zeros(len(some), np.int64), step)
        out[lo : lo + 1024] = [bool(lazy.sets[q] & lazy.nfa.final) for q in ends.tolist()]
    return out


class SetSteps:
    """Moves of sets of NFA states in words of 64 bits: a lookup for each eight states, for all lanes at once."""

    def __init__(self, nfa: Nfa):
        self.words = -(-nfa.size // 64)
        k, groups = nfa.classes.k, -(-nfa.size // 8)
        self.table = np.zeros((k, groups, 256, self.words), np.uint64)
        for g in range(groups):
            for bit in range(min(8, nfa.size - 8 * g)):
                for c in range(k):
                    to = self.pack(nfa.step[8 * g + bit][c])
                    self.table[c, g, np.arange(256) >> bit & 1 == 1] |= to
        self.initial, self.final = self.pack(nfa.initial), self.pack(nfa.final)

    def pack(self, states: int) -> np.ndarray:
        return np.frombuffer(states.to_bytes(8 * self.words, "little"), np.uint64)

    def move(self, sets: np.ndarray, classes: np.ndarray) -> np.ndarray:
        eights = sets.view(np.uint8).reshape(len(sets), -1)
        out = self.table[classes, 0, eights[:, 0]]
        for g in range(1, self.table.shape[1]):
            out |= self.table[classes, g, eights[:, g]]
        return out


def walk_state_sets(lanes: Lanes, sets: SetSteps) -> np.ndarray:
    """Whether each lane is accepted, by simulation with state sets."""
    state = np.broadcast_to(sets.initial, (len(lanes), sets.words)).copy()
    ends = _lockstep(lanes, state, sets.move)
    return (ends & sets.final).any(axis=1)


def halve(lanes: Lanes, delta: np.ndarray, table: np.ndarray, cells: int = 1 << 22) -> np.ndarray:
    """The maps of all lanes by combining neighbours: logarithmically many rounds over the composition table."""
    out = np.zeros(len(lanes), np.int64)
    order = np.argsort(-lanes.length, kind="stable")
    lo = 0
    while lo < len(order) and lanes.length[order[lo]]:
        width = 1 << (int(lanes.length[order[lo]]) - 1).bit_length()
        some = order[lo : lo + max(1, cells // width)]
        column = np.arange(width)
        there = column < lanes.length[some][:, None]
        maps = np.where(there, delta[0, lanes.classes[np.minimum(lanes.start[some][:, None] + column, len(lanes.classes) - 1)]], 0)  # the identity beyond the end
        while maps.shape[1] > 1:
            maps = table[maps[:, ::2], maps[:, 1::2]]
        out[some] = maps[:, 0]
        lo += len(some)
    return out


def match_ends(lanes: Lanes, dfa: Dfa, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lane and position (symbols read) of every prefix after which the state is final, each lane entered in its state."""
    order = np.argsort(-lanes.length, kind="stable")
    state, length, begin = np.asarray(start, np.int64)[order], lanes.length[order], lanes.start[order]
    flat, k = dfa.delta.ravel(), dfa.classes.k
    found: list[tuple[np.ndarray, np.ndarray]] = []
    for t in range(int(length.max(initial=0))):
        active = int(np.searchsorted(-length, -t))
        state[:active] = flat[state[:active] * k + lanes.classes[begin[:active] + t]]
        hit = np.flatnonzero(dfa.final[state[:active]])
        if len(hit):
            found.append((order[hit], np.full(len(hit), t + 1)))
    lane, pos = (np.concatenate([f[i] for f in found]) if found else np.zeros(0, np.int64) for i in (0, 1))
    by = np.lexsort((pos, lane))
    return lane[by], pos[by]


#: Symbols of a lane: longer chunks are walked as several lanes side by side, and their maps composed.
LANE = 4096


def chopped(lanes: Lanes, size: int = LANE) -> tuple[Lanes, np.ndarray]:
    """Lanes of at most ``size`` symbols, in the order of the words, and how many each word has."""
    count = np.maximum(-(-lanes.length // size), 1)
    word = np.repeat(np.arange(len(lanes)), count)
    offset = (np.arange(len(word)) - np.repeat(np.cumsum(count) - count, count)) * size
    return Lanes(lanes.classes, lanes.start[word] + offset, np.minimum(lanes.length[word] - offset, size), lanes.valid[word]), count


def composed(at: np.ndarray, images: list, count: np.ndarray, relational: bool) -> tuple[np.ndarray, list]:
    """The maps of words from those of their lanes, in order: a number for each word, and the images of these numbers."""
    pool = [tuple(i) for i in images]
    known: dict = {}
    for m, image in enumerate(pool):
        known.setdefault(image, m)
    products: dict[tuple[int, int], int] = {}
    out, begin, numbers = np.empty(len(count), np.int64), np.cumsum(count) - count, at.tolist()
    for w, (a, n) in enumerate(zip(begin.tolist(), count.tolist(), strict=True)):
        f = numbers[a]
        for g in numbers[a + 1 : a + n]:
            if (f, g) not in products:
                one, two = pool[f], pool[g]
                image = compose_rel(one, two) if relational else tuple(two[q] for q in one)
                if image not in known:
                    known[image] = len(pool)
                    pool.append(image)
                products[f, g] = known[image]
            f = products[f, g]
        out[w] = f
    used, back = np.unique(out, return_inverse=True)
    return back.ravel(), [list(pool[m]) for m in used.tolist()]


@dataclass
class Scanner:
    """One way to turn chunks into images. kind: maps, relations, halve, lazy, lazy_relations, speculate or merge.

    Maps made on demand are kept from batch to batch and, in a reused worker, from task to task.
    """

    kind: str
    auto: MapAutomaton | None = None
    dfa: Dfa | None = None
    nfa: Nfa | None = None
    table: np.ndarray | None = None
    keep: int = 65_536
    counts: dict = field(default_factory=lambda: {"symbols": 0, "lookups": 0, "maps": 0})
    lazy: LazyMaps | None = None

    @property
    def relational(self) -> bool:
        return self.kind in ("relations", "lazy_relations")

    @property
    def classes(self):
        base = self.dfa if self.dfa is not None else self.nfa if self.nfa is not None else self.auto.base
        return base.classes

    def numbered(self, lanes: Lanes) -> tuple[np.ndarray, list]:
        """A number for each word, and the images of these numbers: lists of states, or of bit masks."""
        if self.kind == "halve" or int(lanes.length.max(initial=0)) <= LANE:
            return self._walked(lanes)
        pieces, count = chopped(lanes)
        return composed(*self._walked(pieces), count, self.relational)

    def _walked(self, lanes: Lanes) -> tuple[np.ndarray, list]:
        n = lanes.symbols()
        self.counts["symbols"] += n
        if self.kind in ("maps", "relations", "halve"):
            self.counts["lookups"] += n
            ends = halve(lanes, self.auto.delta, self.table) if self.kind == "halve" else walk_table(lanes, self.auto.delta)
            used, at = np.unique(ends, return_inverse=True)
            self.counts["maps"] += len(used)
            return at.ravel(), [list(map(int, self.auto.image(m))) for m in used.tolist()]
        if self.kind in ("lazy", "lazy_relations"):
            if self.lazy is None:
                self.lazy = LazyMaps(self.dfa if self.kind == "lazy" else self.nfa, self.keep)
            self.counts["lookups"] += n
            ends = walk_lazy(lanes, self.lazy)
            self.counts["maps"] = self.lazy.made
            used, at = np.unique(ends, return_inverse=True)
            return at.ravel(), [self.lazy.listed(m) for m in used.tolist()]
        if self.kind == "merge":
            found, lookups = walk_merged_states(lanes, self.dfa)
            self.counts["lookups"] += lookups
        else:
            found = walk_all_states(lanes, self.dfa)
            self.counts["lookups"] += n * self.dfa.size
        used, at = np.unique(found, axis=0, return_inverse=True)
        return at.ravel(), used.tolist()

    def images(self, column: pa.Array) -> list:
        """The image of every chunk: a list of states, or of bit masks as whole numbers."""
        at, images = self.numbered(lanes_of(column, self.classes.table, self.classes.unit))
        return [images[i] for i in at.tolist()]
