"""Matching as DataFrame operators: whole rows, chunks of long words, pattern sets, positions of match ends.

Filters and column choices belong before these operators: Spark moves none of them below a Python node. The row
plans use Arrow scalar functions, so other columns never leave the JVM.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..automata import dfa as dfas
from ..automata import maps, nfa, pattern
from ..automata.dfa import Dfa
from ..automata.maps import MapAutomaton
from ..automata.nfa import Nfa
from ..sources.shared import drop_stored, stored
from . import chunks, fold, kernels
from .kernels import Scanner, lanes_of, walk_table


@dataclass(frozen=True)
class Compiled:
    """One pattern and the automata made from it, each on first use."""

    text: str
    unit: str = "codepoint"
    mode: str = "full"
    dotall: bool = True
    max_dfa: int = 100_000
    max_maps: int = 1_100_000

    @cached_property
    def nfa(self) -> Nfa:
        return nfa.position_nfa(pattern.parse(self.text, self.unit, self.mode, self.dotall), self.unit)

    @cached_property
    def raw_dfa(self) -> Dfa:
        return dfas.determinize(self.nfa, self.max_dfa)

    @cached_property
    def dfa(self) -> Dfa:
        return dfas.minimize(self.raw_dfa)

    @cached_property
    def maps(self) -> MapAutomaton:
        return maps.close_functions(self.dfa, self.max_maps)

    def maps_up_to(self, most: int) -> MapAutomaton:
        """The maps, if there are at most so many; else TooLarge, at the cost of making that many."""
        if "maps" not in self.__dict__:
            self.__dict__["maps"] = maps.close_functions(self.dfa, min(most, self.max_maps))
        if self.maps.size > most:
            raise dfas.TooLarge(f"more than {most} maps")
        return self.maps

    @cached_property
    def relations(self) -> MapAutomaton:
        return maps.close_relations(self.nfa)

    @cached_property
    def products(self) -> np.ndarray:
        return maps.compose_table(self.maps)

    def scanner(self, kind: str) -> Scanner:
        if kind == "maps":
            return Scanner(kind, auto=self.maps)
        if kind == "halve":
            return Scanner(kind, auto=self.maps, table=self.products)
        if kind == "relations":
            return Scanner(kind, auto=self.relations)
        if kind == "lazy_relations":
            return Scanner(kind, nfa=self.nfa)
        return Scanner(kind, dfa=self.dfa)


def compiled(p: str | Compiled, **options) -> Compiled:
    return p if isinstance(p, Compiled) else Compiled(p, **options)


def _row_udf(table: np.ndarray, unit: str, delta: np.ndarray, final: np.ndarray, spark):
    sent = spark.sparkContext.broadcast((table, np.ascontiguousarray(delta), final))

    @F.arrow_udf("boolean")
    def accepts(word: pa.Array) -> pa.Array:
        classes, steps, finals = sent.value
        lanes = lanes_of(word, classes, unit)
        verdict = finals[walk_table(lanes, steps)]
        return pa.array(verdict, pa.bool_(), mask=~lanes.valid)

    return accepts


def verdict(df: DataFrame, column: str, p: str | Compiled, plan: str = "dfa_rows") -> Column:
    """Whether each word is accepted (null for a null word). plan: dfa_rows or map_rows."""
    c = compiled(p)
    auto = c.maps if plan == "map_rows" else c.dfa
    return _row_udf(c.dfa.classes.table, c.unit, auto.delta, auto.final, df.sparkSession)(F.col(column))


def with_verdict(df: DataFrame, column: str, p: str | Compiled, out: str = "accepted", plan: str = "dfa_rows") -> DataFrame:
    return df.withColumn(out, verdict(df, column, p, plan))


def with_end_state(df: DataFrame, column: str, p: str | Compiled, out: str = "end_state") -> DataFrame:
    """The state of the minimal automaton after each word."""
    c = compiled(p)
    sent = df.sparkSession.sparkContext.broadcast((c.dfa.classes.table, c.dfa.delta))

    @F.arrow_udf("int")
    def end(word: pa.Array) -> pa.Array:
        lanes = lanes_of(word, sent.value[0], c.unit)
        return pa.array(walk_table(lanes, sent.value[1]), pa.int32(), mask=~lanes.valid)

    return df.withColumn(out, end(F.col(column)))


def where_accepts(df: DataFrame, column: str, p: str | Compiled, negate: bool = False) -> DataFrame:
    """The rows whose word is accepted (or, negated, is not); null words are in neither. Cheap necessary conditions come first."""
    from ..plans.planner import prefilter

    c = compiled(p)
    rows = df if negate else df.where(prefilter(c, F.col(column)))
    accepted = verdict(rows, column, c)
    return rows.where(~accepted if negate else accepted)


def _lists(images: list) -> pa.Array:
    """Images, or None, as an Arrow list column."""
    return pa.array(images, pa.list_(pa.int32()))


def scan_chunks(pieces: DataFrame, scanner: Scanner, fold_runs: bool = True) -> DataFrame:
    """word_id, lo, hi, image for runs of neighbouring chunks: scanned alone, then folded inside the task.

    A null payload gives a null image. Relation images come as arrays of sorted state arrays. Without ``fold_runs``
    every chunk keeps a row of its own.
    """
    sent = pieces.sparkSession.sparkContext.broadcast(scanner)
    relational = scanner.relational
    kind = "array<array<int>>" if relational else "array<int>"

    def composed(images: list, numbers: list[int]):
        if relational:
            out = tuple(images[numbers[0]])
            for m in numbers[1:]:
                out = maps.compose_rel(out, tuple(images[m]))
            return [list(nfa.bits(row)) for row in out]
        out = images[numbers[0]]
        for m in numbers[1:]:
            out = images[m][out]
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = sent.value
        for batch in batches:
            if not len(batch):
                continue
            payload = batch.column("payload")
            at, images = scan.numbered(lanes_of(payload, scan.classes.table, scan.classes.unit))
            images = images if relational else [np.array(i, np.int32) for i in images]
            there = np.asarray(payload.is_valid())
            word = pc.dictionary_encode(batch.column("word_id"), null_encoding="encode").indices.to_numpy()
            ix = batch.column("chunk_ix").to_numpy()
            order = np.lexsort((ix, word))
            at, there, word, ix = at[order], there[order], word[order], ix[order]
            follows = (word[1:] == word[:-1]) & (ix[1:] == ix[:-1] + 1) & there[1:] & there[:-1] & fold_runs
            lo = np.flatnonzero(np.concatenate([[True], ~follows]))
            hi = np.append(lo[1:], len(order))
            alone = [composed(images, [m]) for m in range(len(images))]
            rows = [(alone[at[a]] if b - a == 1 else composed(images, at[a:b].tolist())) if there[a] else None for a, b in zip(lo.tolist(), hi.tolist(), strict=True)]
            found = pa.array(rows, pa.list_(pa.list_(pa.int32()))) if relational else _lists(rows)
            yield pa.RecordBatch.from_arrays([batch.column("word_id").take(pa.array(order[lo])), batch.column("chunk_ix").take(pa.array(order[lo])), batch.column("chunk_ix").take(pa.array(order[hi - 1])), found], ["word_id", "lo", "hi", "image"])

    word_type, ix_type = (pieces.schema[c].dataType.simpleString() for c in ("word_id", "chunk_ix"))
    return pieces.select("word_id", "chunk_ix", "payload").mapInArrow(run, f"word_id {word_type}, lo {ix_type}, hi {ix_type}, image {kind}")


def scan_map_ids(pieces: DataFrame, auto: MapAutomaton) -> DataFrame:
    """word_id, chunk_ix, map_id of every chunk, by the numbers of one compiled map automaton."""
    sent = pieces.sparkSession.sparkContext.broadcast((auto.base.classes.table, auto.delta))
    unit = auto.base.classes.unit

    @F.arrow_udf("int")
    def walk(word: pa.Array) -> pa.Array:
        lanes = lanes_of(word, sent.value[0], unit)
        return pa.array(walk_table(lanes, sent.value[1]), pa.int32(), mask=~lanes.valid)

    return pieces.select("word_id", "chunk_ix", walk("payload").alias("map_id"))


def accepts_segments(segments: DataFrame, c: Compiled, how: str = "in_order", relational: bool = False, fanout: int = fold.CELL, rounds: int = fold.ROUNDS) -> DataFrame:
    """word_id, accepted (null for a word with a null payload) from scanned segments, which are read once. how: in_order or tree."""
    if relational:
        finals = F.array(*[F.lit(q) for q in nfa.bits(c.nfa.final)]).cast("array<int>")
        ends = fold.fold_relations(segments, list(nfa.bits(c.nfa.initial)), how == "in_order", fanout, rounds)
        return ends.select("word_id", F.when(F.col("end_states").isNotNull(), F.arrays_overlap("end_states", finals)).alias("accepted"))
    if how == "in_order":
        state = fold.fold_in_order(segments, 0, fanout, rounds)
    else:
        state = fold.fold_tree(segments, fanout, rounds).select("word_id", F.element_at("image", 1).alias("end_state"))
    if c.dfa.size <= 4096:
        final = F.array(*[F.lit(bool(x)) for x in c.dfa.final])
        return state.select("word_id", F.when(F.col("end_state").isNotNull(), F.element_at(final, F.col("end_state") + 1)).alias("accepted"))
    names = state.sparkSession.createDataFrame([(int(q),) for q in np.flatnonzero(c.dfa.final)], "end_state int")
    found = state.join(F.broadcast(names.withColumn("is_final", F.lit(True))), "end_state", "left")  # a row a state at most
    return found.select("word_id", F.when(F.col("end_state").isNotNull(), F.coalesce("is_final", F.lit(False))).alias("accepted"))


def accepts_chunked(df: DataFrame, word_id: str, text: str, p: str | Compiled, size: int = 65_536, how: str = "in_order", kind: str = "auto", fanout: int = fold.CELL, rounds: int = fold.ROUNDS, longest: int | None = None) -> DataFrame:
    """word_id, accepted for every word, cut into chunks that are scanned independently.

    kind: auto, maps, lazy, speculate, merge, halve, relations, lazy_relations. The answer is the same for all kinds, folds
    and sizes. ``auto`` lets the planner choose by the sizes of the automata and, if given, of the longest word.
    """
    from ..plans.planner import choose

    c = compiled(p)
    if kind == "auto":
        kind = choose(c, longest).plan
        if kind == "rows":
            return with_verdict(df.select(F.col(word_id).alias("word_id"), F.col(text).alias("_w")), "_w", c).select("word_id", "accepted")
    scanner = c.scanner(kind)
    segments = scan_chunks(chunks.chunk_words(df, word_id, text, size), scanner)
    return accepts_segments(segments, c, how, scanner.relational, fanout, rounds)


#: Tasks whose pieces of one word are composed in one row before the last round (a word of rows).
_TASKS = 1 << 10


def accepts_rows(df: DataFrame, key: str, order: list[str], symbol: Column, p: str | Compiled) -> DataFrame:
    """key, accepted for the word that each key's rows make, in a total order. Rows move once; no task joins a whole word."""
    from ..plans.planner import choose

    c = compiled(p)
    segments = scan_chunks(chunks.row_runs(df, key, order, symbol), c.scanner(choose(c, deterministic=True).plan))
    state = fold.fold_in_order(segments, 0, _TASKS << 32, gaps=True)
    final = F.array(*[F.lit(bool(x)) for x in c.dfa.final])
    return state.select(F.col("word_id").alias(key), F.element_at(final, F.col("end_state") + 1).alias("accepted"))


#: Symbols by which the shared automaton of a set of texts knows each of them; the rest of a text is compared directly.
DEPTH = 24


class TextSet:
    """One automaton for many texts: a table over their beginnings in which a failed match goes on with the longest one left.

    States in which a text's beginning has just been read have the highest numbers, so a step looks for them with one
    comparison. What is met is compared with the whole text.
    """

    def __init__(self, texts: list[tuple[int, str]], depth: int = DEPTH):
        self.codes = [np.frombuffer(t.encode("utf-32-le", "surrogatepass"), np.uint32) for _, t in texts]
        self.names = [i for i, _ in texts]
        self.longest = max(map(len, self.codes), default=0)
        self.used = np.unique(np.concatenate([np.zeros(0, np.uint32), *(c[:depth] for c in self.codes)]))
        k = len(self.used) + 1  # the last class is for symbols in no beginning
        children: list[dict[int, int]] = [{}]
        own: list[list[int]] = [[]]
        for n, codes in enumerate(self.codes):
            at = 0
            for c in np.searchsorted(self.used, codes[:depth]).tolist():
                if c not in children[at]:
                    children[at][c] = len(children)
                    children.append({})
                    own.append([])
                at = children[at][c]
            own[at].append(n)
        delta, fail, ends, order = np.zeros((len(children), k), np.int32), [0] * len(children), [list(x) for x in own], [0]
        for q in order:
            delta[q] = delta[fail[q]] if q else 0
            for c, to in children[q].items():
                fail[to] = int(delta[q, c]) if q else 0
                ends[to] = ends[to] + ends[fail[to]]
                order.append(to)
                delta[q, c] = to
        rank = np.empty(len(children), np.int32)
        by = sorted(range(len(children)), key=lambda q: bool(ends[q]))
        rank[by] = np.arange(len(by))
        self.delta, self.first = rank[delta][by], sum(not e for e in ends)
        self.start, self.ends = int(rank[0]), [ends[q] for q in by[self.first :]]
        self.depth = depth

    def find(self, column: pa.Array, size: int = 4096) -> list[list[int]]:
        """The names of the texts that each word holds."""
        at, data = kernels._buffers(column)
        data = data[at[0] : at[-1]]
        heads = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
        at = heads[at - at[0]]
        codes = np.frombuffer(data.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32)
        place = np.minimum(np.searchsorted(self.used, codes), len(self.used) - 1)
        classes = np.where(self.used[place] == codes, place, len(self.used)).astype(np.uint16) if len(self.used) else np.zeros(len(codes), np.uint16)
        length = np.where(np.asarray(column.is_valid()), np.diff(at), 0)
        pieces = np.maximum(-(-length // size), 1)
        word = np.repeat(np.arange(len(column)), pieces)
        offset = (np.arange(len(word)) - np.repeat(np.cumsum(pieces) - pieces, pieces)) * size
        begin = at[:-1][word] + offset
        reach = np.minimum(length[word] - offset, size + self.depth - 1)
        order = np.argsort(-reach, kind="stable")
        word, begin, reach = word[order], begin[order], reach[order]
        k, flat = self.delta.shape[1], (self.delta * self.delta.shape[1]).ravel().astype(np.intp)
        state, found = np.full(len(order), self.start * k, np.intp), set()
        low = self.first * k
        if not low:  # the empty text
            found.update((int(w), n) for w in range(len(column)) for n in self.ends[self.start - self.first])
        t = 0
        while active := int(np.searchsorted(-reach, -t)):
            steps = min(int(reach[active - 1]) - t, 256)
            rows = np.lib.stride_tricks.sliding_window_view(classes, steps)[begin[:active] + t]
            s, cell = state[:active], np.empty(active, np.intp)
            for i, symbols in enumerate(np.ascontiguousarray(rows.T)):
                np.add(s, symbols, out=cell)
                np.take(flat, cell, out=s, mode="clip")
                if s.max() >= low:
                    for lane in np.flatnonzero(s >= low).tolist():
                        w, stop = int(word[lane]), int(begin[lane]) + t + i + 1
                        for n in self.ends[s[lane] // k - self.first]:
                            if (w, n) not in found and self._is_at(codes, stop, int(at[w + 1]), n):
                                found.add((w, n))
            t += steps
        out: list[list[int]] = [[] for _ in range(len(column))]
        for w, n in sorted(found):
            if column[w].is_valid:
                out[w].append(self.names[n])
        return out

    def _is_at(self, codes: np.ndarray, stop: int, end: int, n: int) -> bool:
        text = self.codes[n]
        begin = stop - min(len(text), self.depth)
        return begin + len(text) <= end and bool((codes[begin : begin + len(text)] == text).all())


def match_corpus(df: DataFrame, word_id: str, text: str, patterns: list[tuple[int, str]], mode: str = "full", cells: int = 8_000_000) -> DataFrame:
    """word_id, pattern_id of every hit: all patterns in one pass over the words.

    Patterns that look for a text anywhere share one automaton (or several, of at most ``cells`` cells each, walked one
    after another in the same task). The tables of all others are stacked over shared symbol classes and a word is a lane
    for each of them; words that lack a text which the pattern requires are ruled out before the walk.
    """
    from ..automata.alphabet import from_sets, sets_of
    from ..plans.planner import contained_text, required_literal

    trees = [(i, pattern.parse(p, mode=mode)) for i, p in patterns]
    texts = [(i, t) for i, tree in trees if (t := contained_text(tree)) is not None]
    named = {i for i, _ in texts}
    trees = [(i, tree) for i, tree in trees if i not in named]
    alphabet = len({c for _, t in texts for c in t[:DEPTH]}) + 1
    each = max(1, cells // (DEPTH * alphabet))
    sets = [TextSet(texts[at : at + each]) for at in range(0, len(texts), each)]
    classes = from_sets(set().union(*(sets_of(t) for _, t in trees)))
    stacks, now, size = [], [], 0
    for i, tree in trees:
        d = dfas.minimize(dfas.determinize(nfa.position_nfa(tree)))
        own = [d.classes.table[next(lo for lo, _, c in classes.rows() if c == j)] for j in range(classes.k)]
        delta = d.delta[:, own]
        if now and (size + len(delta)) * classes.k > cells:
            stacks.append(now)
            now, size = [], 0
        now.append((i, delta, d.final, size, required_literal(tree)))
        size += len(delta)
    stacks.append(now)
    packed = [(np.concatenate([t + at for _, t, _, at, _ in s]).astype(np.int32), np.concatenate([x[2] for x in s]), [(x[0], x[3], x[4]) for x in s]) for s in stacks if s]
    sent = df.sparkSession.sparkContext.broadcast((classes.table, packed, sets))

    @F.arrow_udf("array<int>")
    def hits(word: pa.Array) -> pa.Array:
        table, tables, shared = sent.value
        found: list[list[int]] = [[] for _ in range(len(word))]
        for one in shared:
            for row, names in enumerate(one.find(word)):
                found[row] += names
        lanes = lanes_of(word, table, "codepoint") if tables else None
        for delta, final, members in tables:
            for name, start, literal in members:
                maybe = np.flatnonzero(pc.fill_null(pc.match_substring(word, literal), False).to_numpy(zero_copy_only=False)) if literal else np.flatnonzero(lanes.valid)
                some = kernels.Lanes(lanes.classes, lanes.start[maybe], lanes.length[maybe], lanes.valid[maybe])
                for row in maybe[final[walk_table(some, delta, start)]].tolist():
                    found[row].append(name)
        return pa.array(found, pa.list_(pa.int32()))

    return df.select(F.col(word_id).alias("word_id"), F.explode(hits(F.col(text))).alias("pattern_id"))


def match_texts(df: DataFrame, word_id: str, text: str, texts: DataFrame, name: str, needle: str, block: int = 5000) -> DataFrame:
    """word_id and name of every text of a table that a word holds. Texts come to the driver a block at a time; each block is one pass."""
    from ..plans.corpora import contains_all

    out, held = None, []

    def passed(some: list[tuple[int, str]]) -> DataFrame:
        hits = match_corpus(df, word_id, text, contains_all([(i, t) for i, (_, t) in enumerate(some)]))
        names = df.sparkSession.createDataFrame([(i, n) for i, (n, _) in enumerate(some)], f"pattern_id int, {name} {texts.schema[name].dataType.simpleString()}")
        return hits.join(F.broadcast(names), "pattern_id").select("word_id", name)  # ``block`` rows at most

    for row in texts.where(F.col(needle).isNotNull()).select(name, needle).toLocalIterator():
        held.append((row[0], row[1]))
        if len(held) == block:
            out, held = passed(held) if out is None else out.unionByName(passed(held)), []
    if held or out is None:
        out = passed(held) if out is None else out.unionByName(passed(held))
    return out


def any_hit(df: DataFrame, word_id: str, hits: DataFrame) -> DataFrame:
    return df.join(hits.select(F.col("word_id").alias(word_id)).distinct(), word_id, "left_semi")


def no_hit(df: DataFrame, word_id: str, hits: DataFrame) -> DataFrame:
    return df.join(hits.select(F.col("word_id").alias(word_id)).distinct(), word_id, "left_anti")


def combine(a: DataFrame, b: DataFrame, op: str) -> DataFrame:
    """Union, intersection or difference of two sets of hits."""
    return {"union": lambda: a.unionByName(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.exceptAll(b).distinct()}[op]()


#: Chunks whose entry states are broadcast to the second scan (some 30 bytes each); beyond it the chunks are shuffled to them.
BROADCAST_ENTRIES = 1_000_000


def ends(df: DataFrame, word_id: str, text: str, p: str | Compiled, size: int = 65_536, kind: str = "auto") -> DataFrame:
    """word_id, pos: how many symbols were read at each accepting prefix, from two scans of the chunks.

    The first scan gives every chunk's entry state by an exclusive fold; the second walks each chunk from there. With
    chunks large enough that their number stays below BROADCAST_ENTRIES, no text is shuffled.
    """
    from ..plans.planner import choose

    c = compiled(p)
    pieces = chunks.chunk_words(df, word_id, text, size).where("payload IS NOT NULL")
    scanner = c.scanner(choose(c, deterministic=True).plan if kind == "auto" else kind)
    segments = stored(scan_chunks(pieces, scanner, fold_runs=False), "segments")
    entry = stored(fold.carry_in(segments), "entries")
    drop_stored(segments)
    few = entry.count() <= BROADCAST_ENTRIES
    sent = df.sparkSession.sparkContext.broadcast(c.dfa)

    @F.arrow_udf("array<long>")
    def walk(payload: pa.Array, state: pa.Array) -> pa.Array:
        d = sent.value
        lane, pos = kernels.match_ends(lanes_of(payload, d.classes.table, d.classes.unit), d, state.to_numpy(zero_copy_only=False))
        return pa.ListArray.from_arrays(pa.array(np.searchsorted(lane, np.arange(len(payload) + 1)), pa.int32()), pa.array(pos, pa.int64()))

    entry = entry.withColumnRenamed("lo", "chunk_ix")
    entered = pieces.join(F.broadcast(entry) if few else entry, ["word_id", "chunk_ix"])
    return entered.select("word_id", F.col("offset").alias("_o"), F.explode(walk("payload", "entry")).alias("_p")).select("word_id", (F.col("_o") + F.col("_p")).alias("pos"))


def count_ends(df: DataFrame, word_id: str, text: str, p: str | Compiled, size: int = 65_536) -> DataFrame:
    """word_id, n_ends for every word, none included."""
    n = ends(df, word_id, text, p, size).groupBy("word_id").agg(F.count("*").alias("n"))
    return df.select(F.col(word_id).alias("word_id")).join(n, "word_id", "left").select("word_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_ends"))


def _class_of(c: Dfa, symbol: Column) -> Column:
    code, out = F.ascii(symbol), F.lit(c.classes.ids[-1])
    for lo, hi, k in c.classes.rows():
        out = F.when(code.between(lo, hi), F.lit(k)).otherwise(out)
    return out


def accepts_expression(column: Column, p: str | Compiled) -> Column:
    """The sequential run as a plain SQL expression, without Python: for small automata."""
    c = compiled(p).dfa
    steps = F.array(*[F.lit(int(x)) for x in c.delta.ravel()])
    final = F.array(*[F.lit(bool(x)) for x in c.final])
    symbols = F.filter(F.split(column, ""), lambda s: s != "")
    end = F.aggregate(F.transform(symbols, lambda s: _class_of(c, s)), F.lit(0), lambda q, k: F.element_at(steps, q * c.classes.k + k + 1))
    return F.when(column.isNotNull(), F.element_at(final, end + 1))
