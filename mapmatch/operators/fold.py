"""Folding chunk images into one answer for each word.

Composition is associative but not commutative, so every fold sorts by position first and checks that pieces are
adjacent. Segments are rows word_id, lo, hi, image: the composition of chunks lo to hi. Images of deterministic
automata are arrays of states; relation images are arrays of state arrays in SQL (bit masks stay inside kernels).
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..automata.maps import MapAutomaton

#: Neighbouring segments that a round joins in one row, and rounds: with two, a row gathers at most CELL segments, then
#: at most 2**31 / CELL cells.
CELL, ROUNDS = 1 << 15, 2


def compose(f: Column, g: Column) -> Column:
    """First f, then g, for function images."""
    return F.transform(f, lambda q: F.element_at(g, q + 1))


def compose_relations(f: Column, g: Column) -> Column:
    """First f, then g, for relation images given as arrays of sorted state arrays."""
    return F.transform(f, lambda row: F.array_sort(F.array_distinct(F.flatten(F.transform(row, lambda q: F.element_at(g, q + 1))))))


def _adjacent(parts: Column) -> Column:
    """Whether sorted segments follow each other without gap or overlap."""
    pairs = F.arrays_zip(F.slice(parts, 1, F.size(parts) - 1).alias("a"), F.slice(parts, 2, F.size(parts) - 1).alias("b"))
    return F.forall(pairs, lambda p: p["a"]["hi"] + 1 == p["b"]["lo"])


def _collected(segments: DataFrame, *keys: str, gaps: bool = False) -> DataFrame:
    """keys, parts (sorted segments) and whether any image is null; unless gaps may be, parts not adjacent are an error."""
    parts = segments.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("lo", "hi", "image"))).alias("parts"), F.bool_or(F.col("image").isNull()).alias("none"))
    if gaps:
        return parts
    checked = F.when(_adjacent(F.col("parts")), F.col("parts")).otherwise(F.raise_error(F.lit("chunk gap or overlap")))
    return parts.withColumn("parts", checked)


def _joined(segments: DataFrame, both, *keys: str, gaps: bool = False) -> DataFrame:
    """keys, lo, hi, image: each group's images composed in order; null if one is null."""
    parts = _collected(segments, *keys, gaps=gaps)
    first = F.get("parts", F.lit(0))
    image = F.aggregate(F.slice("parts", 2, F.size("parts")), first["image"], lambda f, p: both(f, p["image"]))
    return parts.select(*keys, first["lo"].alias("lo"), F.element_at("parts", -1)["hi"].alias("hi"), F.when(~F.col("none"), image).alias("image"))


def _cells(segments: DataFrame, both, width: int, gaps: bool = False) -> DataFrame:
    """Segments of each cell of ``width`` chunks joined; a segment belongs to the cell in which it begins."""
    return _joined(segments.withColumn("cell", F.floor(F.col("lo") / width)), both, "word_id", "cell", gaps=gaps).drop("cell")


def _rounds(segments: DataFrame, both, fanout: int, rounds: int, gaps: bool = False) -> DataFrame:
    """All rounds but the last: no row gathers more than ``fanout`` neighbours of the round before."""
    for i in range(1, rounds):
        segments = _cells(segments, both, fanout**i, gaps)
    return segments


def fold_tree(segments: DataFrame, fanout: int = CELL, rounds: int = ROUNDS) -> DataFrame:
    """word_id, lo, hi, image: composition in rounds of neighbours; the last round joins what is left of a word."""
    return _joined(_rounds(segments, compose, fanout, rounds), compose, "word_id")


def fold_relations_tree(segments: DataFrame, fanout: int = CELL, rounds: int = ROUNDS) -> DataFrame:
    """The same for relation images (arrays of state arrays): boolean matrix products, round by round."""
    return _joined(_rounds(segments, compose_relations, fanout, rounds), compose_relations, "word_id")


def fold_in_order(segments: DataFrame, start: int = 0, fanout: int = CELL, rounds: int = ROUNDS, gaps: bool = False) -> DataFrame:
    """word_id, end_state: the start state carried through all cells of a word in order, a lookup each; null for a null word."""
    parts = _collected(_rounds(segments, compose, fanout, rounds, gaps), "word_id", gaps=gaps)
    end = F.aggregate("parts", F.lit(start), lambda q, p: F.element_at(p["image"], q + 1))
    return parts.select("word_id", F.when(~F.col("none"), end).alias("end_state"))


def _through(states: Column, image: Column) -> Column:
    return F.array_sort(F.array_distinct(F.flatten(F.transform(states, lambda q: F.element_at(image, q + 1)))))


def fold_relations(segments: DataFrame, initial: list[int], in_order: bool = True, fanout: int = CELL, rounds: int = ROUNDS) -> DataFrame:
    """word_id, end_states: the initial states carried through all cells, or sent once through the tree's product."""
    start = F.array(*[F.lit(q) for q in initial]).cast("array<int>")
    if not in_order:
        return fold_relations_tree(segments, fanout, rounds).select("word_id", F.when(F.col("image").isNotNull(), _through(start, F.col("image"))).alias("end_states"))
    parts = _collected(_rounds(segments, compose_relations, fanout, rounds), "word_id")
    end = F.aggregate("parts", start, lambda states, p: _through(states, p["image"]))
    return parts.select("word_id", F.when(~F.col("none"), end).alias("end_states"))


def check_gaps(chunks: DataFrame) -> DataFrame:
    """word_id, chunk_ix of chunks that do not follow their predecessor."""
    before = F.lag("chunk_ix").over(Window.partitionBy("word_id").orderBy("chunk_ix"))
    return chunks.withColumn("_before", F.coalesce(before, F.lit(-1))).where("chunk_ix <> _before + 1").select("word_id", "chunk_ix")


def carry_in(segments: DataFrame, start: int = 0, cell: int = CELL) -> DataFrame:
    """word_id, lo, entry: the state in which each segment is entered, by an exclusive prefix fold in two passes.

    Cells of ``cell`` chunks are composed, the state is carried over the cells of a word, and then through each cell's own
    segments. ``segments`` is read twice, so it should be written down.
    """
    empty = F.array().cast("array<struct<lo:int,entry:int>>")

    def entries(parts: str, first: Column) -> Column:
        def step(acc: Column, p: Column) -> Column:
            one = F.struct(p["lo"].cast("int").alias("lo"), acc["q"].alias("entry"))
            return F.struct(F.element_at(p["image"], acc["q"] + 1).alias("q"), F.concat(acc["out"], F.array(one)).alias("out"))

        return F.explode(F.aggregate(parts, F.struct(first.cast("int").alias("q"), empty.alias("out")), step, lambda acc: acc["out"]))

    placed = segments.withColumn("cell", F.floor(F.col("lo") / cell))
    whole = _joined(placed, compose, "word_id", "cell")
    entered = _collected(whole, "word_id").select("word_id", entries("parts", F.lit(start)).alias("x")).select("word_id", F.floor(F.col("x.lo") / cell).alias("cell"), F.col("x.entry").alias("first"))
    parts = _collected(placed, "word_id", "cell").join(entered, ["word_id", "cell"])
    return parts.select("word_id", entries("parts", F.col("first")).alias("x")).select("word_id", "x.lo", "x.entry")


def map_images(spark, auto: MapAutomaton) -> DataFrame:
    """map_id, image of a map automaton small enough to keep its images."""
    rows = [(m, [int(q) for q in auto.image(m)]) for m in range(auto.size)]
    return spark.createDataFrame(rows, "map_id int, image array<int>")


def attach_images(maps: DataFrame, auto: MapAutomaton, most: int = 100_000) -> DataFrame:
    """Maps by number joined with their images; the images are broadcast, their number is checked."""
    if auto.size > most:
        raise ValueError("too many maps to broadcast their images")
    return maps.join(F.broadcast(map_images(maps.sparkSession, auto)), "map_id")


class Segments:
    """The segments of one word in any order of arrival: neighbours merge as soon as they touch."""

    def __init__(self, parts: Iterable[tuple[int, int, list[int]]] = ()):
        self.parts: list[tuple[int, int, list[int]]] = []
        for part in parts:
            self.add(*part)

    def add(self, lo: int, hi: int, image: list[int]) -> None:
        at = int(np.searchsorted([p[0] for p in self.parts], lo))
        if (at and self.parts[at - 1][1] >= lo) or (at < len(self.parts) and self.parts[at][0] <= hi):
            raise ValueError("chunk overlap")
        new = (lo, hi, list(image))
        if at < len(self.parts) and self.parts[at][0] == hi + 1:
            right = self.parts.pop(at)
            new = (lo, right[1], [right[2][q] for q in new[2]])
        if at and self.parts[at - 1][1] + 1 == new[0]:
            left = self.parts.pop(at - 1)
            at -= 1
            new = (left[0], new[1], [new[2][q] for q in left[2]])
        self.parts.insert(at, new)

    def complete(self, chunks: int) -> list[int] | None:
        """The image of the whole word once all chunks are in."""
        if len(self.parts) == 1 and self.parts[0][:2] == (0, chunks - 1):
            return self.parts[0][2]
        return None
