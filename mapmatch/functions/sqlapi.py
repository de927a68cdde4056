"""SQL functions: verdicts, maps, ordered composition, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.kernels import lanes_of, match_ends, walk_table
from ..operators.match import Compiled, compiled


def accepts_function(p: str | Compiled):
    """A scalar function text -> boolean."""
    c = compiled(p)
    table, unit, delta, final = c.dfa.classes.table, c.unit, c.dfa.delta, c.dfa.final

    @F.arrow_udf("boolean")
    def automaton_accepts(word: pa.Array) -> pa.Array:
        lanes = lanes_of(word, table, unit)
        return pa.array(final[walk_table(lanes, delta)], pa.bool_(), mask=~lanes.valid)

    return automaton_accepts


def map_function(p: str | Compiled):
    """A scalar function text -> array<int>: the image of the word's map, one entry a state."""
    scanner = compiled(p).scanner("maps")

    @F.arrow_udf("array<int>")
    def automaton_map(word: pa.Array) -> pa.Array:
        found = [i if v else None for i, v in zip(scanner.images(word), word.is_valid().to_pylist(), strict=True)]
        return pa.array(found, pa.list_(pa.int32()))

    return automaton_map


@F.arrow_udf(T.ArrayType(T.IntegerType()))
def compose_group(ix: pa.Array, image: pa.Array) -> list[int]:
    """Aggregate: the images of a group composed in the order of ix. For partial steps fold segments first."""
    order = sorted(zip(ix.to_pylist(), image.to_pylist(), strict=True))
    out = order[0][1]
    for _, g in order[1:]:
        out = [g[q] for q in out]
    return out


def compose_ordered(ix: Column, image: Column) -> Column:
    """The same aggregate out of built-in functions."""
    parts = F.array_sort(F.collect_list(F.struct(ix.alias("ix"), image.alias("image"))))
    return F.aggregate(F.slice(parts, 2, F.size(parts)), F.get(parts, F.lit(0))["image"], lambda f, p: F.transform(f, lambda q: F.element_at(p["image"], q + 1)))


@F.udtf(returnType="map_id int, image array<int>, final boolean")
class CompilePattern:
    """compile_pattern(p): the maps of a pattern as rows."""

    def eval(self, p: str) -> Iterator[tuple]:
        auto = Compiled(p).maps
        for m in range(auto.size):
            yield m, [int(q) for q in auto.image(m)], bool(auto.final[m])


@F.udtf(returnType="pos long")
class MatchEnds:
    """match_ends(text, p): how many symbols were read at each accepting prefix."""

    def eval(self, text: str, p: str) -> Iterator[tuple]:
        import numpy as np

        d = Compiled(p).dfa
        lanes = lanes_of(pa.array([text or ""]), d.classes.table, "codepoint")
        for pos in match_ends(lanes, d, np.zeros(1, np.int32))[1].tolist():
            yield (pos,)


def register(spark: SparkSession, named: dict[str, str]) -> None:
    """Register <name>_accepts and <name>_map for every named pattern, and the table functions."""
    for name, p in named.items():
        spark.udf.register(f"{name}_accepts", accepts_function(p))
        spark.udf.register(f"{name}_map", map_function(p))
    spark.udtf.register("compile_pattern", CompilePattern)
    spark.udtf.register("match_ends", MatchEnds)
