"""What the map automaton is compared with. All give the same verdicts at other costs."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..automata.dfa import LazySubset
from . import match
from .kernels import SetSteps, lanes_of, walk_lazy_subsets, walk_state_sets
from .match import Compiled, compiled


def nfa_sets(df: DataFrame, column: str, p: str | Compiled, out: str = "accepted") -> DataFrame:
    """Simulation of the nondeterministic automaton with state sets: up to N successors a symbol."""
    c = compiled(p)
    sent = df.sparkSession.sparkContext.broadcast((c.nfa.classes, SetSteps(c.nfa)))

    @F.arrow_udf("boolean")
    def accepts(word: pa.Array) -> pa.Array:
        classes, sets = sent.value
        lanes = lanes_of(word, classes.table, classes.unit)
        return pa.array(walk_state_sets(lanes, sets), pa.bool_(), mask=~lanes.valid)

    return df.withColumn(out, accepts(F.col(column)))


def lazy_subset_rows(df: DataFrame, column: str, p: str | Compiled, out: str = "accepted") -> DataFrame:
    """The sequential run with subsets made as words meet them, for automata whose subsets are too many to make beforehand."""
    sent = df.sparkSession.sparkContext.broadcast(compiled(p).nfa)

    @F.arrow_udf("boolean")
    def accepts(word: pa.Array) -> pa.Array:
        n = sent.value
        lanes = lanes_of(word, n.classes.table, n.classes.unit)
        return pa.array(walk_lazy_subsets(lanes, LazySubset(n)), pa.bool_(), mask=~lanes.valid)

    return df.withColumn(out, accepts(F.col(column)))


def dfa_rows(df: DataFrame, column: str, p: str | Compiled, out: str = "accepted") -> DataFrame:
    """The sequential table-driven automaton, a row a lane; a giant word runs in one task."""
    return match.with_verdict(df, column, p, out, "dfa_rows")


def query_parallel(df: DataFrame, column: str, p: str | Compiled, parts: int, out: str = "accepted") -> DataFrame:
    """Parallel over rows only: rows are dealt out, each still runs sequentially, so the longest row decides."""
    return match.with_verdict(df.repartition(parts), column, p, out, "dfa_rows")


def all_states(df: DataFrame, word_id: str, text: str, p: str | Compiled, size: int = 65_536, how: str = "tree", dedupe: bool = False) -> DataFrame:
    """Speculation: every chunk carries the destination of each state; fold by tree or in order."""
    return match.accepts_chunked(df, word_id, text, p, size, how, "merge" if dedupe else "speculate")


def spark_rlike(column: Column, p: str, mode: str = "full") -> Column:
    """The engine's own backtracking expressions, as a yardstick."""
    return column.rlike(f"(?s)\\A(?:{p})\\z" if mode == "full" else f"(?s){p}")
