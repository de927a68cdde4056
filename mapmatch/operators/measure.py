"""Sizes, costs and accuracy: what the experiments count."""

from __future__ import annotations

import dataclasses
import itertools
import math
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automata import alphabet, maps, nfa, pattern
from ..automata import dfa as dfas
from ..automata.dfa import TooLarge
from .kernels import Lanes, lanes_of, walk_table
from .match import Compiled, accepts_segments, compiled, scan_chunks, with_verdict

#: The size study's caps: deterministic states as published, and maps, above the largest published case (1 001 000).
STUDY_DFA, STUDY_MAPS = 1000, 1_100_000

REPORT = (
    "pattern_id int, family string, status string, nfa_states int, dfa_total int, dfa_live int, maps_total int, maps_live int, over_square boolean, over_cube boolean, "
    "over_fourth boolean, over_10k boolean, build_dfa_s double, build_maps_s double, table_bytes_dense256 long, table_bytes_classed long"
)


def size_report(text: str, mode: str = "full", unit: str = "codepoint", max_dfa: int = STUDY_DFA, max_maps: int = STUDY_MAPS) -> dict:
    """One pattern's sizes and build times; what stopped it is its status: ok, unsupported, dfa_cap or map_cap."""
    out: dict = dict.fromkeys(x.split()[0] for x in REPORT.split(", "))
    out["status"] = "ok"
    try:
        t = time.perf_counter()
        n = nfa.position_nfa(pattern.parse(text, unit, mode), unit)
        out["nfa_states"] = n.size
        d = dfas.minimize(dfas.determinize(n, 8 * max_dfa))
        out |= {"dfa_total": d.size, "dfa_live": d.live, "build_dfa_s": time.perf_counter() - t}
        if d.live > max_dfa:
            raise TooLarge
        t = time.perf_counter()
        m = maps.close_functions(d, max_maps)
        live, size = d.live, m.live
        out |= {"maps_total": m.size, "maps_live": size, "build_maps_s": time.perf_counter() - t, "over_10k": size > 10_000}
        out |= {"over_square": size > live**2, "over_cube": size > live**3, "over_fourth": size > live**4}
        out |= {"table_bytes_dense256": 1024 * m.size, "table_bytes_classed": 4 * m.size * d.classes.k}
    except pattern.Unsupported:
        out["status"] = "unsupported"
    except TooLarge:
        out["status"] = "map_cap" if out["dfa_live"] and out["dfa_live"] <= max_dfa else "dfa_cap"
    return out


def compile_status(text: str, **options) -> str:
    return size_report(text, **options)["status"]


def corpus_sizes(patterns: DataFrame, max_dfa: int = STUDY_DFA, max_maps: int = STUDY_MAPS, parts: int | None = None) -> DataFrame:
    """size_report of every row of pattern_id, family, pattern, mode; patterns are dealt over tasks by a hash."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = [size_report(p, m, max_dfa=max_dfa, max_maps=max_maps) | {"pattern_id": i, "family": f} for i, f, p, m in zip(batch["pattern_id"], batch["family"], batch["pattern"], batch["mode"], strict=True)]
            ints = {c: "Int64" for c in ("nfa_states", "dfa_total", "dfa_live", "maps_total", "maps_live", "table_bytes_dense256", "table_bytes_classed")}
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in REPORT.split(", ")]).astype(ints | dict.fromkeys(("over_square", "over_cube", "over_fourth", "over_10k"), "boolean"))

    n = parts or 4 * patterns.sparkSession.sparkContext.defaultParallelism
    return patterns.select("pattern_id", "family", "pattern", "mode").repartition(n, F.xxhash64("pattern_id")).mapInPandas(run, REPORT)


def size_classes(report: DataFrame) -> DataFrame:
    """By family and in all: patterns used, and how many pass the square, cube and fourth power of their states, or 10 000 maps."""
    used = report.where("status = 'ok'")
    count = lambda c: F.sum(F.col(c).cast("long"))
    share = F.round(100.0 * count("over_square") / F.count("*"), 2)
    return used.rollup("family").agg(F.count("*").alias("used"), count("over_square").alias("over_square"), count("over_cube").alias("over_cube"), count("over_fourth").alias("over_fourth"), count("over_10k").alias("over_10k"), share.alias("over_square_percent"))


def retained(report: DataFrame) -> DataFrame:
    """How many patterns the study keeps, and why it refuses the others."""
    return report.groupBy("status").agg(F.count("*").alias("patterns"))


def bound_log2(kind: str, states: int) -> float:
    """Logarithm of the worst-case size: of a deterministic automaton or of relation maps over an NFA, of maps over a DFA."""
    return {"dfa": float(states), "relations": float(states**2), "functions": states * math.log2(max(states, 1))}[kind]


def syntactic_complexity(text: str, mode: str = "full") -> int:
    """The size of the minimal map automaton of the pattern's language, sink and dead map counted."""
    return compiled(text, mode=mode).maps.size


def met_dfa(c: Compiled, symbols: DataFrame) -> dfas.Dfa | None:
    """The deterministic automaton over those of its symbol classes that a table's one-symbol column holds; None if it holds none.

    The states stay; classes that are not met take the column of one that is, so they lead to no map of their own.
    """
    met = sorted({int(c.dfa.classes.table[ord(r[0])]) for r in symbols.distinct().collect()})
    if not met:
        return None
    columns = [k if k in met else met[0] for k in range(c.dfa.classes.k)]
    return dataclasses.replace(c.dfa, delta=np.ascontiguousarray(c.dfa.delta[:, columns]))


def met_sizes(c: Compiled, symbols: DataFrame) -> tuple[int, int, int, int]:
    """States, live states, maps and live maps (any state but the sink in their image) over the symbols that a table holds."""
    met = met_dfa(c, symbols)
    images = np.arange(c.dfa.size)[None] if met is None else maps.close_functions(met).images
    live = len(images) if c.dfa.sink is None else int((images != c.dfa.sink).any(axis=1).sum())
    return c.dfa.size, c.dfa.live, len(images), live


def complexity_terms(c: Compiled, n: int, p: int) -> list[tuple[str, float]]:
    """Predicted work of every method on a word of n symbols in p chunks, in lookups."""
    big_n, d, log = c.nfa.size, c.dfa.size, max(1.0, math.log2(max(p, 2)))
    return [
        ("nfa", float(big_n * n)),
        ("dfa", float(n)),
        ("speculate_tree", d * n / p + d * log),
        ("speculate_in_order", d * n / p + p),
        ("relations_tree", n / p + big_n**3 * log),
        ("relations_in_order", n / p + big_n * p),
        ("maps_tree", n / p + d * log),
        ("maps_in_order", n / p + p),
    ]


def _touched(delta: np.ndarray, classes: np.ndarray) -> int:
    seen, m = set(), 0
    for k in classes.tolist():
        m = int(delta[m, k])
        seen.add(m)
    return len(seen)


def maps_touched(c: Compiled, classes: np.ndarray) -> int:
    """Distinct map states that one lane visits: the working set, however large the table."""
    return _touched(c.maps.delta, classes)


def states_touched(c: Compiled, classes: np.ndarray) -> int:
    """The same for the deterministic automaton."""
    return _touched(c.dfa.delta, classes)


def fold_work(c: Compiled, p: int, how: str) -> tuple[int, int]:
    """Steps and cells of a fold of p chunks."""
    return (p, p) if how == "in_order" else (p - 1, (p - 1) * c.dfa.size)


def counted(spark: SparkSession, c: Compiled, word: str, size: int, kinds: tuple[str, ...]) -> DataFrame:
    """method, symbols, lookups, chunks, fold_steps, fold_cells: counted while tasks scan and compose one word, not predicted.

    Every method scans the chunks in one task, counts its lookups there, and composes the images pair by pair.
    """
    pieces = [word[i : i + size] for i in range(0, len(word), size)]
    scanners = spark.sparkContext.broadcast({kind: c.scanner(kind) for kind in kinds})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for method, texts in zip(batch["method"], batch["pieces"], strict=True):
                scan = scanners.value[method]
                scan.counts.update(symbols=0, lookups=0)
                images = [np.array(i) for i in scan.images(pa.array(list(texts), pa.string()))]
                steps = cells = 0
                while len(images) > 1:
                    pairs = [(images[i], images[i + 1]) for i in range(0, len(images) - 1, 2)]
                    steps, cells = steps + len(pairs), cells + sum(len(f) for f, _ in pairs)
                    images = [g[f] for f, g in pairs] + images[2 * len(pairs) :]
                yield pd.DataFrame([(method, scan.counts["symbols"], scan.counts["lookups"], len(texts), steps, cells)], columns=["method", "symbols", "lookups", "chunks", "fold_steps", "fold_cells"])

    rows = spark.createDataFrame([(kind, pieces) for kind in kinds], "method string, pieces array<string>")
    return rows.mapInPandas(run, "method string, symbols long, lookups long, chunks long, fold_steps long, fold_cells long")


def relation_reach(spark: SparkSession, states: int, most: int) -> DataFrame:
    """symbols, most_maps: the most relation maps that 1 to ``most`` symbols reach over so many states, of all choices of symbols."""
    every = range(1 << states * states)
    choices = spark.createDataFrame([(n, list(some)) for n in range(1, most + 1) for some in itertools.combinations(every, n)], "symbols int, choice array<int>")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        low = (1 << states) - 1
        for batch in batches:
            sizes = []
            for choice in batch["choice"]:
                classes = alphabet.from_sets({((97 + i, 97 + i),) for i in range(len(choice))})
                step = tuple(tuple(int(m) >> states * q & low for m in choice) + (0,) * (classes.k - len(choice)) for q in range(states))
                machine = nfa.Nfa(tuple(row[: len(choice)] for row in step), 1, 1, dataclasses.replace(classes, ids=tuple(min(i, len(choice) - 1) for i in classes.ids)))
                sizes.append(maps.close_relations(machine).size)
            yield pd.DataFrame({"symbols": batch["symbols"], "n": sizes})

    return choices.mapInPandas(run, "symbols int, n int").groupBy("symbols").agg(F.max("n").alias("most_maps"))


def equivalences(pairs: DataFrame) -> DataFrame:
    """a, b, same, witness: whether two patterns have one language; if not, a shortest word in which they differ."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for a, b in zip(batch["a"], batch["b"], strict=True):
                same, word = dfas.equivalent(compiled(a).dfa, compiled(b).dfa)
                rows.append((a, b, same, None if word is None else "".join(map(chr, word))))
            yield pd.DataFrame(rows, columns=["a", "b", "same", "witness"])

    return pairs.select("a", "b").mapInPandas(run, "a string, b string, same boolean, witness string")


BOUNDS = "pattern string, nfa_states int, dfa_total int, maps_total int, dfa_bound_log2 double, functions_bound_log2 double, relations_bound_log2 double, within boolean"


def bounds(patterns: DataFrame) -> DataFrame:
    """Sizes beside the logarithms of their worst cases: 2**N subsets, D**D function maps, 2**(N*N) relation maps."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for p in batch["pattern"]:
                c = compiled(p)
                n, d, s = c.nfa.size, c.dfa.size, c.maps.size
                most = [bound_log2("dfa", n), bound_log2("functions", d), bound_log2("relations", n)]
                rows.append((p, n, d, s, *(round(x, 6) for x in most), math.log2(c.raw_dfa.size) <= most[0] and math.log2(s) <= min(most[1:]) + 1e-9))
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in BOUNDS.split(", ")])

    return patterns.select("pattern").mapInPandas(run, BOUNDS)


def run_mismatches(df: DataFrame, column: str, p: str | Compiled) -> DataFrame:
    """docs, run_mismatches: words on which the symbol-by-symbol runs of the machines and the table kernel do not all agree."""
    c = compiled(p)
    _ = c.maps
    sent = df.sparkSession.sparkContext.broadcast(c)

    @F.arrow_udf("boolean")
    def differ(word: pa.Array) -> pa.Array:
        one = sent.value
        lanes = lanes_of(word, one.dfa.classes.table, one.unit)
        want = one.dfa.final[walk_table(lanes, one.dfa.delta)]
        cut = [lanes.classes[s : s + n].tolist() for s, n in zip(lanes.start.tolist(), lanes.length.tolist(), strict=True)]
        return pa.array([{one.nfa.accepts(w), one.dfa.accepts(w), one.maps.accepts(w)} != {bool(v)} for w, v in zip(cut, want, strict=True)], pa.bool_(), mask=~lanes.valid)

    return df.select(differ(F.col(column)).alias("bad")).agg(F.count("*").alias("docs"), F.coalesce(F.sum(F.col("bad").cast("long")), F.lit(0)).alias("run_mismatches"))


def scan_rate(c: Compiled, classes: np.ndarray, lanes: int, kind: str = "maps", repeat: int = 3) -> float:
    """Symbols a second of one core over class ids already in memory, cut into equal lanes (median; compiling excluded)."""
    size = len(classes) // lanes
    cut = Lanes(classes, np.arange(lanes) * size, np.full(lanes, size), np.ones(lanes, bool))
    from .kernels import walk_all_states

    run = (lambda: walk_all_states(cut, c.dfa)) if kind == "speculate" else (lambda: walk_table(cut, (c.maps if kind == "maps" else c.dfa).delta))
    _ = c.maps if kind == "maps" else c.dfa
    times = []
    for _ in range(repeat):
        t = time.perf_counter()
        run()
        times.append(time.perf_counter() - t)
    return lanes * size / sorted(times)[len(times) // 2]


def repeated_word(spark: SparkSession, period: str, size: int, chunk: int = 1 << 16) -> DataFrame:
    """One word of about ``size`` symbols as a table of chunks: a period, over and over."""
    times = max(1, chunk // len(period))
    pieces = spark.range(max(1, size // (times * len(period))))
    return pieces.select(F.lit(0).cast("long").alias("word_id"), F.col("id").cast("int").alias("chunk_ix"), F.repeat(F.lit(period), F.lit(times)).alias("payload"))


def _seconds(run, repeat: int) -> float:
    times = []
    for _ in range(repeat):
        t = time.perf_counter()
        run()
        times.append(time.perf_counter() - t)
    return min(times)


def parallel_seconds(pieces: DataFrame, c: Compiled, kind: str, workers: int, repeat: int = 2) -> float:
    """A chunk-parallel run by so many tasks at once, start of the job and fold included, compiling excluded."""
    scanner = c.scanner(kind)
    return _seconds(lambda: accepts_segments(scan_chunks(pieces.coalesce(workers), scanner), c).collect(), repeat)


def sequential_seconds(pieces: DataFrame, c: Compiled, repeat: int = 2) -> float:
    """One task that makes one lookup in the deterministic table for every symbol: what the speed-up is measured against."""
    _ = c.dfa
    return _seconds(lambda: with_verdict(pieces.coalesce(1), "payload", c).agg(F.count_if("accepted")).collect(), repeat)


def scaling(pieces: DataFrame, c: Compiled, workers: list[int], kind: str = "maps") -> list[tuple[int, float, float]]:
    """(workers, seconds, speed-up over the sequential run); the first row, with 0 workers, is the sequential run itself."""
    base = sequential_seconds(pieces, c)
    rows = [(w, parallel_seconds(pieces, c, kind, w)) for w in workers]
    return [(0, base, 1.0), *((w, s, base / s) for w, s in rows)]


def small_inputs(spark: SparkSession, c: Compiled, period: str, sizes: list[int], workers: int = 2) -> tuple[list[tuple[int, float, float]], int | None]:
    """(symbols, sequential seconds, parallel seconds) for growing words, and the least size from which parallel stays ahead."""
    rows = []
    for size in sizes:
        pieces = repeated_word(spark, period, size, min(1 << 16, size // (4 * workers))).cache()
        pieces.count()
        rows.append((size, sequential_seconds(pieces, c, 3), parallel_seconds(pieces, c, "maps", workers, 3)))
        pieces.unpersist()
    ahead = [size for size, a, b in rows if b < a]
    late = [size for size, a, b in rows if b >= a]
    even = [size for size in ahead if not late or size > max(late)]
    return rows, min(even) if even else None


def mismatches(a: DataFrame, b: DataFrame, key: str, column: str = "accepted") -> int:
    """Rows on which two ways of matching differ; 0 is the only right answer."""
    return a.join(b.select(key, F.col(column).alias("_other")), key).where(~F.col(column).eqNullSafe(F.col("_other"))).count()


def summary(hits: DataFrame, by: str) -> DataFrame:
    """Hits by a column: rows, distinct words (exact and estimated)."""
    return hits.groupBy(by).agg(F.count("*").alias("hits"), F.count_distinct("word_id").alias("words"), F.approx_count_distinct("word_id").alias("words_estimated"))


def cube(rows: DataFrame, columns: list[str], measure: Column, name: str = "hits") -> DataFrame:
    return rows.cube(*columns).agg(measure.alias(name))


def top_k(rows: DataFrame, by: str, tie: str, k: int) -> DataFrame:
    """The k rows with the highest value, ties to the smaller key."""
    return rows.orderBy(F.desc(by), F.asc(tie)).limit(k)
