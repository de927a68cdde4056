"""Words and chunks as tables. Order lives in columns (chunk_ix, offset), never in the order of rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.shared import reliable


def pack_rows(df: DataFrame, key: str | list[str], order: list[str], symbol: Column, out: str = "word") -> DataFrame:
    """One word for each key: its rows' symbols, in the order of the given columns (which must be total).

    A key's rows meet in one row, so this is for keys of bounded size; ``row_runs`` has no such bound.
    """
    keys = [key] if isinstance(key, str) else key
    item = F.struct(*[F.col(c) for c in order], symbol.alias("_symbol"))
    ordered = F.array_sort(F.collect_list(item))
    return df.groupBy(*keys).agg(F.array_join(F.transform(ordered, lambda x: x["_symbol"]), "").alias(out))


def chunk_words(df: DataFrame, word_id: str, text: str, size: int) -> DataFrame:
    """Pieces of at most ``size`` symbols: word_id, chunk_ix, offset, payload, chunks (their number in the word).

    An empty word is one empty chunk. A null word is one chunk with a null payload.
    """
    n = F.greatest(F.ceil(F.coalesce(F.length(F.col(text)), F.lit(0)) / F.lit(size)), F.lit(1)).cast("int")
    numbered = df.select(F.col(word_id).alias("word_id"), F.col(text).alias("_text"), n.alias("chunks"))
    spread = numbered.withColumn("chunk_ix", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    offset = F.col("chunk_ix").cast("long") * F.lit(size)
    payload = F.substr(F.col("_text"), (offset + 1).cast("int"), F.lit(size))
    return spread.select("word_id", "chunk_ix", offset.alias("offset"), payload.alias("payload"), "chunks")


def cut_at(df: DataFrame, word_id: str, text: str, cuts: list[int]) -> DataFrame:
    """Pieces between the given positions (any, also repeated or beyond the end: such pieces are empty)."""
    edges = [0, *sorted(cuts)]
    pieces = [F.struct(F.lit(i).alias("chunk_ix"), F.lit(a).cast("long").alias("offset"), F.substr(F.col(text), F.lit(a + 1), (F.lit(b) - F.lit(a)) if b is not None else F.greatest(F.length(F.col(text)) - a, F.lit(0))).alias("payload")) for i, (a, b) in enumerate(zip(edges, [*edges[1:], None], strict=True))]
    spread = df.select(F.col(word_id).alias("word_id"), F.explode(F.array(*pieces)).alias("x"))
    return spread.select("word_id", "x.*", F.lit(len(edges)).alias("chunks"))


_INSIDE = (1 << 33) - 1


def index_rows(df: DataFrame, order: list[str], out: str = "i", parts: int | None = None, size: int = 1) -> DataFrame:
    """Number all rows from 0 in a total order without sorting them in one task, and their pieces of at most ``size`` rows.

    Rows are dealt into sorted ranges of the order and written down; their places inside a range are raised by the counts
    of the ranges before. Only the counts (a row a range) meet in one place, and rows move once. Pieces (column _piece)
    begin anew with every range.
    """
    spark = df.sparkSession
    n = parts or max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))
    # range bounds are sampled anew whenever the plan runs, so the deal is written down before it is used twice
    ranged = reliable(df.repartitionByRange(n, *order).sortWithinPartitions(*order))
    place = F.monotonically_increasing_id()  # range by range: the number of the range, then the place inside
    inside = ranged.withColumn("_at", place).select("*", F.shiftright("_at", 33).cast("int").alias("_part"), F.col("_at").bitwiseAND(F.lit(_INSIDE)).alias("_in"))
    counts = ranged.groupBy(F.spark_partition_id().alias("_part")).agg(F.count("*").alias("_n"))
    ahead = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # one row for each range
    before = counts.select("_part", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_before"), F.coalesce(F.sum(F.ceil(F.col("_n") / F.lit(size))).over(ahead), F.lit(0)).alias("_first"))
    found = inside.join(F.broadcast(before), "_part").withColumn(out, (F.col("_in") + F.col("_before")).cast("long"))
    return found.withColumn("_piece", (F.col("_first") + F.floor(F.col("_in") / F.lit(size))).cast("int")).drop("_at", "_part", "_in", "_before", "_first")


def _joined(batch: pa.RecordBatch, cuts: np.ndarray) -> list[str]:
    """The symbols of a batch, joined from cut to cut; null symbols are nothing."""
    symbols = pc.fill_null(batch.column("symbol").cast(pa.string()), "")
    return pc.binary_join(pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), symbols), "").to_pylist()


def pack_one(df: DataFrame, symbol: Column, index: str = "i") -> DataFrame:
    """All rows, as index_rows left them, as one word: chunk by chunk, without another shuffle; no task holds the word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []  # chunk, offset, texts of the chunk that is not over yet

        def rows(done: list[list]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([0] * len(done), pa.int64()), pa.array([d[0] for d in done], pa.int32()), pa.array([d[1] for d in done], pa.int64()), pa.array(["".join(d[2]) for d in done], pa.string())], ["word_id", "chunk_ix", "offset", "payload"])

        for batch in batches:
            if not len(batch):
                continue
            piece, at = batch.column("piece").to_numpy(), batch.column("at").to_numpy()
            begin = np.concatenate([[0], np.flatnonzero(np.diff(piece)) + 1])
            done = []
            for a, text in zip(begin.tolist(), _joined(batch, np.append(begin, len(batch))), strict=True):
                if held and held[0] == piece[a]:
                    held[2].append(text)
                else:
                    done += [held] if held else []
                    held = [int(piece[a]), int(at[a]), [text]]
            yield rows(done)
        if held:
            yield rows([held])

    rows = df.select(F.col("_piece").alias("piece"), F.col(index).alias("at"), symbol.alias("symbol"))
    return rows.mapInArrow(run, "word_id long, chunk_ix int, offset long, payload string")


def row_runs(df: DataFrame, key: str, order: list[str], symbol: Column) -> DataFrame:
    """word_id, chunk_ix (ascending, with gaps), payload: the word of every key, in pieces that no task joins.

    Rows are dealt into ranges of key and order, so a key with very many rows lies over several tasks, and each run of its
    rows in a batch is a piece. Null symbols are left out; null is a key of its own.
    """
    named = df.select(F.col(key).alias("word_id"), symbol.alias("symbol"), *[F.col(c).alias(f"_{i}") for i, c in enumerate(order)])
    by = ["word_id", *[f"_{i}" for i in range(len(order))]]
    dealt = named.repartitionByRange(*by).sortWithinPartitions(*by).select("word_id", "symbol")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        first = TaskContext.get().partitionId() << 32
        for n, batch in enumerate(batches):
            if not len(batch):
                continue
            word = pc.dictionary_encode(batch.column("word_id"), null_encoding="encode").indices.to_numpy()
            begin = np.concatenate([[0], np.flatnonzero(np.diff(word)) + 1])
            texts = _joined(batch, np.append(begin, len(batch)))
            yield pa.RecordBatch.from_arrays([batch.column("word_id").take(pa.array(begin)), pa.array([first + n] * len(begin), pa.int64()), pa.array(texts, pa.string())], ["word_id", "chunk_ix", "payload"])

    return dealt.mapInArrow(run, f"word_id {named.schema['word_id'].dataType.simpleString()}, chunk_ix long, payload string")
