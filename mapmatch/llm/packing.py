"""Best-fit packing with certified repacking.

Every document becomes token pieces of at most one sequence; full pieces are sequences by themselves. The shorter
pieces are dealt into partitions of bounded size, each packed by best-fit decreasing. Dual-feasible functions give a
lower bound on the bins of a partition: one that meets its bound is certified and done. Partitions with a gap keep
their full bins, pool the documents of their other bins, and are packed again in new company, until a round
certifies all, gains nothing, or ``rounds`` is reached.

Defined results: null or empty text is one piece holding the end id alone; repeated rows are packed once each; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import parts_for, stored, tidied
from .tokens import Encoder

#: Sequence numbers of a packing round: round, partition and bin side by side.
_BIN_BITS, _PART_BITS = 24, 32


def lower_bound(lengths: np.ndarray, capacity: int) -> int:
    """The best of two families of dual-feasible functions, over the histogram of lengths (integer arithmetic).

    Thresholds: lengths above capacity - t count 1, those below t count 0, the rest count as they are.
    Rounding: a length x counts x/capacity where (k+1)x is a multiple of capacity, else floor((k+1)x/capacity)/k.
    """
    if not len(lengths):
        return 0
    count = np.bincount(lengths, minlength=capacity + 1).astype(np.int64)
    size = np.arange(capacity + 1, dtype=np.int64)
    below, mass = np.cumsum(count), np.cumsum(count * size)
    best = -(-int(mass[-1]) // capacity)
    t = np.arange(1, capacity // 2 + 1)
    middle = mass[capacity - t] - mass[t - 1]
    large = below[-1] - below[capacity - t]
    best = max(best, int((large + -(-middle // capacity)).max()))
    for k in range(1, 64):
        scaled = (k + 1) * size
        weight = np.where(scaled % capacity == 0, size * k, scaled // capacity * capacity)  # in units of 1 / (k * capacity)
        best = max(best, -(-int((weight * count).sum()) // (k * capacity)))
    return best


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Bin and offset of every piece, and the number of bins. Bins are found by their room through one bit mask."""
    order = np.argsort(-lengths, kind="stable")
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    mask = used = 0
    for i, n in zip(order.tolist(), lengths[order].tolist(), strict=True):
        fits = mask >> n
        if fits:
            room = n + (fits & -fits).bit_length() - 1
            b = by_room[room].pop()
            if not by_room[room]:
                mask &= ~(1 << room)
        else:
            room, b, used = capacity, used, used + 1
        bins[i], offsets[i] = b, capacity - room
        if room > n:
            by_room[room - n].append(b)
            mask |= 1 << (room - n)
    return bins, offsets, used


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, deal long"
_PIECE_NAMES = [x.split()[0] for x in _PIECES.split(", ")]


def pieces(documents: DataFrame, tokenizer: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """Token pieces of every document, with a number to deal them by that spreads repeated rows too."""

    @tidied
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, seen = Encoder.of(tokenizer), 0
        for batch in batches:
            for lo, hi, ids, edges in encoder.closed(batch.column("text"), end_id):
                size = np.diff(edges)
                n = -(-size // capacity)
                doc = np.repeat(np.arange(hi - lo), n)
                piece = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
                start = piece * capacity
                length = np.minimum(size[doc] - start, capacity)
                at = edges[doc] + start
                crc = [zlib.crc32(ids[a:b]) for a, b in zip(at.tolist(), (at + length).tolist(), strict=True)]
                columns = [batch.column("doc_id").slice(lo, hi - lo).take(pa.array(doc)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(seen + np.arange(len(doc)))]
                seen += len(doc)
                yield pa.RecordBatch.from_arrays(columns, _PIECE_NAMES)

    source = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return source.mapInArrow(cut, _PIECES).withColumn("deal", F.xxhash64(F.spark_partition_id(), "deal"))


def _packer(capacity: int, round_: int):
    base = round_ << (_PART_BITS + _BIN_BITS)

    def pack(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["doc_id", "piece", "deal"], kind="stable")
        lengths = rows["length"].to_numpy()
        bins, offsets, used = best_fit_decreasing(lengths, capacity)
        gap = used > lower_bound(lengths, capacity)
        fill = np.bincount(bins, weights=lengths, minlength=used)
        return rows.drop(columns="part").assign(sequence_id=base | int(key[0]) << _BIN_BITS | bins, offset=offsets, again=gap & (fill[bins] < capacity))

    return pack


def pack(documents: DataFrame, tokenizer: str, capacity: int = 4096, end_id: int = 1, per_partition: int = 50_000, rounds: int = 3) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece."""
    all_pieces = stored(pieces(documents, tokenizer, capacity, end_id), "pieces")
    out = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    full = all_pieces.where(F.col("length") == capacity).withColumn("sequence_id", -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    left = all_pieces.where(F.col("length") < capacity)
    schema = _PIECES + ", sequence_id long, offset long, again boolean"
    done = [full.select(*out)]
    parts = parts_for(left.count(), per_partition)
    for round_ in range(1, rounds + 1):
        dealt = left.select(*_PIECE_NAMES).withColumn("part", F.pmod(F.xxhash64("deal", F.lit(round_)), F.lit(parts)))
        tried = stored(dealt.groupBy("part").applyInPandas(_packer(capacity, round_), schema), "packed")
        best = tried
        if round_ > 1:
            old, new = (x.agg(F.count_distinct("sequence_id")).first()[0] for x in (left, tried))
            best = tried if new < old else left.withColumn("again", F.lit(False))
        if parts == 1 or round_ == rounds or not best.where("again").limit(1).count():
            done.append(best.select(*out))
            break
        done.append(best.where(~F.col("again")).select(*out))
        left = best.where("again").drop("again")
        parts = parts_for(left.count(), per_partition)
    result = done[0]
    for one in done[1:]:
        result = result.unionByName(one)
    return result
