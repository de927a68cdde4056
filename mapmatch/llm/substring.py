"""Exact substring deduplication with fixed-block anchors.

A repeat is a run of at least ``window`` words that also occurs in a document with a smaller id. Each document is cut
into reference blocks of half a window, without overlap; any run of a whole window holds one of them entire. The blocks
are the index: every rolling window of block length in every document probes it, and the blocks and probes that meet are
the anchors. Around each anchor the run can only begin within half a window, so the hits are extended there: the full
windows that hold an anchor are hashed (96 bits), and a window whose hash also begins in a document with a smaller id
marks its words. Neighbouring marked windows join into maximal repeats.

Blocks and probes are dealt by segments of the hash space and meet there, segment by segment: the number of segments grows
with the text, what one segment holds does not, and nothing that grows with the text is broadcast or sent to the driver.
A probe travels as eight bytes: 32 more bits of its hash (a wrong meeting costs a needless candidate, nothing else) and
its place in a batch of documents; what a batch holds several times travels once. What is hit goes back to its batch's list
of documents, and so to the text.

The text is dealt once, by document, into a bucketed table; copies, anchors and marks are joined to it where it lies.
Documents with the same whole text are settled before all this: all but the one with the smallest id repeat it entirely,
so they give neither blocks nor probes.

Defined results: null text has no words; documents with a null id neither remove nor lose words; rows that share an
id never remove each other's words; words removed are judged on the input alone; other columns are ignored. Rows alike in
id and text lie in one bucket.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_folder, drop_stored, parts_for, shared_folder, stored, text_slices, tidied

#: Words of a window; reference blocks of a segment; bytes of text in a bucket.
WINDOW, SEGMENT_BLOCKS, BUCKET_BYTES = 50, 100_000, 64 << 20
_BASES = (np.uint64(0x9E3779B97F4A7C15 | 1), np.uint64(0xD6E8FEB86659FD93 | 1))
_ALIGNED = np.uint32(1 << 31)


def _inverse(x: np.uint64) -> np.uint64:
    return np.uint64(pow(int(x), -1, 1 << 64))


class _Powers:
    """Powers of the rolling-hash bases and of their inverses, grown on demand."""

    def __init__(self):
        self.table = [(np.ones(1, np.uint64), np.ones(1, np.uint64)) for _ in _BASES]

    def of(self, n: int, which: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.table[which][0]) < n:
            grow = max(n, 2 * len(self.table[which][0]))
            self.table[which] = tuple(np.cumprod(np.concatenate([[np.uint64(1)], np.full(grow - 1, x, np.uint64)])) for x in (_BASES[which], _inverse(_BASES[which])))
        return self.table[which][0][:n], self.table[which][1][:n]


_POWERS = _Powers()


def _split(texts: pa.Array) -> tuple[pa.StringArray, np.ndarray]:
    """All words of a slice of texts, and the edges of the texts among them."""
    words = pc.ascii_split_whitespace(pc.fill_null(texts.cast(pa.string()), ""))
    flat, offsets = words.flatten(), words.offsets.to_numpy().astype(np.int64)
    offsets = offsets - offsets[0]
    there = pc.greater(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False)
    edges = np.concatenate([[0], np.cumsum(there)])[offsets]
    return flat.filter(pa.array(there)), edges


def _hashed(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The edges of the texts of a slice among all its words, and a hash of every word."""
    flat, edges = _split(texts)
    coded = pc.dictionary_encode(flat)
    hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
    return edges, hashes[coded.indices.to_numpy()] if len(flat) else np.zeros(0, np.uint64)


def rolling(hashes: np.ndarray, length: int, which: int = 0) -> np.ndarray:
    """A hash of every run of ``length`` words, by position."""
    n = len(hashes) - length + 1
    if n < 1:
        return np.zeros(0, np.uint64)
    up, down = _POWERS.of(len(hashes), which)
    sums = np.concatenate([[np.uint64(0)], np.cumsum(hashes * up)])
    out = (sums[length:] - sums[:-length]) * down[:n]
    out ^= out >> np.uint64(32)
    out *= np.uint64(0xD6E8FEB86659FD93)
    return out ^ (out >> np.uint64(29))


_GATHERED = "segment int, batch long, keys binary, places binary, doc_ids binary, tags binary, starts binary"
_NAMES = [x.split()[0] for x in _GATHERED.split(", ")]


def _blocks_and_probes(docs: DataFrame, block: int, segments: int) -> DataFrame:
    """For each batch of documents and segment the hashes of all runs of ``block`` words, blocks marked; and a row with the batch's documents.

    A run that a batch holds several times travels once, with one of its places; all its places count as met at once. So a
    passage that very many documents share weighs on its segment by the number of batches. docs: doc_id, tag, text, all known.
    """

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        serial = TaskContext.get().partitionId() << 32
        for batch in batches:
            for lo, hi in text_slices(batch.column("text")):
                edges, hashes = _hashed(batch.column("text").slice(lo, hi - lo))
                runs = rolling(hashes, block)
                size = np.diff(edges)
                place = np.arange(len(runs))
                inside = place - np.repeat(edges[:-1], size)[: len(runs)]
                whole = inside + block <= np.repeat(size, size)[: len(runs)]
                runs, place, inside = runs[whole], place[whole].astype(np.uint32), inside[whole]
                if not len(runs):
                    continue
                place[inside % block == 0] |= _ALIGNED
                order = np.argsort(runs, kind="stable")
                runs, place = runs[order], place[order].astype("<u4")
                first = np.flatnonzero(np.concatenate([[True], runs[1:] != runs[:-1]]))
                times = np.diff(np.append(first, len(runs)))
                again = np.repeat(times > 1, times)
                aligned = np.maximum.reduceat(place & _ALIGNED, first)
                distinct, own = runs[first], (place[first] | aligned).astype("<u4")
                segment = (distinct >> np.uint64(32)) * np.uint64(segments) >> np.uint64(32)  # ranges of the upper bits, so the order stays
                keys = distinct.astype("<u4")
                cuts = np.flatnonzero(np.concatenate([[True], segment[1:] != segment[:-1]]))
                ends = np.append(cuts[1:], len(segment))
                n = len(cuts)
                blobs = [pa.array([x[a:b].tobytes() for a, b in zip(cuts.tolist(), ends.tolist(), strict=True)], pa.binary()) for x in (keys, own)]
                none = pa.nulls(n, pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(segment[cuts].astype(np.int32)), pa.array([serial] * n, pa.int64()), *blobs, none, none, none], _NAMES)
                listed = [batch.column(c).slice(lo, hi - lo).to_numpy().astype("<i8") for c in ("doc_id", "tag")] + [edges[:-1].astype("<i8")]
                here = (place[again] & ~_ALIGNED).tobytes()  # met inside the batch already
                yield pa.RecordBatch.from_arrays([pa.array([serial % segments], pa.int32()), pa.array([serial], pa.int64()), pa.nulls(1, pa.binary()), pa.array([here]), *[pa.array([x.tobytes()]) for x in listed]], _NAMES)
                serial += 1

    return docs.select("doc_id", "tag", "text").mapInArrow(run, _GATHERED)


def _met(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
    """Of one segment: for each batch the places of blocks and probes whose hash is a block's and occurs again; lists of documents go through."""
    lists = rows[rows["keys"].isna()]
    rows = rows[rows["keys"].notna()]
    sizes = rows["keys"].str.len().to_numpy() // 4
    keys, places = (np.frombuffer(b"".join(rows[c]), "<u4") for c in ("keys", "places"))
    order = np.argsort(keys, kind="stable")
    sorted_keys = keys[order]
    cuts = np.flatnonzero(np.concatenate([np.ones(min(1, len(keys)), bool), sorted_keys[1:] != sorted_keys[:-1]]))
    times = np.diff(np.append(cuts, len(keys)))
    blocks = np.add.reduceat((places[order] >= _ALIGNED).astype(np.int32), cuts) if len(cuts) else times
    hit = np.sort(order[np.repeat((blocks > 0) & (times > 1), times)])
    at = np.searchsorted(np.cumsum(sizes), hit, "right")
    found, plain = np.flatnonzero(np.bincount(at, minlength=len(rows))), places[hit] & ~_ALIGNED
    edges = np.searchsorted(at, np.append(found, len(rows)))
    met = pd.DataFrame({"batch": rows["batch"].to_numpy()[found], "places": [plain[a:b].tobytes() for a, b in zip(edges[:-1], edges[1:], strict=True)], "doc_ids": None, "tags": None, "starts": None})
    return pd.concat([met, lists[["batch", "places", "doc_ids", "tags", "starts"]]])


def _by_document(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
    """Of one batch: doc_id, tag and the hit places inside each of its documents."""
    places = [p for p in rows["places"] if p is not None and len(p)]
    if not places:
        return pd.DataFrame({"doc_id": [], "tag": [], "at": []})
    listed = rows[rows["doc_ids"].notna()].iloc[0]
    doc_ids, tags, starts = (np.frombuffer(listed[c], "<i8") for c in ("doc_ids", "tags", "starts"))
    places = np.unique(np.frombuffer(b"".join(places), "<u4").astype(np.int64))
    doc = np.searchsorted(starts, places, "right") - 1
    found, begin = np.unique(doc, return_index=True)
    ends = np.append(begin[1:], len(doc))
    return pd.DataFrame({"doc_id": doc_ids[found], "tag": tags[found], "at": [(places[a:b] - starts[d]).astype("<u4").tobytes() for d, a, b in zip(found, begin, ends, strict=True)]})


def anchors(docs: DataFrame, text_bytes: int, window: int = WINDOW, segment_blocks: int = SEGMENT_BLOCKS) -> DataFrame:
    """doc_id, tag and at (32-bit places, as binary) of every run of half a window that is an anchor. docs: doc_id, tag, text, all known."""
    block = window // 2
    segments = parts_for(text_bytes // 6 // block + 1, segment_blocks)  # a word and its space take some six bytes
    gathered = _blocks_and_probes(docs, block, segments)
    met = stored(gathered.groupBy("segment").applyInPandas(_met, "batch long, places binary, doc_ids binary, tags binary, starts binary"), "met")
    return met.groupBy("batch").applyInPandas(_by_document, "doc_id long, tag long, at binary")


def candidate_windows(held: DataFrame, window: int = WINDOW) -> DataFrame:
    """h, c (two hashes), doc_id, tag, pos of every window that holds an anchor. held: doc_id, tag, text, at."""
    block = window // 2

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in text_slices(batch.column("text")):
                edges, hashes = _hashed(batch.column("text").slice(lo, hi - lo))
                at = batch.column("at").slice(lo, hi - lo)
                sizes = pc.binary_length(at).to_numpy().astype(np.int64) // 4
                anchor = np.frombuffer(b"".join(at.to_pylist()), "<u4").astype(np.int64)
                begin, end = np.repeat(edges[:-1], sizes), np.repeat(edges[1:], sizes)
                first, last = np.maximum(begin + anchor - (window - block), begin), np.minimum(begin + anchor, end - window)
                some = last >= first
                mark = np.zeros(len(hashes) + 2, np.int32)
                np.add.at(mark, first[some], 1)
                np.add.at(mark, last[some] + 1, -1)
                pos = np.flatnonzero(np.cumsum(mark[: len(hashes)]))
                if not len(pos):
                    continue
                doc = np.searchsorted(edges, pos, "right") - 1
                h, c = rolling(hashes, window)[pos], (rolling(hashes, window, 1)[pos] >> np.uint64(32)).astype(np.uint32)
                names = [batch.column(x).slice(lo, hi - lo).take(pa.array(doc)) for x in ("doc_id", "tag")]
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c.view(np.int32)), *names, pa.array((pos - edges[doc]).astype(np.int32))], ["h", "c", "doc_id", "tag", "pos"])

    return held.select("doc_id", "tag", "text", "at").mapInArrow(run, "h long, c int, doc_id long, tag long, pos int")


def _marked(held: DataFrame, window: int) -> DataFrame:
    """doc_id, tag and the positions of its windows that also begin in a document with a smaller id."""
    found = stored(candidate_windows(held, window), "windows")
    spread = found.groupBy("h", "c").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most")).where("least < most").drop("most")
    least = stored(spread, "least")  # written down, so that the join deals both sides itself and can split a window that very many documents share
    marked = found.join(least, ["h", "c"]).where("doc_id > least").groupBy("doc_id", "tag").agg(F.collect_list("pos").alias("marked"))
    out = stored(marked, "marked")
    drop_stored(found)
    drop_stored(least)
    return out


def _dealt(documents: DataFrame, text_bytes: int, bucket_bytes: int) -> tuple[DataFrame, str, str]:
    """doc_id, tag, text, dealt by document into a bucketed table in the shared folder; the table's name and folder."""
    spark = documents.sparkSession
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), parts_for(text_bytes, bucket_bytes))
    name = f"mapmatch_{uuid.uuid4().hex}"
    folder = f"{shared_folder(spark)}/{name}"
    writer = documents.repartition(n, "doc_id", "tag").write.option("compression", "zstd").option("path", folder)
    writer.bucketBy(n, "doc_id", "tag").saveAsTable(name)
    return spark.table(name), name, folder


def _copies(docs: DataFrame) -> DataFrame:
    """doc_id, tag of documents whose whole text a document with a smaller id has."""
    texts = docs.where("doc_id IS NOT NULL AND text IS NOT NULL").select("doc_id", "tag", F.md5(F.col("text").cast("binary")).alias("m"))
    marks = stored(texts, "marks")
    least = stored(marks.groupBy("m").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most")).where("least < most").drop("most"), "first")
    out = stored(marks.join(least, "m").where("doc_id > least").select("doc_id", "tag").distinct(), "copies")
    drop_stored(marks)
    drop_stored(least)
    return out


def remove_repeats(documents: DataFrame, window: int = WINDOW, segment_blocks: int = SEGMENT_BLOCKS, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """doc_id, n_words, n_removed, kept (the words left, joined by single spaces) of every document."""
    plain = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("tag", F.xxhash64("text"))
    size = plain.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    docs, name, folder = _dealt(plain, size, bucket_bytes)
    copies = _copies(docs)
    key = ["doc_id", "tag"]
    flagged = docs.join(copies.withColumn("copy", F.lit(True)).hint("shuffle_hash"), key, "left")
    known = flagged.where("copy IS NULL AND doc_id IS NOT NULL AND text IS NOT NULL")
    found = stored(anchors(known, size, window, segment_blocks).groupBy(*key).agg(F.min("at").alias("at")), "anchors")  # rows alike have equal places
    marked = _marked(docs.join(found.hint("shuffle_hash"), key), window)
    drop_stored(found)
    joined = flagged.join(marked.hint("shuffle_hash"), key, "left").select("doc_id", "text", "marked", F.coalesce("copy", F.lit(False)).alias("copy"))

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in text_slices(batch.column("text")):
                doc_id, copy, places = (batch.column(c).slice(lo, hi - lo) for c in ("doc_id", "copy", "marked"))
                words, edges = _split(batch.column("text").slice(lo, hi - lo))
                size = np.diff(edges)
                whole = copy.to_numpy(zero_copy_only=False) & (size >= window)
                gone = np.repeat(whole, size)
                n = pc.fill_null(pc.list_value_length(places), 0).to_numpy().astype(np.int64)
                starts = places.flatten().to_numpy() + np.repeat(edges[:-1], n)
                edge = np.zeros(len(words) + window + 1, np.int32)
                np.add.at(edge, starts, 1)
                np.add.at(edge, starts + window, -1)
                gone |= np.cumsum(edge)[: len(words)] > 0
                left = np.concatenate([[0], np.cumsum(~gone)])[edges]
                kept = pc.binary_join(pa.ListArray.from_arrays(pa.array(left, pa.int32()), words.filter(pa.array(~gone))), " ")
                yield pa.RecordBatch.from_arrays([doc_id, pa.array(size), pa.array(size - np.diff(left)), kept], ["doc_id", "n_words", "n_removed", "kept"])

    out = stored(joined.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept string"), "kept")
    for done in (copies, marked):
        drop_stored(done)
    docs.sparkSession.sql(f"DROP TABLE {name}")
    drop_folder(docs.sparkSession, folder)
    return out
