"""Token ids in binary files: frequency-ranked ids in byte-aligned variable-length coding.

File format (one shard): a 32-byte header of four little-endian unsigned 64-bit numbers (magic, documents, values,
data bytes), a table of documents (id, null flag, values), the control bytes, then the data bytes. An id is replaced
by its rank in the frequency table (0 the commonest); a rank takes 1 to 4 little-endian bytes, and each control byte
holds the lengths less one of four ranks, two bits each, lowest first. Decoding looks a control byte up in a table
of 256 rows, so it runs in numpy without a loop over values. The frequency table is stored beside the shards.

Shards hold ascending doc_id (null first, repeated ids by content) and are written by executors through the file
system that the folder's scheme names, each attempt under a name of its own; only the shards in the manifest count,
so repeated attempts do no harm. Only per-shard totals are summed in one place.

Defined results: null or empty text is the end id alone; an empty table gives an empty result; repeated rows are
written once each; other columns are ignored.
"""

from __future__ import annotations

import json
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import drop_stored, parts_for, shared_folder, stored, tidied
from .tokens import Encoder, word_level

#: The first eight bytes of every shard.
MAGIC = int.from_bytes(b"MMTOKEN1", "little")
_DOC = np.dtype([("doc_id", "<i8"), ("null", "<u1"), ("values", "<u8")])
_CODES = np.arange(256)[:, None] >> (2 * np.arange(4)) & 3
_LENGTHS = (_CODES + 1).astype(np.uint8)
_IDS = "doc_id long, ids binary, mark long, counted binary, counts binary"
_ID_NAMES = [x.split()[0] for x in _IDS.split(", ")]


def encode(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Control bytes and data bytes of unsigned 32-bit values."""
    values = values.astype("<u4")
    code = (values > 0xFF).astype(np.uint8) + (values > 0xFFFF) + (values > 0xFFFFFF)
    quads = np.pad(code, (0, -len(code) % 4)).reshape(-1, 4)
    control = (quads << (2 * np.arange(4, dtype=np.uint8))).sum(axis=1).astype(np.uint8)
    kept = np.arange(4) <= code[:, None]
    return control, values.view(np.uint8).reshape(-1, 4)[kept]


def decode(control: np.ndarray, data: np.ndarray, n: int) -> np.ndarray:
    """The n values of a control and a data stream."""
    lengths = _LENGTHS[control].reshape(-1)[:n].astype(np.int64)
    start = np.cumsum(lengths) - lengths
    padded = np.concatenate([data, np.zeros(4, np.uint8)])
    out = np.zeros(n, np.uint32)
    for k in range(4):
        out |= np.where(lengths > k, padded[start + k], 0).astype(np.uint32) << np.uint32(8 * k)
    return out


def _open(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder if "://" in folder else "file://" + folder.removeprefix("file:"))


def write_shard(folder: str, name: str, docs: np.ndarray, ranks: np.ndarray) -> str:
    system, path = _open(folder)
    system.create_dir(path, recursive=True)
    control, data = encode(ranks)
    header = np.array([MAGIC, len(docs), len(ranks), len(data)], "<u8")
    with system.open_output_stream(f"{path}/{name}") as out:
        for part in (header, docs, control, data):
            out.write(part.tobytes())
    return name


def read_shard(folder: str, name: str) -> tuple[np.ndarray, np.ndarray]:
    system, path = _open(folder)
    with system.open_input_stream(f"{path}/{name}") as file:
        magic, n_docs, n_values, n_bytes = (int(x) for x in np.frombuffer(file.read(32), "<u8"))
        if magic != MAGIC:
            raise ValueError(f"{name} is not a token shard")
        docs = np.frombuffer(file.read(n_docs * _DOC.itemsize), _DOC)
        control = np.frombuffer(file.read(-(-n_values // 4)), np.uint8)
        return docs, decode(control, np.frombuffer(file.read(n_bytes), np.uint8), n_values)


def tokenize(documents: DataFrame, tokenizer: str, end_id: int) -> DataFrame:
    """doc_id, ids and their crc32 as mark of every document, stored; and a row for each task with the counts of its ids.

    Ids take 16 bits each where vocabulary and end id allow, else 32. Rows of counts hold ``counted`` (distinct ids) and
    ``counts`` alone; rows of documents have null there.
    """
    kind = kind_of(tokenizer, end_id)

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, total = Encoder.of(tokenizer), np.zeros(1 << 16, np.int64)
        for batch in batches:
            for lo, hi, ids, edges in encoder.closed(batch.column("text"), end_id):
                found = np.bincount(ids, minlength=len(total))
                found[: len(total)] += total
                total = found
                ids = ids.astype(kind)
                mark = [zlib.crc32(ids[a:b]) for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]
                none = pa.nulls(hi - lo, pa.binary())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(lo, hi - lo), _binary(ids, edges), pa.array(mark, pa.int64()), none, none], _ID_NAMES)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.nulls(1, pa.int64()), pa.array([at.astype("<u4").tobytes()]), pa.array([total[at].astype("<u8").tobytes()])], _ID_NAMES)

    source = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return stored(source.mapInArrow(run, _IDS), "ids")


def kind_of(tokenizer: str, end_id: int) -> np.dtype:
    """The width in which ids are kept on the way to the files."""
    with open(tokenizer, encoding="utf-8") as file:
        return np.dtype("<u2" if word_level(json.load(file)) and end_id < 1 << 16 else "<u4")


def frequencies(ids: DataFrame) -> list[tuple[int, int]]:
    """(id, count), commonest first, from the rows of counts: at most one for each entry of the vocabulary."""

    def spread(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for counted, counts in zip(batch["counted"], batch["counts"], strict=True):
                yield pd.DataFrame({"id": np.frombuffer(counted, "<u4").astype(np.int64), "n": np.frombuffer(counts, "<u8").astype(np.int64)})

    rows = ids.where("counts IS NOT NULL").select("counted", "counts").mapInPandas(spread, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).collect()
    return sorted(((r["id"], r["n"]) for r in rows), key=lambda x: (-x[1], x[0]))


def _binary(values: np.ndarray, edges: np.ndarray) -> pa.Array:
    """Runs of values, from edge to edge, as binary."""
    offsets = (edges * values.itemsize).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(edges) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(values))])


def _runs(column: pa.Array, kind: np.dtype) -> tuple[np.ndarray, np.ndarray]:
    """The values of a binary column, and the edges of its rows in them."""
    edges = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8)[edges[0] : edges[-1]]
    return data.view(kind), (edges - edges[0]) // kind.itemsize


def write(documents: DataFrame, tokenizer: str, folder: str, end_id: int = 2, shard_tokens: int = 2_000_000) -> DataFrame:
    """Write all documents; returns the manifest: shard, part, n_docs, n_tokens and its start (ids before it)."""
    spark, kind = documents.sparkSession, kind_of(tokenizer, end_id)
    ids = tokenize(documents, tokenizer, end_id)
    ranked = frequencies(ids)
    rank = np.zeros(max([1 << 16, *(i + 1 for i, _ in ranked)]), np.uint32)
    rank[[i for i, _ in ranked]] = np.arange(len(ranked))
    spark.createDataFrame(ranked, "id long, n long").coalesce(1).write.parquet(f"{folder}/vocabulary")
    sent = spark.sparkContext.broadcast(rank)  # four bytes an entry of the vocabulary, whatever the input
    shards = parts_for(sum(n for _, n in ranked), shard_tokens)

    @tidied
    def save(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, held, size, serial = TaskContext.get().partitionId(), [], 0, 0

        def flush() -> pa.RecordBatch:
            docs = np.concatenate([d for d, _ in held])
            ranks = sent.value[np.concatenate([v for _, v in held])]
            name = write_shard(folder, f"part-{part:06d}-{serial:04d}-{uuid.uuid4().hex}.tok", docs, ranks)
            row = {"shard": name, "part": part, "serial": serial, "n_docs": len(docs), "n_tokens": len(ranks)}
            return pa.RecordBatch.from_pylist([row], pa.schema([("shard", pa.string()), ("part", pa.int32()), ("serial", pa.int32()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

        for batch in batches:
            values, edges = _runs(batch.column("ids"), kind)
            docs = np.zeros(len(batch), _DOC)
            docs["doc_id"], docs["null"] = pc.fill_null(batch.column("doc_id"), 0), batch.column("doc_id").is_null()
            docs["values"] = np.diff(edges)
            lo = 0
            while lo < len(docs):
                hi = min(len(docs), max(lo + 1, int(np.searchsorted(edges, edges[lo] + shard_tokens - size))))
                held.append((docs[lo:hi].copy(), values[edges[lo] : edges[hi]].copy()))
                size += int(edges[hi] - edges[lo])
                if size >= shard_tokens:
                    yield flush()
                    held, size, serial = [], 0, serial + 1
                lo = hi
        if held:
            yield flush()

    rows = ids.where("counts IS NULL").select("doc_id", "ids", "mark")
    order = [F.col("doc_id").asc_nulls_first(), F.col("mark")]
    dealt = rows.repartitionByRange(max(shards, spark.sparkContext.defaultParallelism), *order).sortWithinPartitions(*order, "ids")
    manifest = stored(dealt.mapInArrow(save, "shard string, part int, serial int, n_docs long, n_tokens long"), "manifest")
    drop_stored(ids)
    before = Window.orderBy("part", "serial").rowsBetween(Window.unboundedPreceding, -1)  # one row for each shard
    return manifest.withColumn("start", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)).cast("long"))


def read(manifest: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids (the original token ids, 32 bits each) of every document, from the files."""
    spark = manifest.sparkSession
    ranked = [r["id"] for r in spark.read.parquet(f"{folder}/vocabulary").orderBy(F.desc("n"), "id").collect()]
    back = spark.sparkContext.broadcast(np.array(ranked, "<u4"))

    @tidied
    def load(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, start in zip(batch.column("shard").to_pylist(), batch.column("start").to_pylist(), strict=True):
                docs, ranks = read_shard(folder, name)
                edges = np.concatenate([[0], np.cumsum(docs["values"], dtype=np.int64)])
                doc_id = pa.array(docs["doc_id"], mask=docs["null"].astype(bool))
                yield pa.RecordBatch.from_arrays([doc_id, pa.array(start + edges[:-1]), pa.array(np.diff(edges)), _binary(back.value[ranks], edges)], ["doc_id", "start", "n_tokens", "ids"])

    spread = manifest.select("shard", "start").repartition(spark.sparkContext.defaultParallelism * 2)
    return spread.mapInArrow(load, "doc_id long, start long, n_tokens long, ids binary")


def round_trip(documents: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Write, read back, and give doc_id, start, n_tokens, ids_crc32 of what the files hold."""
    folder = f"{shared_folder(documents.sparkSession)}/tokens-{uuid.uuid4().hex}"
    manifest = write(documents, tokenizer, folder, end_id)
    return read(manifest, folder).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))
