"""SimHash near-duplicates with pivot distance tables.

A fingerprint has a bit for each of the 64 hash bits that more than half of the shingle hashes set. Distinct
fingerprints are compared once, however many documents share them. With at most d differing bits, cutting the 64 bits
into m blocks leaves m - d of them equal in some choice, so joining on every choice of m - d blocks meets every
linked pair; m grows with the number of fingerprints, which keeps the keys selective. Within a key the Hamming
distances to the pivots are laid out as a table sorted by the first pivot: only rows whose distances to every pivot
differ by at most d can be linked (triangle inequality), and the few left over are verified on the bits. A key with
very many fingerprints is dealt as a grid of blocks, so no task holds it whole. From each task come only enough links
to keep its components whole; ``connected`` joins them.

Defined results: a null text counts as no words; a text without words has fingerprint zero and links like any
other; a null doc_id never becomes a component id unless its group has no other; repeated rows share their
component; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import runs_of, stored, tidied
from .components import connected

SEED, WORDS, BITS = 42, 4, 4
#: Reference fingerprints of the distance tables: splitmix64 of 1, 2, 3, ...
PIVOTS = 24
#: More fingerprints than this under one key are dealt as a grid.
GROUP = 8192
#: Pairs of a cell up to which no pivot table is made; differing bits beyond which it would rule out nothing; pairs of a slice.
DIRECT, FAR, SLICE = 1024, 12, 2_000_000


def _pivots(n: int = PIVOTS) -> np.ndarray:
    x = (np.arange(1, n + 1, dtype=np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def shingle_hashes(text: str | None, words: int = WORDS, seed: int = SEED) -> np.ndarray:
    """The hash of every run of ``words`` words of a text, in order; of all its words if there are fewer."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    joined = memoryview(b" ".join(parts))
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = max(1, len(parts) - words + 1)
    digest = xxhash.xxh64_intdigest
    pairs = zip(starts[:n].tolist(), ends[len(parts) - n :].tolist(), strict=True)
    return np.fromiter((digest(joined[a:b], seed) for a, b in pairs), np.uint64, n)


def bits_of(hashes: np.ndarray) -> int:
    """The fingerprint of shingle hashes: the bits that more than half of them set."""
    n = len(hashes)
    if not n:
        return 0
    ones = np.zeros(64, np.int64)
    for lo in range(0, n, 1 << 16):
        ones += np.unpackbits(hashes[lo : lo + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, words: int = WORDS, seed: int = SEED) -> int:
    """The fingerprint of one text."""
    return bits_of(shingle_hashes(text, words, seed))


def fingerprints(documents: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns and fp, the fingerprint as a signed long."""

    @tidied
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = np.array([fingerprint(t) for t in batch["text"]], np.uint64).view(np.int64)
            yield batch[list(keep)].assign(fp=found)

    source = documents.select(*keep, "text")
    fields = ", ".join(f"`{x}` {t}" for x, t in source.select(*keep).dtypes)
    return source.mapInPandas(run, f"{fields}, fp long")


def links_within(a: np.ndarray, b: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (into a and b) of fingerprints at most ``bits`` apart. Both sides are cut by their pivot tables.

    Distances to a pivot have a deviation of four bits, so beyond FAR bits a table rules out nothing; then, and for so few
    pairs that a table would cost more than it saves, all are compared on the bits, slice by slice.
    """
    if bits > FAR or len(a) * len(b) <= DIRECT:
        each = max(1, SLICE // max(1, len(b)))
        found = [np.nonzero(np.bitwise_count(a[lo : lo + each, None] ^ b) <= bits) for lo in range(0, len(a), each)]
        return np.concatenate([i + lo for (i, _), lo in zip(found, range(0, len(a), each), strict=True)] or [np.zeros(0, np.int64)]), np.concatenate([j for _, j in found] or [np.zeros(0, np.int64)])
    pivots = _pivots()
    table_a, table_b = (np.bitwise_count(x[:, None] ^ pivots).astype(np.int8) for x in (a, b))
    order = np.argsort(table_b[:, 0], kind="stable")
    first = table_b[order, 0]
    lo, hi = np.searchsorted(first, table_a[:, 0] - bits), np.searchsorted(first, table_a[:, 0] + bits, "right")
    out_a, out_b = [], []
    width = hi - lo
    done = 0
    while done < len(a):  # slices of at most a few million pairs
        upto = max(done + 1, int(np.searchsorted(np.cumsum(width[done:]), SLICE, "right")) + done)
        w = width[done:upto]
        i = np.repeat(np.arange(done, upto), w)
        j = order[np.arange(int(w.sum())) - np.repeat(np.cumsum(w) - w, w) + np.repeat(lo[done:upto], w)]
        for p in range(1, len(pivots)):
            near = np.abs(table_a[i, p] - table_b[j, p]) <= bits
            i, j = i[near], j[near]
        near = np.bitwise_count(a[i] ^ b[j]) <= bits
        out_a.append(i[near])
        out_b.append(j[near])
        done = upto
    return np.concatenate(out_a or [np.zeros(0, np.int64)]), np.concatenate(out_b or [np.zeros(0, np.int64)])


def _spanning(n: int, i: np.ndarray, j: np.ndarray) -> list[tuple[int, int]]:
    """A forest of the given links: enough of them to keep their components."""
    root = list(range(n))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    kept = []
    for x, y in zip(i.tolist(), j.tolist(), strict=True):
        if (p := find(x)) != (q := find(y)):
            root[max(p, q)] = min(p, q)
            kept.append((x, y))
    return kept


def _masks(blocks: int, same: int) -> list[int]:
    """Bit masks of every choice of ``same`` of ``blocks`` nearly equal blocks of the 64 bits."""
    edges = [64 * i // blocks for i in range(blocks + 1)]
    one = [((1 << edges[i + 1]) - 1) ^ ((1 << edges[i]) - 1) for i in range(blocks)]
    return [sum(one[i] for i in choice) for choice in combinations(range(blocks), same)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def links(distinct: DataFrame, bits: int = BITS, group: int = GROUP) -> DataFrame:
    """Links a, b between distinct fingerprints (column fp) at most ``bits`` apart; enough to keep all components."""
    n = distinct.count()
    blocks = next((b for b in range(bits + 1, bits + 4) if n >> (64 * (b - bits) // b) < 64), bits + 4)
    masks = _masks(blocks, blocks - bits)
    keyed = distinct.select("fp", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(_signed(m))) for m in masks])).alias("t", "k"))
    sizes = keyed.groupBy("t", "k").agg(F.count("*").alias("n")).where("n > 1")
    sized = keyed.join(sizes, ["t", "k"])
    cells = F.ceil(F.col("n") / F.lit(group)).cast("int")
    own = F.pmod(F.xxhash64("fp", F.lit(7)), F.col("s")).cast("int")
    grid = F.transform(F.sequence(F.lit(0), F.col("s") - 1), lambda o: F.struct(F.least(F.col("own"), o).alias("i"), F.greatest(F.col("own"), o).alias("j")))
    dealt = sized.withColumn("s", cells).withColumn("own", own).select("fp", "t", "k", "own", F.explode(grid).alias("c"))
    dealt = dealt.select("fp", "own", F.xxhash64("t", "k", "c.i", "c.j").alias("cell"), F.col("c.i").alias("i"), F.col("c.j").alias("j"))
    dealt = dealt.repartition("cell").sortWithinPartitions("cell", "own", "fp")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple[int, int]] = []
        for rows in runs_of(batches, "cell"):
            if len(rows["fp"]) > 1:
                fp = rows["fp"].view(np.uint64)
                left, right = (np.flatnonzero(rows["own"] == rows[c][0]) for c in "ij")
                a, b = links_within(fp[left], fp[right], bits)
                out += [(int(rows["fp"][x]), int(rows["fp"][y])) for x, y in _spanning(len(fp), left[a], right[b])]
            if len(out) > 100_000:
                yield _pairs(out)
                out = []
        yield _pairs(out)

    return dealt.mapInArrow(compare, "a long, b long").where("a <> b").distinct()


def _pairs(rows: list[tuple[int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in (0, 1)], ["a", "b"])


def _placed(docs: DataFrame, bits: int) -> DataFrame:
    """fp, least (the smallest doc_id with it) and root (the fingerprint that names the component)."""
    nodes = stored(docs.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = connected(links(nodes.select("fp"), bits))
    return nodes.join(roots, nodes["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))


def near_duplicates(documents: DataFrame, keep: tuple[str, ...] = ("doc_id",), bits: int = BITS) -> DataFrame:
    """The kept columns with fingerprint (16 hex digits) and component_id (the smallest doc_id reachable)."""
    docs = stored(fingerprints(documents, tuple(dict.fromkeys(("doc_id", *keep)))), "fingerprints")
    placed = _placed(docs, bits)
    least = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    named = placed.join(least, "root").select("fp", "component_id")
    return docs.join(named, "fp").select(*keep, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def representatives(documents: DataFrame, bits: int = BITS) -> DataFrame:
    """One document of each component, with all its columns: that with the smallest doc_id (null last, then by a hash of the text)."""
    mark = F.xxhash64(F.col("doc_id"), F.xxhash64("text"))
    docs = stored(fingerprints(documents.select("doc_id", "text", mark.alias("mark")), ("doc_id", "mark")), "fingerprints")
    placed = _placed(docs, bits).select("fp", "root")
    first = docs.join(placed, "fp").groupBy("root").agg(F.min(F.struct(F.isnull("doc_id").alias("none"), "doc_id", "mark")).alias("x")).select(F.col("x.mark").alias("_mark"))
    kept = documents.withColumn("_mark", mark).join(first.distinct(), "_mark", "left_semi")
    return kept.dropDuplicates(["_mark", "doc_id", "text"]).select(*documents.columns)
