"""Near copies: documents whose sets of five-word shingles have a Jaccard likeness of at least four fifths.

First comes SimHash as in ``simhash``: fingerprints of the texts' shingle sets meet by equal bit blocks and pivot tables at
four differing bits, equal ones by a star; what meets is verified on whole sets. At a likeness of 0.8 fingerprints differ in
some ten of 64 bits, and no choice of equal bit blocks is selective at such a distance, so the rest has an exact way: in any
order of all shingles, two sets so alike share one of their first |x| - ceil(4|x|/5) + 1 shingles. The order puts shingles
that a sample of texts shows to be common last; it has a say in the cost alone. Texts of different components that meet there
are candidates if the shingle's places leave room for the overlap that is needed and their fingerprints of 256 bits differ
in at most ``far`` bits: at a likeness of 0.8 these differ in 39 with a deviation of 5.8, in up to 48 where sets are tiny, so
those beyond are five deviations off; unrelated texts differ in 128 with a deviation of 8.

From each task come only links enough to keep the components of the candidates. Each of these is then one group (a grid of
blocks, if large) that holds each text's whole set once, and in it all candidates that are not yet joined are verified. So
rows grow with the texts; comparisons inside a group of texts that are alike below four fifths still grow with its square.

Defined results: words are split and lower-cased as in ``simhash``; a text of less than five words is one shingle;
texts without words, null too, are copies of each other; groups are the components of verified pairs; repeated rows
are one; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WORD, drop_stored, runs_of, stored, tidied
from .components import connected
from .simhash import GROUP, bits_of, shingle_hashes
from .simhash import links as fingerprint_links

WORDS = 5
#: The least likeness, as a fraction.
PART, WHOLE = 4, 5
#: Words of 64 bits of a wide fingerprint, the first of which is the SimHash; the bits that may differ, for sets of up to SMALL shingles and beyond.
WIDE, SMALL, FAR_SMALL, FAR = 4, 24, 80, 70
#: Texts whose shingles are counted for the order, and the most shingles that are known as common.
SAMPLE, COMMON = 5_000, 100_000
#: Shingles of a block in which sets are compared.
BLOCK = 2_000_000
#: Candidates up to this number are broadcast to find their texts.
BROADCAST = 500_000
_SLICE = 1000
_W = [f"w{i}" for i in range(WIDE)]


def shingles(text: str | None) -> np.ndarray:
    """The distinct shingle hashes of a text, sorted without sign, as signed longs."""
    return np.unique(shingle_hashes(text, WORDS)).view(np.int64)


def wide(found: np.ndarray) -> list[int]:
    """WIDE SimHashes of a set of shingles, as signed longs: of its hashes, and of these hashed again."""
    h, out = found.view(np.uint64), []
    for _ in range(WIDE):
        out.append(bits_of(h))
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
        h = h ^ (h >> np.uint64(32))
    return np.array(out, np.uint64).view(np.int64).tolist()


def far(size_a: np.ndarray, size_b: np.ndarray) -> np.ndarray:
    """The bits in which wide fingerprints of sets that are alike enough may differ."""
    return np.where(np.minimum(size_a, size_b) <= SMALL, FAR_SMALL, FAR)


def _node(text: Column) -> Column:
    """A number for each text; 0 for all without words."""
    return F.when(text.rlike(WORD), F.xxhash64(text)).otherwise(F.lit(0)).cast("long")


def _common(texts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Shingles met in several texts of a sample, sorted, with the number of those texts."""

    @tidied
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for lo in range(0, len(batch), _SLICE):
                yield pd.DataFrame({"k": np.concatenate([shingles(t) for t in batch["text"].iloc[lo : lo + _SLICE]])})

    deal = max(1, -(-texts.count() // SAMPLE))
    sample = texts.where(F.pmod(F.xxhash64("node", F.lit(3)), F.lit(deal)) == 0).dropDuplicates(["node"])
    counts = sample.select("text").mapInPandas(run, "k long").groupBy("k").agg(F.count("*").alias("n")).where("n > 1")
    found = counts.orderBy(F.desc("n"), "k").limit(COMMON).toPandas().sort_values("k")
    return found["k"].to_numpy(np.int64), found["n"].to_numpy(np.int64)


def prefix(found: np.ndarray, common: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The shingles of a set by which it is met: rare ones first."""
    take = len(found) - -(-PART * len(found) // WHOLE) + 1
    if not len(common):
        return found[:take]
    at = np.minimum(np.searchsorted(common, found), len(common) - 1)
    rank = np.where(common[at] == found, counts[at], 0)
    return found[np.lexsort((found, rank))[:take]]


def _prints(texts: DataFrame) -> DataFrame:
    """node, the words of its wide fingerprint, size (of its set) and ks (the prefix of its set) of every text, once."""
    common, counts = _common(texts)

    @tidied
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: set[int] = set()
        for batch in batches:
            for lo in range(0, len(batch), _SLICE):
                rows = []
                for node, text in zip(batch["node"].iloc[lo : lo + _SLICE].tolist(), batch["text"].iloc[lo : lo + _SLICE], strict=True):
                    if node not in seen:
                        seen.add(node)
                        found = shingles(text)
                        rows.append((node, *wide(found), len(found), prefix(found, common, counts)))
                yield pd.DataFrame(rows, columns=["node", *_W, "size", "ks"])

    made = texts.mapInPandas(run, f"node long, {', '.join(f'{w} long' for w in _W)}, size int, ks array<long>")
    return stored(made.dropDuplicates(["node"]), "prints")


def _met(prints: DataFrame) -> DataFrame:
    """k, node and the place of k in its prefix, for shingles in the prefixes of several texts."""
    here = Window.partitionBy("k")
    rows = prints.select("node", F.posexplode("ks").alias("place", "k"))
    several = rows.withColumn("lo", F.min("node").over(here)).withColumn("hi", F.max("node").over(here)).where("lo < hi")
    return stored(several.select("k", "node", "place"), "met")


def _near(prints: DataFrame) -> DataFrame:
    """Pairs a, b of texts whose SimHashes are close, enough to keep the components, and of those that share one."""
    named = stored(prints.groupBy(F.col("w0").alias("fp")).agg(F.min("node").alias("least")), "named")
    linked = fingerprint_links(named.select("fp"))
    least = lambda x: named.select(F.col("fp").alias(x), F.col("least").alias(f"n{x}"))
    far_ones = linked.join(least("a"), "a").join(least("b"), "b").select(F.least("na", "nb").alias("a"), F.greatest("na", "nb").alias("b"))
    equal = prints.select("node", F.col("w0").alias("fp")).join(named, "fp").where("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b"))
    out = stored(far_ones.unionByName(equal).distinct(), "pairs")
    drop_stored(named)
    return out


def _sets(texts: DataFrame, wanted: DataFrame, name: str) -> DataFrame:
    """node, s (its set) of the wanted texts, once."""

    @tidied
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for lo in range(0, len(batch), _SLICE):
                part = batch.iloc[lo : lo + _SLICE]
                yield pd.DataFrame({"node": part["node"], "s": [shingles(t).tobytes() for t in part["text"]]})

    some = texts.join(F.broadcast(wanted) if wanted.count() <= BROADCAST else wanted, "node", "left_semi").dropDuplicates(["node"])
    return stored(some.mapInPandas(run, "node long, s binary"), name)


def _verified(texts: DataFrame, pairs: DataFrame) -> DataFrame:
    """Those of the pairs a, b that are alike enough."""

    @F.arrow_udf("boolean")
    def alike(x: pa.Array, y: pa.Array) -> pa.Array:
        sets = ((np.frombuffer(a.as_buffer(), np.int64), np.frombuffer(b.as_buffer(), np.int64)) for a, b in zip(x, y, strict=True))
        return pa.array([_enough(len(np.intersect1d(a, b, assume_unique=True)), len(a) + len(b)) for a, b in sets], pa.bool_())

    wanted = stored(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "wanted")
    sets = _sets(texts, wanted, "sets")
    left, right = (sets.select(F.col("node").alias(x), F.col("s").alias(f"s{x}")) for x in "ab")
    out = stored(pairs.join(left, "a").join(right, "b").where(alike("sa", "sb")).select("a", "b"), "alike")
    for done in (sets, wanted, pairs):
        drop_stored(done)
    return out


def _enough(shared, both):
    """Whether so many shared shingles of two sets of ``both`` together are the least likeness or more."""
    return WHOLE * shared >= PART * (both - shared)


def _rest(met: DataFrame, prints: DataFrame, roots: DataFrame) -> DataFrame:
    """k, node, place, root and fingerprint of the texts under keys that hold several components."""
    here = Window.partitionBy("k")
    named = prints.drop("ks").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    rest = met.join(named, "node").withColumn("least", F.min("root").over(here)).withColumn("most", F.max("root").over(here))
    return stored(rest.where("least < most").drop("least", "most"), "rest")


def _gridded(rows: DataFrame, key: str, blocks: Column) -> DataFrame:
    """The rows of each key as a grid of blocks: own (a row's block), i, j and cell (the blocks that meet there, and its hash)."""
    sizes = stored(rows.groupBy(key).agg(blocks.cast("int").alias("blocks")), "sizes")
    sized = rows.join(sizes, key).withColumn("own", F.pmod(F.xxhash64("node", F.lit(5)), F.col("blocks")).cast("int"))
    grid = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda o: F.struct(F.least(F.col("own"), o).alias("i"), F.greatest(F.col("own"), o).alias("j")))
    dealt = sized.withColumn("c", F.explode(grid)).withColumn("cell", F.xxhash64(key, "c.i", "c.j"))
    return dealt.select(*[c for c in rows.columns if c != key], "own", F.col("c.i").alias("i"), F.col("c.j").alias("j"), "cell").repartition("cell").sortWithinPartitions("cell")


def _labels(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The smallest index that each of n indices reaches over links i, j."""
    label = np.arange(n)
    while len(i):
        low, high = np.minimum(label[i], label[j]), np.maximum(label[i], label[j])
        np.minimum.at(label, high, low)
        while (label[label] != label).any():
            label = label[label]
        apart = label[i] != label[j]
        i, j = i[apart], j[apart]
    return label


def _batch(pairs: list[tuple[int, int]]) -> pa.RecordBatch:
    rows = sorted(set(pairs))
    return pa.RecordBatch.from_arrays([pa.array([r[x] for r in rows], pa.int64()) for x in (0, 1)], ["a", "b"])


def _candidates(rest: DataFrame, group: int = GROUP) -> DataFrame:
    """Links a, b that keep the components of the candidates: texts under one key that lie in different components and can be alike enough."""
    dealt = _gridded(rest, "k", F.ceil(F.count("*") / F.lit(group)))

    @tidied
    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple[int, int]] = []
        for rows in runs_of(batches, "cell"):
            root, size = rows["root"], rows["size"].astype(np.int64)
            room, w = size - rows["place"], np.stack([rows[c].view(np.uint64) for c in _W])
            left, right = (np.flatnonzero(rows["own"] == rows[c][0]) for c in "ij")
            label = np.arange(len(root))
            each = max(1, 1_000_000 // max(1, len(right)))
            for lo in range(0, len(left), each):
                a = left[lo : lo + each, None]
                fits = (root[a] != root[right]) & (np.minimum(room[a], room[right]) * (PART + WHOLE) >= PART * (size[a] + size[right]))
                x, y = np.nonzero(fits)
                x, y = a[x, 0], right[y]
                near = np.bitwise_count(w[:, x] ^ w[:, y]).sum(axis=0, dtype=np.int64) <= far(size[x], size[y])
                label = _labels(len(root), label[x[near]], label[y[near]])[label]
            moved = np.flatnonzero(label != np.arange(len(root)))
            out += zip(rows["node"][moved].tolist(), rows["node"][label[moved]].tolist(), strict=True)
            if len(out) > 100_000:
                yield _batch(out)
                out = []
        yield _batch(out)

    return dealt.mapInArrow(compare, "a long, b long").where("a <> b").distinct()


def _settled(texts: DataFrame, groups: DataFrame, group: int = GROUP) -> DataFrame:
    """Pairs a, b of texts of one group that are alike enough; enough of them to keep all components. groups: node, root (the group)."""
    sets = _sets(texts, groups.select("node"), "sets")
    rows = sets.join(groups, "node").select("root", "node", "s")
    dealt = _gridded(rows, "root", F.greatest(F.ceil(F.count("*") / F.lit(group)), F.ceil(F.sum(F.octet_length("s")) / F.lit(8 * BLOCK))))

    @tidied
    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple[int, int]] = []
        for rows in runs_of(batches, "cell"):
            sets = [np.frombuffer(s, np.uint64) for s in rows["s"]]  # sorted as such
            size, node = np.array([len(s) for s in sets]), rows["node"]
            w = np.array([wide(s) for s in sets], np.int64).view(np.uint64).T
            own, other = rows["i"][0], rows["j"][0]
            right = np.flatnonzero(rows["own"] == other)
            label = np.arange(len(sets))
            for a in np.flatnonzero(rows["own"] == own).tolist():
                b = right[label[right] != label[a]]
                b = b[b > a] if own == other else b
                b = b[WHOLE * np.minimum(size[a], size[b]) >= PART * np.maximum(size[a], size[b])]
                b = b[np.bitwise_count(w[:, b] ^ w[:, a, None]).sum(axis=0, dtype=np.int64) <= far(size[a], size[b])]
                for lo in range(0, len(b), _SLICE):
                    some = b[lo : lo + _SLICE]
                    all_of = np.concatenate([sets[x] for x in some])
                    at = np.minimum(np.searchsorted(sets[a], all_of), size[a] - 1)
                    shared = np.add.reduceat(sets[a][at] == all_of, np.cumsum(size[some]) - size[some], dtype=np.int64)
                    for x in some[_enough(shared, size[a] + size[some])].tolist():
                        if label[x] != label[a]:
                            out.append((min(node[a], node[x]), max(node[a], node[x])))
                            label[label == max(label[a], label[x])] = min(label[a], label[x])
            if len(out) > 100_000:
                yield _batch(out)
                out = []
        yield _batch(out)

    found = stored(dealt.mapInArrow(compare, "a long, b long").distinct(), "settled")
    drop_stored(sets)
    return found


def links(texts: DataFrame) -> DataFrame:
    """Pairs a, b of near copies among the rows of node, text; enough of them to keep all components."""
    prints = _prints(texts)
    found = _verified(texts, _near(prints))
    roots = connected(found)
    met = _met(prints)
    rest = _rest(met, prints, roots)
    for done in (met, prints):
        drop_stored(done)
    candidates = stored(_candidates(rest), "candidates")
    drop_stored(rest)
    groups = connected(candidates)
    second = _settled(texts, stored(groups.unionByName(groups.select(F.col("root").alias("node"), "root").distinct()), "groups"))
    drop_stored(candidates)
    return found.unionByName(second)


def representatives(documents: DataFrame) -> DataFrame:
    """One document of each group of near copies, with all its columns: that with the smallest doc_id (null last, then by a hash of the text)."""
    text = F.col("text").cast("string")
    mark = F.xxhash64(F.col("doc_id"), F.xxhash64("text"))
    roots = connected(links(documents.select(_node(text).alias("node"), text.alias("text")).where("node <> 0")))
    docs = documents.select("doc_id", mark.alias("mark"), _node(text).alias("n"))
    placed = docs.join(roots, docs["n"] == roots["node"], "left").withColumn("root", F.coalesce("root", "n"))
    first = placed.groupBy("root").agg(F.min(F.struct(F.isnull("doc_id").alias("none"), "doc_id", "mark")).alias("x")).select(F.col("x.mark").alias("_mark"))
    kept = documents.withColumn("_mark", mark).join(first.distinct(), "_mark", "left_semi")
    return kept.dropDuplicates(["_mark", "doc_id", "text"]).select(*documents.columns)
