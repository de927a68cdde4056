"""Exact top-k inner products by norm-bucketed retrieval.

Vectors are dealt into buckets by length, over the whole table, and large buckets into blocks. The longest vectors overall
give every query a score that its k best reach at least; a query is sent only to buckets whose longest vector, times its
own length, can reach that score, and a block only to the blocks of queries that go to its bucket: what length rules out
is never shuffled. Inside a block the vectors are sorted by length and cut into finer buckets. A query's present k-th
score, over its own length and the bucket's largest, is the cosine a vector of the bucket must reach: above 1 the
bucket is passed over. Where that local threshold is high, the query's largest coordinate bounds the same coordinate
of any match (the rest of the two unit vectors can make up only so much), and a binary search in the bucket's sorted
coordinate gives the candidates; where it is low, the candidates are the leading vectors long enough to reach the
score. The products of candidates are then computed exactly. Whatever a block keeps of a query, k rows at most, is ranked in a last step.

Defined results: vectors that are null, or hold a null or a component that is not finite, take no part, nor do rows
with a null id; only vectors of equal dimension are compared; rows that share the query's id count as its own; a
query row that is repeated is answered each time, with equal rows; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import parts_for, stored

#: Vectors and queries of a block, vectors of a fine bucket; the longest vectors that give first thresholds; the most buckets
#: by length of the whole table; pairs of query block and bucket up to which they are broadcast.
BLOCK, QUERY_BLOCK, BUCKET, SEEDS, LENGTHS, BROADCAST_PAIRS = 32_768, 8_192, 1_024, 512, 1_024, 1_000_000
#: The shortest vector of a bucket over its longest; the local cosine from which on coordinates prune.
SIMILAR, HIGH_COSINE = 0.9, 0.7
_SLACK = 1 + 1e-9


def integer_vectors(embeddings: DataFrame, vector: str = "embedding", scale: int = 256) -> DataFrame:
    """vec_id and v, floor(scale * x) of every component as double, of the rows that take part."""
    x = F.col(vector).cast("array<double>")
    rows = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("x")).where(F.col("vec_id").isNotNull() & F.col("x").isNotNull())
    rows = rows.where(F.forall("x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf")))))
    return rows.select("vec_id", F.transform("x", lambda c: F.floor(c * F.lit(float(scale))).cast("double")).alias("v"))


class _Best:
    """The k best (score, smaller id first) of every query, and the score to reach."""

    def __init__(self, n: int, k: int):
        self.k, self.reach = k, np.full(n, -np.inf)
        self.query = self.id = np.zeros(0, np.int64)
        self.score = np.zeros(0)

    def add(self, query: np.ndarray, ids: np.ndarray, score: np.ndarray) -> None:
        if not len(query):
            return
        query, ids, score = np.concatenate([self.query, query]), np.concatenate([self.id, ids]), np.concatenate([self.score, score])
        order = np.lexsort((ids, -score, query))
        query, ids, score = query[order], ids[order], score[order]
        place = np.arange(len(query)) - np.searchsorted(query, query)
        kept = place < self.k
        self.query, self.id, self.score = query[kept], ids[kept], score[kept]
        last = place[kept] == self.k - 1
        self.reach[self.query[last]] = np.maximum(self.reach[self.query[last]], self.score[last])


def search(queries: np.ndarray, query_ids: np.ndarray, vectors: np.ndarray, ids: np.ndarray, k: int, reach: np.ndarray | None = None) -> _Best:
    """The best k of the block for every query; rows that cannot beat ``reach`` may be left out."""
    best = _Best(len(queries), k)
    if reach is not None:
        best.reach = reach.copy()
    q_len, v_len = np.sqrt((queries**2).sum(axis=1)), np.sqrt((vectors**2).sum(axis=1))
    order = np.argsort(-v_len, kind="stable")
    vectors, ids, v_len = vectors[order], ids[order], v_len[order]
    lo = 0
    while lo < len(vectors):
        hi = int(min(lo + BUCKET, max(lo + 1, len(v_len) - np.searchsorted(v_len[::-1], v_len[lo] * SIMILAR))))
        bucket, names, top = vectors[lo:hi], ids[lo:hi], v_len[lo]
        bound = q_len * top
        active = np.flatnonzero(bound * _SLACK >= best.reach)
        if len(active):
            with np.errstate(divide="ignore", invalid="ignore"):
                cosine = np.where(bound[active] > 0, best.reach[active] / bound[active], -1.0)
            sharp = cosine >= HIGH_COSINE
            sorted_by: dict[int, tuple[np.ndarray, np.ndarray]] = {}
            for i, c in zip(active[sharp].tolist(), np.minimum(cosine[sharp], 1.0).tolist(), strict=True):
                f = int(np.argmax(np.abs(queries[i])))
                angle, width = np.arccos(np.clip(queries[i, f] / q_len[i], -1, 1)), np.arccos(c)
                if f not in sorted_by:
                    share = bucket[:, f] / np.maximum(v_len[lo:hi], 1e-300)
                    sorted_by[f] = np.argsort(share), np.sort(share)
                by_share, share = sorted_by[f]
                least, most = np.cos(min(np.pi, angle + width)) - 1e-7, np.cos(max(0.0, angle - width)) + 1e-7
                at = by_share[np.searchsorted(share, least) : np.searchsorted(share, most, "right")]
                product = bucket[at] @ queries[i]
                ok = (product >= best.reach[i]) & (names[at] != query_ids[i])
                best.add(np.full(int(ok.sum()), i), names[at][ok], product[ok])
            plain = active[~sharp]
            if len(plain):
                with np.errstate(divide="ignore", invalid="ignore"):
                    need = np.where(q_len[plain] > 0, best.reach[plain] / q_len[plain], -np.inf)
                n = int((v_len[lo:hi] * _SLACK >= need.min()).sum())
                product = queries[plain] @ bucket[:n].T
                i, j = np.nonzero(product >= best.reach[plain][:, None])
                own = names[j] == query_ids[plain[i]]
                i, j = i[~own], j[~own]
                best.add(plain[i], names[j], product[i, j])
        lo = hi
    return best


def _matrix(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_numpy()) if len(column) else np.zeros((0, 0))


def _with_reach(asked: DataFrame, seeds, k: int) -> DataFrame:
    """Queries with reach, a score that their k best vectors reach at least (null if the longest vectors do not tell)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            reach = np.full(len(batch), np.nan)
            for d in set(batch["d"]):
                same = [(i, v) for i, v in seeds.value if len(v) == d]
                at = np.flatnonzero(batch["d"] == d)
                if len(same) > k and d:
                    score = _matrix(batch["v"].iloc[at]) @ np.stack([v for _, v in same]).T
                    score[batch["vec_id"].to_numpy()[at][:, None] == np.array([i for i, _ in same])[None, :]] = -np.inf
                    reach[at] = np.partition(score, -k, axis=1)[:, -k]
            yield batch.assign(reach=np.where(np.isfinite(reach), reach, np.nan))

    fields = ", ".join(f"{c} {t}" for c, t in asked.dtypes)
    return asked.mapInPandas(run, f"{fields}, reach double").withColumn("reach", F.when(~F.isnan("reach"), F.col("reach")))


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, block: int = BLOCK, query_block: int = QUERY_BLOCK, lengths: int = LENGTHS) -> DataFrame:
    """query_id, rank, vec_id, score. Both inputs: vec_id, v (as ``integer_vectors`` makes them)."""
    spark = vectors.sparkSession
    length = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x))
    rows = stored(vectors.withColumn("d", F.size("v")).withColumn("length", length).withColumn("deal", F.xxhash64(F.monotonically_increasing_id())), "vectors")
    n = rows.count()
    longest = rows.orderBy(F.desc("length"), "vec_id", "deal").limit(SEEDS).collect()
    seeds = spark.sparkContext.broadcast([(r["vec_id"], np.array(r["v"])) for r in longest])  # a fixed number of rows
    plain = queries.withColumn("d", F.size("v")).withColumn("length", length).withColumn("query", F.monotonically_increasing_id()).withColumn("deal", F.xxhash64("query"))
    asked = stored(_with_reach(plain, seeds, k), "queries")
    m = asked.count()
    each = min(block, max(2048, n // (2 * spark.sparkContext.defaultParallelism) + 1))
    lines, buckets = parts_for(m, query_block), min(lengths, parts_for(n, each))
    # every bucket goes down to its cut, the last one to zero; all have about the same number of vectors
    cuts = sorted(set(rows.approxQuantile("length", [i / buckets for i in range(1, buckets)], 0.25 / buckets)), reverse=True) if buckets > 1 else []
    floor = F.array(*[F.lit(float(c)) for c in cuts]).cast("array<double>")
    placed = rows.withColumn("bucket", F.size(F.filter(floor, lambda c: c > F.col("length"))))
    # a bucket's blocks, and its longest vector: at most ``lengths`` rows
    found = {r["bucket"]: (r["top"], -(-r["n"] // each)) for r in placed.groupBy("bucket").agg(F.max("length").alias("top"), F.count("*").alias("n")).collect()}
    listed = F.array(*[F.struct(F.lit(b).alias("bucket"), F.lit(float(top)).alias("top"), F.lit(c).alias("blocks")) for b, (top, c) in sorted(found.items())]).cast("array<struct<bucket:int,top:double,blocks:int>>")
    reachable = lambda b: F.col("reach").isNull() | (F.col("length") * b["top"] * _SLACK >= F.col("reach"))
    sent = asked.withColumn("line", F.pmod("deal", F.lit(lines)).cast("int")).withColumn("b", F.explode(F.filter(listed, reachable)))
    right = sent.withColumn("col", F.explode(F.sequence(F.lit(0), F.col("b.blocks") - 1))).select("d", "line", F.col("b.bucket").alias("bucket"), "col", "query", "vec_id", "v")
    pairs = stored(sent.select("line", F.col("b.bucket").alias("bucket")).distinct(), "pairs")
    meets = F.broadcast(pairs) if pairs.count() <= BROADCAST_PAIRS else pairs
    own = F.element_at(F.transform(F.filter(listed, lambda b: b["bucket"] == F.col("bucket")), lambda b: b["blocks"]), 1)
    left = placed.withColumn("col", F.pmod("deal", own).cast("int")).join(meets, "bucket").select("d", "line", "bucket", "col", "vec_id", "v")

    def first_reach(q: np.ndarray, q_ids: np.ndarray) -> np.ndarray:
        same = [(i, v) for i, v in seeds.value if len(v) == q.shape[1]]
        if len(same) <= k:
            return np.full(len(q), -np.inf)
        score = q @ np.stack([v for _, v in same]).T
        score[q_ids[:, None] == np.array([i for i, _ in same])[None, :]] = -np.inf
        return np.partition(score, -k, axis=1)[:, -k]

    def meet(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"query": [], "query_id": [], "vec_id": [], "score": []}).astype("int64")
        q, v, q_ids, ids = _matrix(b["v"]), _matrix(a["v"]), b["vec_id"].to_numpy(), a["vec_id"].to_numpy()
        if q.shape[1] * float(np.abs(q).max(initial=0)) * float(np.abs(v).max(initial=0)) < 2**53:
            best = search(q, q_ids, v, ids, k, first_reach(q, q_ids))
            found = best.query, best.id, best.score
        else:  # beyond exact doubles: whole numbers in Python
            exact = [[int(x) for x in row] for row in v]
            triples = [(i, int(ids[j]), s) for i, row in enumerate(q) for s, j in sorted(((sum(int(x) * y for x, y in zip(row, exact[j], strict=True)), j) for j in range(len(v)) if ids[j] != q_ids[i]), key=lambda t: (-t[0], ids[t[1]]))[:k]]
            found = tuple(np.array([t[x] for t in triples]) for x in range(3))
        return pd.DataFrame({"query": b["query"].to_numpy()[found[0].astype(int)], "query_id": q_ids[found[0].astype(int)], "vec_id": found[1], "score": found[2]}).astype("int64")

    by = ["d", "bucket", "col", "line"]
    met = left.groupBy(*by).cogroup(right.groupBy(*by)).applyInPandas(meet, "query long, query_id long, vec_id long, score long")
    place = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id"))
    return met.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
