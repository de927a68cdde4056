"""Document fingerprints from spot signatures.

Wherever one of the commonest words of a language stands (an anchor), the next content words form a chain; the
hashes of anchor and chain are the document's set of signatures. Boilerplate has few such words, prose many. Sets are
compared by Jaccard likeness, after the bound by their lengths (the shorter over the longer); the search for near
documents deals sets into ranges of length so that only neighbouring ranges can hold partners, looks for a shared
signature among each set's rarest few (enough for the wanted likeness), and verifies what it meets.

Neighbours in descending doc_id are found without a global sort in one task: ids are dealt into ranges by their
quantiles, and the first row of each range also closes the range before it.

Defined results: null text is empty; a text with no signature has the hash of its text as its only one, so equal
texts stay alike and different ones apart; rows that share an id are in order of a hash of their text; null ids come
last; the neighbour of a lone row is itself; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import stored
from .expressions import let

#: Anchors, common words of English, German, French and Spanish.
ANCHORS = """
the of and to in is that it was for on are as with at by this from be have not but had his her they which you were there
der die und den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach
le la les de des et un une du en que qui dans pour par sur pas plus ne se sont avec il est au ce cette
el los las y del que en una por con no para su al lo como más pero sus es ha
""".split()
#: Content words in a chain.
CHAIN = 3
_ID_RANGES, _ROWS_PER_RANGE = 128, 4_000


def signatures(text: Column, anchors: list[str] | None = None, chain: int = CHAIN) -> Column:
    """The sorted distinct signature hashes of a text, as longs of 32 bits."""
    common = sorted(set(anchors or ANCHORS))
    words = F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+", -1), lambda w: w != "")
    spots = lambda ws: F.filter(F.transform(ws, lambda w, i: F.when(w.isin(common), F.struct(i.alias("i"), w.alias("w")))), lambda s: s.isNotNull())
    content = lambda ws: F.filter(ws, lambda w: ~w.isin(common))

    def chains(s: Column) -> Column:
        each = F.transform(s["spots"], lambda a, j: F.struct(a["w"].alias("w"), F.slice(s["content"], a["i"] - j + 1, chain).alias("c")))
        return F.transform(F.filter(each, lambda x: F.size(x["c"]) == chain), lambda x: F.xxhash64(x["w"], x["c"]).bitwiseAND(F.lit(0xFFFFFFFF)))

    found = let(words, lambda ws: let(F.struct(spots(ws).alias("spots"), content(ws).alias("content")), chains))
    alone = F.array(F.xxhash64(text).bitwiseAND(F.lit(0xFFFFFFFF)))
    return F.array_sort(F.array_distinct(let(found, lambda h: F.when(F.size(h) > 0, h).otherwise(alone))))


def as_text(sigs: Column) -> Column:
    """The fingerprint: eight hex digits for each signature, in order."""
    return F.array_join(F.transform(sigs, lambda h: F.lower(F.lpad(F.hex(h), 8, "0"))), "")


def jaccard(a: Column, b: Column, least: float = 0.0) -> Column:
    """Likeness of two signature sets; 0 where their lengths alone keep it under ``least``."""
    bound = F.least(F.size(a), F.size(b)) / F.greatest(F.size(a), F.size(b))
    shared = let(F.size(F.array_intersect(a, b)), lambda n: n / (F.size(a) + F.size(b) - n))
    return F.when(bound < least, F.lit(0.0)).otherwise(shared)


def _ranges(documents: DataFrame) -> tuple[list[float], list[list[float]]]:
    """Edges of id ranges, descending: outer ones, and those inside each; at most _ID_RANGES squared ranges."""
    n = documents.count()
    k = min(_ID_RANGES**2, math.ceil(n / _ROWS_PER_RANGE)) if n else 1
    cuts = sorted(set(documents.approxQuantile("doc_id", [i / k for i in range(1, k)], 0.2 / k)), reverse=True) if k > 1 else []
    step = max(1, math.ceil(math.sqrt(len(cuts) + 1)))
    outer = cuts[step - 1 :: step]
    inner = [cuts[i : i + step - 1] for i in range(0, len(cuts) + 1, step)]
    return outer, inner + [[]] * (len(outer) + 1 - len(inner))


def with_next(documents: DataFrame) -> DataFrame:
    """doc_id, text, next_text and the order columns, in descending doc_id; the last row's next is the first row."""
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    outer, inner = _ranges(docs.select("doc_id"))
    doubles = lambda xs: F.array(*[F.lit(x) for x in xs]).cast("array<double>")
    above = lambda xs: F.size(F.filter(xs, lambda x: x > F.coalesce(F.col("doc_id").cast("double"), F.lit(float("-inf")))))
    docs = docs.withColumn("big", above(doubles(outer)))
    docs = docs.withColumn("bucket", F.col("big") * _ID_RANGES * 2 + above(F.get(F.array(*[doubles(x) for x in inner]), F.col("big")))).drop("big")
    docs = docs.withColumn("h", F.xxhash64("text"))
    # h descends too, so the first row of a range is the greatest of its keys (null ids least)
    firsts = docs.groupBy("bucket").agg(F.max(F.struct("doc_id", "h")).alias("first"))
    line = Window.orderBy("bucket")  # one row for each range
    ends = Window.orderBy(F.desc("bucket")).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    firsts = firsts.withColumn("before", F.coalesce(F.lag("bucket").over(line), F.first("bucket").over(ends)))
    placed = docs.join(F.broadcast(firsts), "bucket")  # at most _ID_RANGES squared rows
    is_first = F.struct("doc_id", "h").eqNullSafe(F.col("first"))
    own, closing = F.struct(F.col("bucket").alias("b"), F.lit(0).alias("closing")), F.struct(F.col("before").alias("b"), F.lit(1).alias("closing"))
    both = placed.withColumn("x", F.explode(F.when(is_first, F.array(own, closing)).otherwise(F.array(own))))
    both = both.select("doc_id", "text", "h", F.col("x.b").alias("bucket"), F.col("x.closing").alias("closing"))
    return both.withColumn("next_text", F.lead("text").over(order_of()))


def order_of():
    return Window.partitionBy("bucket").orderBy("closing", F.col("doc_id").desc_nulls_last(), F.desc("h"))


def compare_edited(documents: DataFrame, part: int = 3) -> DataFrame:
    """For every document: its fingerprint, that of its edited text, and its likeness to both neighbours.

    The edited text has its last 1/part code points replaced by the first as many of the next document.
    """
    rows = with_next(documents)
    n = F.length("text")
    gone = F.floor(n / part).cast("int")
    rows = rows.withColumn("n_chars", n.cast("long")).withColumn("sigs", signatures(F.col("text")))
    rows = rows.withColumn("next_sigs", F.lead("sigs").over(order_of())).where("closing = 0")
    rows = rows.withColumn("edited", F.concat(F.substr("text", F.lit(1), n - gone), F.substr("next_text", F.lit(1), gone)))
    rows = rows.withColumn("edited_sigs", signatures(F.col("edited")))
    return rows.select(
        "doc_id",
        "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        as_text(F.col("sigs")).alias("fingerprint"),
        as_text(F.col("edited_sigs")).alias("edited_fingerprint"),
        jaccard(F.col("sigs"), F.col("edited_sigs")).alias("near_edited"),
        jaccard(F.col("sigs"), F.col("next_sigs")).alias("near_next"),
    )


def near_pairs(documents: DataFrame, least: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """Pairs (a, b, likeness) of class representatives at least so alike, and members (doc_id, class_id).

    A class holds the documents with equal sets; its id is its smallest doc_id.
    """
    sets = documents.select("doc_id", signatures(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("sigs"))
    classes = sets.groupBy("sigs").agg(F.min("doc_id").alias("class_id"))
    members = sets.join(classes, "sigs").select("doc_id", "class_id")
    # rare signatures first: what very many sets share is met only by sets that have nothing rarer to be met by
    each = stored(classes.select("class_id", F.explode("sigs").alias("sig")), "signatures")
    times = stored(each.groupBy("sig").agg(F.count("*").alias("n")), "times")  # written down, so that the join can split a common signature
    ranked = each.join(times, "sig").groupBy("class_id").agg(F.array_sort(F.collect_list(F.struct("n", "sig"))).alias("ranked"))
    size = F.size("ranked")
    width = -math.log(least)
    spread = ranked.withColumn("size", size).withColumn("range", F.floor(F.log(size.cast("double")) / width).cast("int"))
    prefix = F.explode(F.slice("ranked.sig", 1, (size - F.ceil(size * least) + 1).cast("int")))
    left = stored(spread.select("class_id", "size", "range", prefix.alias("sig")), "prefixes")
    right = left.select(F.col("class_id").alias("other"), F.col("size").alias("other_size"), F.explode(F.array(F.col("range"), F.col("range") - 1)).alias("range"), "sig")
    near = (F.col("class_id") != F.col("other")) & (F.least("size", "other_size") >= least * F.greatest("size", "other_size"))
    pairs = left.join(right, ["sig", "range"]).where(near).select(F.least("class_id", "other").alias("a"), F.greatest("class_id", "other").alias("b")).distinct()
    sets_of = lambda x: classes.select(F.col("class_id").alias(x), F.col("sigs").alias(f"sigs_{x}"))
    verified = pairs.join(sets_of("a"), "a").join(sets_of("b"), "b").select("a", "b", jaccard(F.col("sigs_a"), F.col("sigs_b"), least).alias("likeness"))
    return verified.where(F.col("likeness") >= least), members
