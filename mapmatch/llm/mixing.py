"""Mixing sources to target weights by weighted sampling without replacement.

Sources get shares of the words by weight, none above ``most`` times its own words: the level at which sources stop
is found in closed form over the table of sources. Each source then gives as many complete epochs as fit its target;
the rest comes from documents in the order of exponential keys (-ln u / quality, u a hash of the document), summed up
to the budget. Where a source's budget ends is found digit by digit: three rounds sum sizes by 17 bits of the key,
so no source is ever sorted in one task. The document at the edge gives only the words that are left, which makes
every source's words the whole part of its target.

Quality is how close a text's characters per word are to those of ordinary prose, from 1 down to 0.1.

Defined results: null text has size 0 and takes 0; null is a source of its own, the last; rows alike in id and text
share a key and are taken in turn; an empty table gives an empty result; other columns are ignored by ``plan``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WORD, stored, word_count

#: Weights by rank of the source, repeating; words of the mix by words of the corpus; most epochs of a source.
WEIGHTS, SHARE, MOST = (5, 2, 1), 1.5, 2
#: Characters per word (with its space) of ordinary prose.
PROSE = 6.5
_DIGIT, _DIGITS = 17, 3
#: Tables of sources up to this size are broadcast.
BROADCAST_SOURCES = 100_000


def quality(text: Column, size: Column) -> Column:
    per_word = F.length(text) / F.when(size > 0, size)
    return F.greatest(F.lit(0.1), F.coalesce(F.lit(1.0) / (F.lit(1.0) + F.abs(per_word - F.lit(PROSE))), F.lit(0.1)))


def _key(doc_id: Column, text: Column, size: Column) -> Column:
    """The exponential key as a whole number of 51 bits."""
    digest = F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(":"), F.coalesce(text, F.lit(""))).cast("binary"))
    u = (F.conv(F.substr(digest, F.lit(1), F.lit(13)), 16, 10).cast("long") + F.lit(1)) / F.lit(float(2**52 + 1))
    return F.least(F.floor(-F.ln(u) / quality(text, size) * F.lit(float(2**42))), F.lit(2**51 - 1)).cast("long")


def keyed(documents: DataFrame) -> DataFrame:
    """doc_id, source, size and key of every document."""
    rows = documents.select("doc_id", F.col("source").cast("string").alias("source"), F.col("text").cast("string").alias("text")).withColumn("size", word_count(F.col("text")))
    return rows.select("doc_id", "source", "size", _key(F.col("doc_id"), F.col("text"), F.col("size")).alias("key"))


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """source, source_size, target from source, source_size (one row for each source)."""
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    turns = F.array(*[F.lit(float(w)) for w in weights])
    rows = sizes.withColumn("weight", F.get(turns, F.pmod(rank, F.lit(len(weights))))).withColumn("cap", (F.col("source_size") * most).cast("double"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before, rest = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    total = F.sum("source_size").over(whole) * F.lit(float(share))
    level = (total - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(rest)
    leveled = rows.withColumn("level", level).withColumn("at", F.row_number().over(order))
    holds = F.when(F.col("level") <= F.col("cap") / F.col("weight"), F.struct("at", "level"))
    found = leveled.withColumn("level", F.min(holds).over(whole)["level"])
    return found.select("source", "source_size", F.least("cap", F.coalesce(F.col("level") * F.col("weight"), F.col("cap"))).alias("target"))


def plan(documents: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """doc_id, source, key, size, source_size, target, taken for every document."""
    rows = stored(keyed(documents), "keyed")
    sources = stored(targets(rows.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most), "targets")
    small = sources.count() <= BROADCAST_SOURCES
    fit = F.broadcast if small else (lambda x: x)
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    goal = sources.withColumn("epochs", epochs).withColumn("left", F.floor("target") - F.col("epochs") * F.col("source_size"))
    edge = goal.select(F.col("source").alias("s"), "left", F.lit(0).cast("long").alias("prefix"))
    for level in range(_DIGITS - 1, -1, -1):
        near = rows.join(fit(edge), rows["source"].eqNullSafe(edge["s"])).where(F.shiftright("key", (level + 1) * _DIGIT) == F.col("prefix"))
        sums = near.groupBy("s", "left", F.shiftright("key", level * _DIGIT).alias("digit")).agg(F.sum("size").alias("n"))
        upto = Window.partitionBy("s").orderBy("digit").rowsBetween(Window.unboundedPreceding, 0)
        ahead = sums.withColumn("upto", F.sum("n").over(upto)).where(F.col("upto") > F.col("left"))
        first = ahead.groupBy("s").agg(F.min(F.struct("digit", (F.col("left") - F.col("upto") + F.col("n")).alias("left"))).alias("x"))
        edge = stored(first.select("s", F.col("x.left").alias("left"), F.col("x.digit").alias("prefix")), "edge")
    placed = goal.select("source", "source_size", "target", "epochs").join(edge, F.col("source").eqNullSafe(F.col("s")), "left").select("source", "source_size", "target", "epochs", F.col("left").alias("edge_left"), F.col("prefix").alias("edge"))
    placed = stored(placed, "placed").withColumnRenamed("source", "s")
    docs = rows.join(fit(placed), rows["source"].eqNullSafe(placed["s"])).drop("s")
    turn = Window.partitionBy("source").orderBy(F.col("doc_id").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    tied = docs.where(F.col("key") == F.col("edge")).withColumn("part", F.greatest(F.lit(0), F.least("size", F.col("edge_left") - F.coalesce(F.sum("size").over(turn), F.lit(0)))))
    clear = docs.where(F.col("edge").isNull() | (F.col("key") != F.col("edge"))).withColumn("part", F.when(F.col("key") < F.col("edge"), F.col("size")).otherwise(0))
    both = clear.unionByName(tied)
    return both.select("doc_id", "source", "key", "size", "source_size", "target", (F.col("epochs") * F.col("size") + F.col("part")).cast("long").alias("taken"))


def mix(documents: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """The mixed documents, with the columns of the input: a row for each copy.

    Documents stay whole: the one at the edge of a source's budget comes once more if at least half of it is within the
    budget. Documents that the mix does not take, or without words, go. Rows alike in id, source and text are merged first
    and share what they take.
    """
    columns = documents.columns
    mark = F.xxhash64(F.col("doc_id"), F.col("source").cast("string"))
    chosen = plan(documents, weights, share, most).groupBy(mark.alias("_mark"), F.col("key").alias("_key")).agg(F.first("size").alias("_size"), F.sum("taken").alias("_taken"))
    chosen = chosen.withColumn("_copies", F.floor((F.col("_taken") + F.col("_size") / 2) / F.col("_size"))).where("_size > 0 AND _copies > 0")
    text = F.col("text").cast("string")
    docs = documents.withColumn("_mark", mark).withColumn("_key", _key(F.col("doc_id"), text, word_count(text)))
    met = docs.join(chosen, ["_mark", "_key"]).dropDuplicates(["_mark", "_key", "doc_id", "source", "text"]).withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies"))))
    return met.select(*columns)
