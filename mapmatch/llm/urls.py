"""URL filters by host-suffix and path-prefix expressions.

Every distinct url is taken apart once. Its host gives all dot-separated suffixes, its path all prefixes that end in
a slash, the whole path, and prefixes of the lengths that rules without a closing slash have. Suffixes with more
labels and prefixes with more slashes than any rule are left out, since none could match. An expression joins the
rules on the first 32 bits of its SHA-256 and counts only if the whole digest agrees; of the rules that fit, the one
with the longest host and path together wins (then the longer host). The rules are broadcast only below a size that
is counted first; beyond it both sides are dealt by hash prefix and salt.

Defined results: a null url, or one without ``://``, has empty host and path; an empty path fits no rule, since rule
paths begin with a slash; urls that no rule fits get the default verdict and a null rule; rules that differ in
verdict alone count as the blocking one; repeated rows are each returned; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rules are broadcast up to this number of rows (about 200 bytes each); salts of the hash join beyond it.
BROADCAST_RULES, SALTS = 500_000, 16

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z lower-cased; empty without ://."""
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)\A.*?://([^/?#]*)", 1), _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    """After the host up to ? # or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)\A.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), path), 256)


def _suffixes(host: Column, most: Column) -> Column:
    """Suffixes of the host at its dots, with at most so many labels."""
    labels = F.split(host, r"\.", -1)
    n = F.size(labels)
    return F.transform(F.sequence(F.lit(1), F.least(n, most)), lambda k: F.array_join(F.slice(labels, n - k + 1, k), "."))


def _prefixes(path: Column, most: Column, lengths: Column) -> Column:
    """Prefixes that end in a slash (with at most so many slashes), the whole path, and those of the given lengths."""
    parts = F.split(path, "/", -1)
    slashes = F.size(parts) - 1
    closed = F.transform(F.sequence(F.lit(0), F.least(slashes, most)), lambda k: F.array_join(F.slice(parts, 1, k + 1), "/"))
    closed = F.filter(F.transform(closed, lambda x: F.concat(x, F.lit("/"))), lambda x: F.startswith(path, x))
    cut = F.transform(F.filter(lengths, lambda n: n <= F.length(path)), lambda n: F.substr(path, F.lit(1), n))
    return F.array_distinct(F.concat(closed, F.array(path), cut))


def judge(pages: DataFrame, rules: DataFrame, key: str = "page_id", url: str = "url", default: str = "allow", broadcast_rules: int = BROADCAST_RULES) -> DataFrame:
    """key, url, host, path, rule, verdict of every row. rules: host, path, verdict (``block`` or ``allow``)."""
    rules = rules.select(F.translate("host", _UPPER, _LOWER).alias("host"), F.col("path"), F.col("verdict")).where("host IS NOT NULL AND path IS NOT NULL")
    rules = rules.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))  # block sorts after allow
    rules = rules.select(F.struct((F.length("host") + F.length("path")).alias("n"), F.length("host").alias("m"), F.concat("host", "path").alias("rule"), "verdict").alias("found"), _digest(F.col("host"), F.col("path")).alias("full"), "host", "path")
    bounds = rules.agg(
        F.count("*").alias("n"),
        F.coalesce(F.max(F.size(F.split("host", r"\.", -1))), F.lit(1)).alias("labels"),
        F.coalesce(F.max(F.size(F.split("path", "/", -1))), F.lit(1)).alias("slashes"),
        F.collect_set(F.when(~F.endswith("path", F.lit("/")), F.length("path"))).alias("lengths"),
    ).first()
    lengths = F.array(*[F.lit(n) for n in sorted(bounds["lengths"])]).cast("array<int>")
    urls = pages.select(F.col(key).alias("k"), F.col(url).alias("u")).groupBy("k", "u").agg(F.count("*").alias("n"))
    urls = urls.withColumn("host", host_of(F.col("u"))).withColumn("path", path_of(F.col("u")))
    suffixes, prefixes = _suffixes(F.col("host"), F.lit(bounds["labels"])), _prefixes(F.col("path"), F.lit(bounds["slashes"]), lengths)
    each = urls.select("*", F.explode(suffixes).alias("s")).select("*", F.explode(prefixes).alias("p")).withColumn("full", _digest(F.col("s"), F.col("p"))).drop("s", "p")
    rules = rules.select("found", F.col("full").alias("rule_full"), F.substr("full", F.lit(1), F.lit(8)).alias("prefix"))
    each = each.withColumn("prefix", F.substr("full", F.lit(1), F.lit(8)))
    if bounds["n"] <= broadcast_rules:
        met = each.join(F.broadcast(rules), "prefix", "left")
    else:
        salted = rules.withColumn("salt", F.explode(F.array(*[F.lit(i) for i in range(SALTS)])))
        met = each.withColumn("salt", F.pmod(F.xxhash64("k", "u"), F.lit(SALTS)).cast("int")).join(salted, ["prefix", "salt"], "left")
    best = met.groupBy("k", "u", "n", "host", "path").agg(F.max(F.when(F.col("full") == F.col("rule_full"), F.col("found"))).alias("best"))
    again = best.withColumn("_", F.explode(F.sequence(F.lit(1), F.col("n"))))
    return again.select(F.col("k").alias(key), F.col("u").alias(url), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))
