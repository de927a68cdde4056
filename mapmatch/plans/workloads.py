"""The registered queries: the experiments and typical uses, over the given tables, with their SQL twins."""

from __future__ import annotations

import uuid
from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..automata.maps import close_functions
from ..operators import baselines, chunks, distributed, fold, match, measure
from ..operators.match import Compiled, compiled
from ..sources.shared import shared_folder
from ..sources.sinks import map_states
from ..sources.tables import table
from ..streaming import stream
from . import corpora
from .corpora import RULES

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

#: Symbols of a chunk in the registered queries.
SIZE = 1024


def query(sql: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return keep


@cache
def _of(p: str) -> Compiled:
    return compiled(p)


def _quoted(p: str) -> str:
    return "'" + p.replace("'", "''") + "'"


def _full(column: str, p: str) -> str:
    return f"regexp_full_match({column}, {_quoted(p)}, 's')"


# documents, pages, parts: a word a row


def _rows(name: str, tab: str, key: str, column: str, rule: str, plan: str = "dfa_rows", expr: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        words = table(spark, sf_dir, tab).select(F.col(key), F.expr(expr or column).alias("_w"))
        return match.with_verdict(words, "_w", _of(RULES[rule]), "accepted", plan).select(key, "accepted")

    query(f"SELECT {key}, {_full(expr or column, RULES[rule])} AS accepted FROM {tab}", name)(run)


for _rule in ("email", "ipv4", "licence", "secret", "junkrun"):
    _rows(f"doc_{_rule}_rows", "documents", "doc_id", "text", _rule, "map_rows" if _rule in ("email", "junkrun") else "dfa_rows")
_rows("page_url_shape", "pages", "page_id", "url", "url")
_rows("page_plain_heading", "pages", "page_id", "html", "heading")
_rows("page_entity_run", "pages", "page_id", "html", "entities")
_rows("part_promo_ring", "part", "p_partkey", "p_type", "part", expr="concat(p_type, ' ', p_name)")
ORACLES["part_promo_ring"] = f"SELECT p_partkey, {_full("p_type || ' ' || p_name", RULES['part'])} AS accepted FROM part"

# the same verdicts by every method and baseline

_EMAIL = f"SELECT doc_id, {_full('text', RULES['email'])} AS accepted FROM documents"


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", "text")


def _chunked(name: str, kind: str, how: str, **options) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = match.accepts_chunked(_documents(spark, sf_dir), "doc_id", "text", _of(RULES["email"]), SIZE, how, kind, **options)
        return found.select(F.col("word_id").alias("doc_id"), "accepted")

    query(_EMAIL, name)(run)


_ROUNDS = {"fanout": 4, "rounds": 3}  # narrow, so that the trees have several levels here
for _name, _kind, _how, _options in (
    ("doc_email_chunked_inorder", "maps", "in_order", {}),
    ("doc_email_chunked_tree", "maps", "tree", _ROUNDS),
    ("doc_email_chunked_auto", "auto", "in_order", {}),
    ("doc_email_rows_auto", "auto", "in_order", {"longest": 1 << 20}),
    ("doc_email_lazy", "lazy", "tree", _ROUNDS),
    ("doc_email_nfa_maps", "relations", "in_order", {}),
    ("doc_email_nfa_maps_tree", "relations", "tree", _ROUNDS),
    ("doc_email_nfa_lazy", "lazy_relations", "tree", _ROUNDS),
    ("doc_email_speculative", "speculate", "tree", _ROUNDS),
    ("doc_email_speculative_inorder", "speculate", "in_order", {}),
    ("doc_email_speculative_merged", "merge", "in_order", {}),
    ("doc_email_halving", "halve", "in_order", {}),
):
    _chunked(_name, _kind, _how, **_options)


#: The deterministic automaton of this pattern has 2**18 states, above the cap, and its relation maps are more yet.
TAIL = ".*[aeiou].{17}"


@query(f"SELECT page_id, {_full('url', TAIL)} AS accepted FROM pages")
def page_url_tail_lazy_nfa(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The planner goes to maps made on demand over the nondeterministic automaton; no subset automaton is made."""
    found = match.accepts_chunked(table(spark, sf_dir, "pages"), "page_id", "url", _of(TAIL), 32)
    return found.select(F.col("word_id").alias("page_id"), "accepted")


@query(f"SELECT page_id, {_full('url', TAIL)} AS accepted FROM pages")
def page_url_tail_lazy_subsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by subsets made on demand, a word a row."""
    return baselines.lazy_subset_rows(table(spark, sf_dir, "pages"), "url", _of(TAIL)).select("page_id", "accepted")


@query(_EMAIL)
def doc_email_nfa_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.nfa_sets(_documents(spark, sf_dir), "text", _of(RULES["email"])).select("doc_id", "accepted")


@query(_EMAIL)
def doc_email_query_parallel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.query_parallel(_documents(spark, sf_dir), "text", _of(RULES["email"]), 16).select("doc_id", "accepted")


@query(_EMAIL)
def doc_email_catalyst(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _documents(spark, sf_dir).select("doc_id", match.accepts_expression(F.col("text"), _of(RULES["email"])).alias("accepted"))


@query(_EMAIL)
def doc_email_rlike(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _documents(spark, sf_dir).select("doc_id", baselines.spark_rlike(F.col("text"), RULES["email"]).alias("accepted"))


@query(f"SELECT doc_id FROM documents WHERE {_full('text', RULES['secret'])}")
def doc_secret_filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    return match.where_accepts(_documents(spark, sf_dir), "text", _of(RULES["secret"])).select("doc_id")


# words made of rows


def _word_sql(tab: str, key: str, symbol: str, order: str, p: str, where: str = "") -> str:
    return f"SELECT {key}, {_full('w', p)} AS accepted FROM (SELECT {key}, string_agg({symbol}, '' ORDER BY {order}) AS w FROM {tab} {where} GROUP BY {key})"


def _accepted(words: DataFrame, key: str, rule: str) -> DataFrame:
    return match.with_verdict(words, "word", _of(RULES[rule])).select(key, "accepted")


def _turns(spark: SparkSession, sf_dir: str, rule: str) -> DataFrame:
    return match.accepts_rows(table(spark, sf_dir, "conversations"), "conv_id", ["turn"], F.substr("role", F.lit(1), F.lit(1)), _of(RULES[rule]))


@query(_word_sql("conversations", "conv_id", "substr(role, 1, 1)", "turn", RULES["turns"]))
def chat_turn_protocol(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _turns(spark, sf_dir, "turns")


@query(_word_sql("conversations", "conv_id", "substr(role, 1, 1)", "turn", RULES["strict_turns"]))
def chat_strict_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _turns(spark, sf_dir, "strict_turns")


def _funnel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", "ts", "user_id", F.substr("event_type", F.lit(1), F.lit(1)).alias("s"))


_FUNNEL = _word_sql("events", "user_id", "substr(event_type, 1, 1)", "ts, event_id", RULES["funnel"])


@query(_FUNNEL)
def user_funnel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return match.accepts_rows(_funnel(spark, sf_dir), "user_id", ["ts", "event_id"], F.col("s"), _of(RULES["funnel"]))


@query(_FUNNEL)
def user_funnel_packed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with every user's word in one row: for keys of bounded size."""
    return _accepted(chunks.pack_rows(_funnel(spark, sf_dir), "user_id", ["ts", "event_id"], F.col("s")), "user_id", "funnel")


@query(f"SELECT user_id, day, {_full('w', RULES['day_funnel'])} AS accepted FROM (SELECT user_id, strftime(ts, '%Y-%m-%d') AS day, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS w FROM events GROUP BY ALL)")
def user_funnel_by_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    days = stream.windowed(_funnel(spark, sf_dir), "user_id", "ts", "event_id", F.col("s"), "tumbling", "1 day")
    return match.with_verdict(days, "word", _of(RULES["day_funnel"])).select("user_id", F.date_format("start", "yyyy-MM-dd").alias("day"), "accepted")


@query(_FUNNEL)
def user_funnel_from_day_panes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The maps of a user's days, composed in the order of days, decide the whole history."""
    days = stream.windowed(_funnel(spark, sf_dir), "user_id", "ts", "event_id", F.col("s"), "tumbling", "1 day")
    from pyspark.sql.window import Window

    pieces = days.select(F.col("user_id").alias("word_id"), (F.row_number().over(Window.partitionBy("user_id").orderBy("start")) - 1).alias("chunk_ix"), F.col("word").alias("payload"))
    c = _of(RULES["funnel"])
    return match.accepts_segments(match.scan_chunks(pieces, c.scanner("maps")), c).select(F.col("word_id").alias("user_id"), "accepted")


@query(_FUNNEL)
def events_stream_funnel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as one-symbol chunks in shuffled files, matched by the streaming operator: the verdicts of the batch."""
    from pyspark.sql.window import Window

    by = Window.partitionBy("user_id")
    events = _funnel(spark, sf_dir).select(F.col("user_id").alias("word_id"), (F.row_number().over(by.orderBy("ts", "event_id")) - 1).cast("int").alias("chunk_ix"), F.count("*").over(by).cast("int").alias("chunks"), F.col("s").alias("payload"), F.col("ts").cast("timestamp").alias("ts"))
    folder, name = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}", f"funnel_{uuid.uuid4().hex}"
    events.repartition(4, F.xxhash64("word_id", "chunk_ix")).write.parquet(f"{folder}/in")
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 2).parquet(f"{folder}/in")
    found = stream.match_stream(source, _of(RULES["funnel"]), "3650 days")
    started = found.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/{name}").outputMode("append").trigger(availableNow=True).start()
    started.awaitTermination()
    return spark.read.schema("word_id long, status string").parquet(f"{folder}/out").select(F.col("word_id").alias("user_id"), (F.col("status") == "accepted").alias("accepted"))


_FLAGS = "l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate"


@query(_word_sql("lineitem", "l_orderkey", "l_returnflag", _FLAGS, RULES["flag_parity"]))
def order_flag_parity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return match.accepts_rows(table(spark, sf_dir, "lineitem"), "l_orderkey", _FLAGS.split(", "), F.col("l_returnflag"), _of(RULES["flag_parity"]))


@query(f"""WITH w AS (SELECT o_custkey, {_full("string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey)", RULES['status'])} AS a FROM orders GROUP BY o_custkey)
SELECT r_name, n_name, count(*) AS customers, sum(a::INT)::BIGINT AS accepted FROM w JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey
GROUP BY ROLLUP (r_name, n_name)""")
def customer_status_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    hits = match.accepts_rows(table(spark, sf_dir, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], F.col("o_orderstatus"), _of(RULES["status"]))
    named = hits.join(table(spark, sf_dir, "customer"), F.col("c_custkey") == F.col("o_custkey")).join(table(spark, sf_dir, "nation"), F.col("n_nationkey") == F.col("c_nationkey")).join(table(spark, sf_dir, "region"), F.col("r_regionkey") == F.col("n_regionkey"))
    return named.rollup("r_name", "n_name").agg(F.count("*").alias("customers"), F.sum(F.col("accepted").cast("long")).alias("accepted"))


@query(f"SELECT vec_id, {_full("array_to_string(list_transform(embedding, lambda x: CASE WHEN x >= 0 THEN 'p' ELSE 'n' END), '')", RULES['signs'])} AS accepted FROM embeddings")
def embedding_sign_word(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = table(spark, sf_dir, "embeddings").select("vec_id", F.array_join(F.transform("embedding", lambda x: F.when(x >= 0, "p").otherwise("n")), "").alias("word"))
    return _accepted(words, "vec_id", "signs")


# one giant word in many chunks

_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate"]


def digit_chunks(spark: SparkSession, sf_dir: str, n: int, size: int = SIZE) -> DataFrame:
    rows = chunks.index_rows(table(spark, sf_dir, "lineitem").select(*_ORDER, "l_quantity"), _ORDER, size=size)
    digit = F.pmod(F.col("l_quantity").cast("long"), F.lit(5)) + F.when(F.col("i") % (2 * n) >= n, 5).otherwise(0)
    return chunks.pack_one(rows, digit.cast("string"))


def parity_chunks(spark: SparkSession, sf_dir: str, size: int = SIZE) -> DataFrame:
    rows = chunks.index_rows(table(spark, sf_dir, "lineitem").select(*_ORDER, "l_quantity"), _ORDER, size=size)
    return chunks.pack_one(rows, (2 * F.pmod(F.col("l_quantity").cast("long"), F.lit(5)) + F.col("i") % 2).cast("string"))


def _giant_sql(symbol: str, p: str) -> str:
    return f"""WITH w AS (SELECT row_number() OVER (ORDER BY {', '.join(_ORDER)}) - 1 AS i, l_quantity::BIGINT AS q FROM lineitem)
SELECT 0::BIGINT AS word_id, {_full(f"string_agg(({symbol})::VARCHAR, '' ORDER BY i)", p)} AS accepted FROM w"""


def _digit_sql(n: int, p: str | None = None) -> str:
    return _giant_sql(f"q % 5 + CASE WHEN i % {2 * n} >= {n} THEN 5 ELSE 0 END", p or corpora.loop(n))


@query(_digit_sql(5))
def digit_word_r5(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = _of(corpora.loop(5))
    return match.accepts_segments(match.scan_chunks(digit_chunks(spark, sf_dir, 5), c.scanner("maps")), c)


@query(_digit_sql(50))
def digit_word_r50(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = _of(corpora.loop(50))
    return match.accepts_segments(match.scan_chunks(digit_chunks(spark, sf_dir, 50), c.scanner("maps")), c, "tree", fanout=8, rounds=3)


@query(_digit_sql(50), "digit_word_r50_lazy")
def _digit_lazy(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = _of(corpora.loop(50))
    return match.accepts_segments(match.scan_chunks(digit_chunks(spark, sf_dir, 50), c.scanner("lazy")), c)


@query(_digit_sql(500))
def digit_word_r500(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table of a million maps made beforehand: the case in which the table outgrows the caches."""
    c = _of(corpora.loop(500))
    return match.accepts_segments(match.scan_chunks(digit_chunks(spark, sf_dir, 500), c.scanner("maps")), c)


@query(_digit_sql(500))
def digit_word_r500_dfa(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table of a million maps would not fit any cache, so the plan makes maps on demand."""
    c = _of(corpora.loop(500))
    return match.accepts_segments(match.scan_chunks(digit_chunks(spark, sf_dir, 500), c.scanner("lazy")), c)


def run_chunks(spark: SparkSession, n: int, size: int = SIZE) -> DataFrame:
    """One word of n letters a."""
    pieces = spark.range(-(-n // size))
    return pieces.select(F.lit(0).cast("long").alias("word_id"), F.col("id").cast("int").alias("chunk_ix"), F.repeat(F.lit("a"), F.least(F.lit(size), F.lit(n) - F.col("id") * size).cast("int")).alias("payload"))


def _run_query(name: str, n: int, kind: str) -> None:
    p = corpora.loop_or_run(n)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        c = _of(p)
        return match.accepts_segments(match.scan_chunks(run_chunks(spark, table(spark, sf_dir, "lineitem").count()), c.scanner(kind)), c)

    # the language holds every run of a, whatever n; RE2 does not take repetitions as large as 1000 positions many times over
    query(f"SELECT 0::BIGINT AS word_id, {_full("repeat('a', count(*)::INT)", corpora.loop_or_run(min(n, 50)))} AS accepted FROM lineitem", name)(run)


_run_query("digit_word_ra", 50, "maps")
_run_query("digit_word_ra500", 500, "lazy")


@query(_giant_sql("2 * (q % 5) + i % 2", corpora.alternating()))
def parity_word_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = _of(corpora.alternating())
    return match.accepts_segments(match.scan_chunks(parity_chunks(spark, sf_dir), c.scanner("halve")), c)


@query("SELECT true AS same")
def long_document_any_cut(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents as chunks of several sizes: no size changes a verdict."""
    docs, c = _documents(spark, sf_dir), _of(RULES["junkrun"])
    runs = [match.accepts_chunked(docs, "doc_id", "text", c, size).withColumnRenamed("accepted", f"a{size}") for size in (64, 1000, 100_000)]
    both = runs[0].join(runs[1], "word_id").join(runs[2], "word_id")
    return both.agg(F.bool_and((F.col("a64") == F.col("a1000")) & (F.col("a64") == F.col("a100000"))).alias("same"))


# sizes


def _closure_sql(c: Compiled, symbols: str | None = None) -> str:
    """The maps m(f), by the classes of the pattern or of those symbols that a SELECT of a column s gives."""
    start = f"m(f) AS (SELECT {list(range(c.dfa.size))} UNION SELECT list_transform(m.f, lambda q: d.s[q + 1]) FROM m, d)"
    columns = [c.dfa.delta[:, k].tolist() for k in range(c.dfa.classes.k)]
    if symbols is None:
        return f"""WITH RECURSIVE d(s) AS (VALUES {', '.join(f'({x})' for x in columns)}), {start}"""
    cases = " ".join(f"WHEN unicode(s) BETWEEN {lo} AND {hi} THEN {k + 1}" for lo, hi, k in c.dfa.classes.rows())
    return f"""WITH RECURSIVE u AS MATERIALIZED (SELECT DISTINCT CASE {cases} END AS k FROM ({symbols}) WHERE s <> ''), d(s) AS MATERIALIZED (SELECT DISTINCT {columns}[k] FROM u), {start}"""


_LETTERS = "SELECT DISTINCT unnest(string_split(text, '')) AS s FROM documents"
_DIGITS = "SELECT DISTINCT (l_quantity::BIGINT % 10)::VARCHAR AS s FROM lineitem"
_DIGITS_FLAGS = f"{_DIGITS} UNION SELECT DISTINCT lower(l_returnflag) FROM lineitem"


def _letters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every symbol of the documents."""
    return _documents(spark, sf_dir).select(F.explode(F.array_distinct(F.split("text", ""))).alias("s")).where("s <> ''").distinct()


def _digits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last digits of the quantities."""
    return table(spark, sf_dir, "lineitem").select(F.pmod(F.col("l_quantity").cast("long"), F.lit(10)).cast("string").alias("s")).where("s IS NOT NULL").distinct()


def _digits_flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    flags = table(spark, sf_dir, "lineitem").select(F.lower("l_returnflag").alias("s")).where("s <> ''").distinct()
    return _digits(spark, sf_dir).union(flags)


@query(_closure_sql(_of("(ab)*"), _LETTERS) + " SELECT array_to_string(f, ',') AS image, f[1] = 0 AS final FROM m")
def map_table_ab(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The maps over the symbols that the documents hold."""
    dfa = measure.met_dfa(_of("(ab)*"), _letters(spark, sf_dir))
    if dfa is None:
        return spark.createDataFrame([("0,1,2", True)], "image string, final boolean")
    return map_states(spark, close_functions(dfa)).select(F.array_join("image", ",").alias("image"), "final")


@query(_closure_sql(_of("(ab)*")) + " SELECT array_to_string(f, ',') AS image, f[1] = 0 AS final FROM m")
def map_table_ab_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distributed.close_distributed(spark, _of("(ab)*").dfa).select(F.array_join("image", ",").alias("image"), "final")


@query(_closure_sql(_of(corpora.map_blowup(5)), _LETTERS) + " SELECT count(*) AS maps, count(*) FILTER (f[1] = 0) AS finals FROM m")
def closure_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Thousands of maps by joins alone, over the symbols that the documents hold: a round for each level of the search."""
    dfa = measure.met_dfa(_of(corpora.map_blowup(5)), _letters(spark, sf_dir))
    if dfa is None:
        return spark.createDataFrame([(1, 1)], "maps long, finals long")
    found = distributed.close_distributed(spark, dfa)
    return found.agg(F.count("*").alias("maps"), F.sum(F.col("final").cast("long")).alias("finals"))


def _size_query(name: str, p: str, symbols, sql: str) -> None:
    c = _of(p)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.createDataFrame([measure.met_sizes(c, symbols(spark, sf_dir))], "dfa_total long, dfa_live long, maps_total long, maps_live long")

    sink = c.dfa.sink
    dead = "true" if sink is None else f"len(list_filter(f, lambda q: q <> {sink})) > 0"
    query(_closure_sql(c, sql) + f" SELECT {c.dfa.size}::BIGINT AS dfa_total, {c.dfa.size - (sink is not None)}::BIGINT AS dfa_live, count(*) AS maps_total, count(*) FILTER ({dead}) AS maps_live FROM m", name)(run)


# sizes over the symbols that a table holds
_size_query("closure_size_r5", corpora.loop(5), _digits, _DIGITS)
_size_query("closure_size_ra5", corpora.loop_or_run(5), _digits_flags, _DIGITS_FLAGS)
_size_query("closure_size_alt5", corpora.alternating(), _digits, _DIGITS)
_size_query("closure_size_w9", corpora.subset_blowup(5), _letters, _LETTERS)
_size_query("closure_size_w10", corpora.map_blowup(4), _letters, _LETTERS)


@query("SELECT * FROM (VALUES (2, 4, 5, 5), (3, 8, 12, 12), (4, 16, 27, 27), (5, 32, 58, 58)) t(n, dfa_total, function_maps, relation_maps)")
def subset_blowup_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = [(n, _of(corpora.subset_blowup(n))) for n in range(2, 6)]
    return spark.createDataFrame([(n, c.dfa.size, c.maps.size, c.relations.size) for n, c in made], "n int, dfa_total int, function_maps int, relation_maps int")


@query("SELECT DISTINCT l_linenumber::INT AS n, (l_linenumber ** l_linenumber)::INT AS maps_live FROM lineitem WHERE l_linenumber >= 2")
def map_blowup_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As many states as an order has lines; every pattern is compiled in a task of its own."""
    n = table(spark, sf_dir, "lineitem").select(F.col("l_linenumber").cast("int").alias("n")).where("n >= 2").distinct()
    patterns = n.select(F.col("n").alias("pattern_id"), F.lit("map_blowup").alias("family"), F.format_string(corpora.MAP_BLOWUP, F.col("n") - 2).alias("pattern"), F.lit("full").alias("mode"))
    return measure.corpus_sizes(patterns).select(F.col("pattern_id").alias("n"), "maps_live")


@query("""WITH q AS (SELECT DISTINCT l_quantity::INT AS n FROM lineitem WHERE l_quantity >= 1), t AS (SELECT 10 * max(n) AS n FROM q HAVING max(n) IS NOT NULL)
SELECT 'loop' AS family, n, 2 * n AS dfa_live, 4 * n * n + 2 * n - 1 AS maps_live FROM (SELECT n FROM q UNION SELECT n FROM t) UNION ALL SELECT 'loop_or_run', n, 2 * n + 2, 4 * n * n + 2 * n FROM t""")
def loop_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loops as long as the quantities sold and ten times the largest, for which the run variant is sized too: the published
    sizes (5, 50, 500 and the run of 500) are among them. Every pattern is compiled in a task of its own."""
    q = table(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("int").alias("n")).where("n >= 1").distinct()
    top = q.agg((10 * F.max("n")).alias("n")).where("n IS NOT NULL")
    loops = q.union(top).distinct().select(F.col("n").alias("pattern_id"), F.lit("loop").alias("family"), F.format_string("([0-4]{%d}[5-9]{%d})*", "n", "n").alias("pattern"), F.lit("full").alias("mode"))
    runs = top.select((-F.col("n")).alias("pattern_id"), F.lit("loop_or_run").alias("family"), F.format_string("([0-4]{%d}[5-9]{%d})*|a*", "n", "n").alias("pattern"), F.lit("full").alias("mode"))
    return measure.corpus_sizes(loops.union(runs), max_dfa=2000).select("family", F.abs("pattern_id").alias("n"), "dfa_live", "maps_live")


@query("SELECT 11 AS dfa_total, 15564 AS maps_total, true AS over_cube, true AS over_fourth")
def ten_gap_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = measure.size_report(RULES["ten_gaps"])
    return spark.createDataFrame([(r["dfa_total"], r["maps_total"], r["over_cube"], r["over_fourth"])], "dfa_total int, maps_total int, over_cube boolean, over_fourth boolean")


def _ab(symbol: str) -> str:
    return f"CASE WHEN {symbol} = 'view' THEN 'a' ELSE 'b' END"


def _image_sql(w: str) -> str:
    """The map of (ab)* that a word of letters a and b has, as text."""
    return f"array_to_string(list_transform([0, 1, 2], lambda s: list_reduce(list_prepend(s, list_transform(string_split({w}, ''), lambda x: CASE x WHEN 'a' THEN 3 ELSE 6 END)), lambda q, k: [1, 2, 2, 2, 0, 2][q + k - 2])), ',')"


@query(f"""WITH w AS (SELECT user_id, string_agg({_ab('event_type')}, '' ORDER BY ts, event_id) AS w FROM events GROUP BY user_id), p AS (SELECT user_id, w, unnest(range(ceil(len(w) / 3)::BIGINT)) AS i FROM w)
SELECT user_id, i::INT AS chunk_ix, {_image_sql('substr(w, 3 * i + 1, 3)')} AS image FROM p""")
def chunk_maps_ab(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The maps of the pieces of every user's word: a for a view, b for any other event."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", F.expr(_ab("event_type")).alias("s"))
    words = chunks.pack_rows(events, "user_id", ["ts", "event_id"], F.col("s"))
    maps = match.scan_map_ids(chunks.chunk_words(words, "user_id", "word", 3), _of("(ab)*").maps)
    return fold.attach_images(maps, _of("(ab)*").maps).select(F.col("word_id").alias("user_id"), "chunk_ix", F.array_join("image", ",").alias("image"))


@query(f"""WITH w AS (SELECT user_id, strftime(ts, '%Y-%m-%d') AS day, string_agg({_ab('event_type')}, '' ORDER BY ts, event_id) AS w FROM events GROUP BY ALL)
SELECT user_id, day, split_part({_image_sql('w')}, ',', 1)::INT AS end_state, {_image_sql('w')} AS image FROM w""")
def fold_ab(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The words of every user's days in pieces of two letters, folded in order and as a tree."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", F.concat_ws(" ", F.date_format("ts", "yyyy-MM-dd"), "user_id").alias("key"), F.expr(_ab("event_type")).alias("s"))
    words = chunks.pack_rows(events, "key", ["ts", "event_id"], F.col("s"))
    segments = match.scan_chunks(chunks.chunk_words(words, "key", "word", 2), _of("(ab)*").scanner("maps"), fold_runs=False)
    both = fold.fold_in_order(segments).join(fold.fold_tree(segments, 2, 3), "word_id")
    return both.select(F.expr("try_cast(substr(word_id, 12) AS bigint) AS user_id"), F.substr("word_id", F.lit(1), F.lit(10)).alias("day"), "end_state", F.array_join("image", ",").alias("image"))


_SIZES = ["family", "pattern", "status", "nfa_states", "dfa_total", "dfa_live", "maps_total", "maps_live", "over_square", "over_cube", "over_fourth", "over_10k", "table_bytes_dense256", "table_bytes_classed"]


def _report(spark: SparkSession, sf_dir: str) -> DataFrame:
    patterns = corpora.corpus(spark, sf_dir)
    return measure.corpus_sizes(patterns).join(patterns.select("pattern_id", "pattern"), "pattern_id")


@query()
def corpus_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _report(spark, sf_dir).select(*_SIZES)


#: The study's classes over the tables of 1000 documents (family, used, over the square, cube and fourth power, over 10 000 maps, share).
_CLASSES = """SELECT * FROM (VALUES (NULL, 2226, 1817, 3, 2, 41, 81.63::DOUBLE), ('alternating', 20, 1, 0, 0, 0, 5), ('gap1', 36, 0, 0, 0, 0, 0), ('gap2', 40, 37, 0, 0, 0, 92.5), ('gap3', 40, 40, 0, 0, 0, 100), ('gap4', 40, 40, 0, 0, 0, 100),
('literal', 160, 160, 0, 0, 0, 100), ('loop', 30, 30, 0, 0, 0, 100), ('loop_or_run', 15, 0, 0, 0, 0, 0), ('map_blowup', 4, 3, 2, 1, 0, 75), ('part_brand', 150, 0, 0, 0, 0, 0), ('part_name', 64, 0, 0, 0, 0, 0), ('part_type', 48, 0, 0, 0, 0, 0),
('passage', 40, 40, 0, 0, 40, 100), ('phrase', 1458, 1458, 0, 0, 0, 100), ('rule', 17, 8, 1, 1, 1, 47.06), ('subset_blowup', 6, 0, 0, 0, 0, 0), ('url', 58, 0, 0, 0, 0, 0)) t(family, used, over_square, over_cube, over_fourth, over_10k, over_square_percent)"""


@query(_CLASSES)
def corpus_size_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = measure.size_classes(_report(spark, sf_dir))
    counts = ("used", "over_square", "over_cube", "over_fourth", "over_10k")
    return found.select("family", *[F.col(c).cast("int").alias(c) for c in counts], "over_square_percent")


@query("SELECT * FROM (VALUES ('ok', 2226::BIGINT), ('unsupported', 3), ('dfa_cap', 1)) t(status, patterns)")
def corpus_retained(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.retained(_report(spark, sf_dir))


@query("SELECT * FROM (VALUES ('(ab)*', 6), ('(ab)*(ab)*', 6), ('a*', 2), ('([0-4]{5}[5-9]{5})*', 110)) t(pattern, complexity)")
def syntactic_complexities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(p, measure.syntactic_complexity(p)) for p in ("(ab)*", "(ab)*(ab)*", "a*", corpora.loop(5))], "pattern string, complexity int")


_TERMS = """WITH n AS (SELECT count(*)::DOUBLE AS n FROM lineitem), p AS (SELECT unnest([1, 2, 4, 8, 12])::INT AS chunks), c AS (SELECT 11.0::DOUBLE AS nfa, 11.0::DOUBLE AS dfa),
t AS (SELECT chunks, n, nfa, dfa, greatest(1.0, log2(greatest(chunks, 2))) AS log FROM n, p, c)
SELECT chunks, method, round(lookups, 3) AS lookups FROM t, LATERAL (VALUES ('nfa', nfa * n), ('dfa', n), ('speculate_tree', dfa * n / chunks + dfa * log), ('speculate_in_order', dfa * n / chunks + chunks),
  ('relations_tree', n / chunks + nfa * nfa * nfa * log), ('relations_in_order', n / chunks + nfa * chunks), ('maps_tree', n / chunks + dfa * log), ('maps_in_order', n / chunks + chunks)) m(method, lookups)"""


@query(_TERMS)
def complexity_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Predicted work of every method on the digit word, by number of chunks."""
    c, n = _of(corpora.loop(5)), table(spark, sf_dir, "lineitem").count()
    return spark.createDataFrame([(p, *t) for p in (1, 2, 4, 8, 12) for t in measure.complexity_terms(c, n, p)], "chunks int, method string, lookups double").withColumn("lookups", F.round("lookups", 3))


@query("""WITH n AS (SELECT count(*)::BIGINT AS n FROM lineitem), k AS (SELECT n, ceil(n / 4096.0)::BIGINT AS p FROM n)
SELECT method, symbols, lookups, chunks, fold_steps, fold_cells FROM k, LATERAL (VALUES ('maps', n, n, p, p - 1, (p - 1) * 11), ('speculate', n, n * 11, p, p - 1, (p - 1) * 11), ('lazy', n, n, p, p - 1, (p - 1) * 11)) m(method, symbols, lookups, chunks, fold_steps, fold_cells)""")
def counted_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a run really looks up and composes, counted while it runs: one lookup a symbol for maps, one a state for speculation."""
    n, c = table(spark, sf_dir, "lineitem").count(), _of(corpora.loop(5))
    return measure.counted(spark, c, corpora.digits(5, n), 4096, ("maps", "speculate", "lazy"))


@query("SELECT * FROM (VALUES ('loop', 44, 30), ('loop_or_run', 1, 1), ('alternating', 10, 10)) t(word, maps_touched, dfa_touched)")
def maps_touched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct map states on a run from the identity, however large the table is."""
    words = [("loop", corpora.loop(15), corpora.digits(15, 3000)), ("loop_or_run", corpora.loop_or_run(15), "a" * 3000), ("alternating", corpora.alternating(), "01" * 1500)]
    rows = [(name, measure.maps_touched(_of(p), _of(p).dfa.classes.table[[ord(x) for x in w]]), measure.states_touched(_of(p), _of(p).dfa.classes.table[[ord(x) for x in w]])) for name, p, w in words]
    return spark.createDataFrame(rows, "word string, maps_touched int, dfa_touched int")


@query("SELECT * FROM (VALUES (1, 3), (2, 12), (3, 16)) t(symbols, most_maps)")
def relation_maps_by_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The most relation maps that so many symbols reach over two states, of all choices: all 16 take three."""
    return measure.relation_reach(spark, 2, 3)


def _any_of(names: str) -> str:
    return f"concat('(', array_join({names}, '|'), ')*')"


@query("""WITH d AS (SELECT user_id, ts::DATE AS day, list_sort(list(DISTINCT event_type)) AS s FROM events WHERE event_type <> '' GROUP BY ALL), p AS (SELECT s AS a, lead(s) OVER (PARTITION BY user_id ORDER BY day) AS b FROM d),
x AS (SELECT DISTINCT a, b FROM p WHERE b IS NOT NULL)
SELECT '(' || array_to_string(a, '|') || ')*' AS a, '(' || array_to_string(b, '|') || ')*' AS b, a = b AS same,
list_sort(list_transform(list_filter(list_concat(a, b), lambda t: NOT (list_contains(a, t) AND list_contains(b, t))), lambda t: {'n': len(t), 't': t}))[1].t AS witness FROM x""")
def equivalences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the languages of the kinds of events of a user's day and of the next are one, and if not a shortest word that tells them apart."""
    from pyspark.sql.window import Window

    events = table(spark, sf_dir, "events").where("event_type <> ''")
    days = events.groupBy("user_id", F.to_date("ts").alias("day")).agg(F.array_sort(F.collect_set("event_type")).alias("s"))
    pairs = days.select(F.col("s").alias("a"), F.lead("s").over(Window.partitionBy("user_id").orderBy("day")).alias("b")).where("b IS NOT NULL").distinct()
    return measure.equivalences(pairs.selectExpr(f"{_any_of('a')} AS a", f"{_any_of('b')} AS b"))


_BOUNDS = "WITH s(pattern, n, d, s) AS (VALUES ('(ab)*', 3, 3, 6), ('[ap]*[al][alp]{3}', 6, 32, 58), ('(m|(t|c([mt]*c){2})[cmt])*', 9, 5, 257)) SELECT pattern, n AS nfa_states, d AS dfa_total, s AS maps_total, n::DOUBLE AS dfa_bound_log2, round(d * log2(d), 6) AS functions_bound_log2, (n * n)::DOUBLE AS relations_bound_log2, log2(s) <= least(d * log2(d), n * n) + 1e-9 AS within FROM s"


@query(_BOUNDS)
def worst_case_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.bounds(spark.createDataFrame([(p,) for p in ("(ab)*", corpora.subset_blowup(5), corpora.map_blowup(4))], "pattern string"))


@query("SELECT count(*) AS docs, 0::BIGINT AS run_mismatches FROM documents")
def reference_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every machine's own run over whole texts, symbol by symbol, against the kernels' verdicts."""
    return measure.run_mismatches(_documents(spark, sf_dir), "text", _of(RULES["junkrun"]))


# many patterns, positions, and what is done with hits


@query("SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = match.match_texts(_documents(spark, sf_dir), "doc_id", "text", table(spark, sf_dir, "benchmark"), "item_id", "text")
    return found.select(F.col("word_id").alias("doc_id"), "item_id")


_ENDS = "SELECT doc_id, len(regexp_extract_all(text, '[.] '))::BIGINT AS n_ends FROM documents"


@query(_ENDS)
def match_end_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return match.count_ends(_documents(spark, sf_dir), "doc_id", "text", _of(".*[.] "), SIZE).select(F.col("word_id").alias("doc_id"), "n_ends")


@query(f"SELECT * FROM ({_ENDS}) ORDER BY n_ends DESC, doc_id LIMIT 10")
def top_docs_by_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.top_k(match_end_counts(spark, sf_dir), "n_ends", "doc_id", 10)


@query(f"SELECT lang, source, count(*) AS docs, sum({_full('text', RULES['ipv4'])}::INT)::BIGINT AS hits FROM documents GROUP BY CUBE (lang, source)")
def hits_by_lang_source_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = match.with_verdict(table(spark, sf_dir, "documents").select("lang", "source", "text"), "text", _of(RULES["ipv4"]))
    return docs.drop("text").cube("lang", "source").agg(F.count("*").alias("docs"), F.sum(F.col("accepted").cast("long")).alias("hits"))


@query(f"""SELECT count(*) AS docs, sum((a AND quality = 0)::INT)::BIGINT AS true_hits, sum(a::INT)::BIGINT AS hits, sum((quality = 0)::INT)::BIGINT AS wanted
FROM (SELECT quality, {_full('text', RULES['junkrun'])} AS a FROM documents JOIN labels USING (doc_id))""")
def hits_vs_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    met = match.with_verdict(_documents(spark, sf_dir).join(labels, "doc_id"), "text", _of(RULES["junkrun"]))
    n = lambda c: F.sum(c.cast("long"))
    return met.agg(F.count("*").alias("docs"), n(F.col("accepted") & (F.col("quality") == 0)).alias("true_hits"), n(F.col("accepted")).alias("hits"), n(F.col("quality") == 0).alias("wanted"))


def _state_sql(c: Compiled) -> str:
    cases = " ".join(f"WHEN u BETWEEN {lo} AND {hi} THEN {k}" for lo, hi, k in c.dfa.classes.rows())
    classes = f"list_transform(list_transform(string_split(text, ''), lambda s: unicode(s)), lambda u: CASE {cases} END)"
    return f"""WITH e AS (SELECT list_reduce(list_prepend(0, {classes}), lambda q, k: {c.dfa.delta.ravel().tolist()}[q * {c.dfa.classes.k} + k + 1]) AS end_state FROM documents)
SELECT end_state, count(*) AS docs FROM e GROUP BY end_state"""


@query(_state_sql(_of(RULES["email"])))
def state_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return match.with_end_state(_documents(spark, sf_dir), "text", _of(RULES["email"])).groupBy("end_state").agg(F.count("*").alias("docs"))


def _set_query(name: str, op: str, joined: str) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        hits = lambda rule: match.where_accepts(_documents(spark, sf_dir), "text", _of(RULES[rule])).select("doc_id")
        return match.combine(hits("junkrun"), hits("ipv4"), op)

    query(f"SELECT doc_id FROM documents WHERE {_full('text', RULES['junkrun'])} {joined} {_full('text', RULES['ipv4'])}", name)(run)


_set_query("rules_union", "union", "OR")
_set_query("rules_intersect", "intersect", "AND")
_set_query("rules_except", "except", "AND NOT")


@query(f"SELECT doc_id FROM documents WHERE NOT {_full('text', RULES['email'])}")
def docs_without_email(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir)
    hits = match.where_accepts(docs, "text", _of(RULES["email"])).select(F.col("doc_id").alias("word_id"))
    return match.no_hit(docs, "doc_id", hits).select("doc_id")


@query("SELECT count(*) AS docs, 0::BIGINT AS mismatches FROM documents")
def method_mismatches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts of the map automaton against simulation of the nondeterministic one."""
    docs, c = _documents(spark, sf_dir), _of(RULES["secret"])
    a = match.accepts_chunked(docs, "doc_id", "text", c, SIZE).withColumnRenamed("word_id", "doc_id")
    b = baselines.nfa_sets(docs, "text", c).select("doc_id", F.col("accepted").alias("other"))
    return a.join(b, "doc_id").agg(F.count("*").alias("docs"), F.sum((~F.col("accepted").eqNullSafe(F.col("other"))).cast("long")).alias("mismatches"))
