"""Chunks, folds, baselines, sources, functions and streams on Spark."""

import random
import re

import pytest
from pyspark.sql import functions as F

from mapmatch.functions import sqlapi
from mapmatch.automata import nfa
from mapmatch.operators import baselines, chunks, distributed, fold, match, measure
from mapmatch.operators.match import Compiled
from mapmatch.plans import corpora
from mapmatch.sources import sinks, tables
from mapmatch.streaming import stream

P = "(a|b)*abb(é|c)?"
ROWS = [(1, "abb"), (2, "aabbé"), (3, ""), (4, None), (5, "ab" * 300 + "b"), (6, "ba"), (7, "abbc😀"), (8, "b" * 999 + "abb")]
WANT = {i: None if t is None else re.fullmatch(P, t) is not None for i, t in ROWS}


@pytest.fixture(scope="module")
def words(spark):
    return spark.createDataFrame(ROWS, "id long, text string").repartition(3)


def got(df, key="id", value="accepted"):
    return {r[key]: r[value] for r in df.collect()}


@pytest.mark.parametrize("kind", ["auto", "maps", "lazy", "speculate", "merge", "halve", "relations", "lazy_relations"])
@pytest.mark.parametrize(("size", "how", "options"), [(1, "tree", {"fanout": 3, "rounds": 4}), (7, "in_order", {"fanout": 5, "rounds": 2}), (64, "tree", {}), (4096, "in_order", {"longest": 1000})])
def test_chunked_kinds(words, kind, size, how, options):
    assert got(match.accepts_chunked(words, "id", "text", Compiled(P), size, how, kind, **options), "word_id") == WANT


def test_planner_avoids_the_deterministic_automaton(spark):
    p = ".*a.{18}"
    rows = [(i, "b" * i + "a" + "c" * (18 + i % 2)) for i in range(12)] + [(50, ""), (51, None)]
    found = got(match.accepts_chunked(spark.createDataFrame(rows, "id long, text string"), "id", "text", p, 5), "word_id")
    assert found == {i: None if t is None else re.fullmatch(p, t) is not None for i, t in rows}


def test_python_scan_is_planned_once(words):
    """The chunks are scanned by one Python node, whatever the fold, and nothing runs while the plan is made."""
    for how in ("in_order", "tree"):
        found = match.accepts_chunked(words, "id", "text", Compiled(P), 7, how, "maps")
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert plan.count("MapInArrow") + plan.count("ArrowEvalPython") == 1, plan


def test_words_of_rows_that_no_task_joins(spark):
    """A key with most of the rows, null keys, null symbols and single rows, against whole words."""
    rng = random.Random(4)
    rows = [(1 if i % 4 else [None, 2, 3, 4][i // 4 % 4], i, rng.choice("abc") if i % 17 else None) for i in range(5000)]
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "k int, t int, s string").repartition(6)
    for p in ("(a|b|c)*abb(a|b|c)*", "[^c]*c(a|b|c)*b", "(a|b|c){1187}"):
        want = {k: re.fullmatch(p, "".join(s or "" for q, _, s in sorted(rows, key=lambda r: r[1]) if q == k)) is not None for k in (None, 1, 2, 3, 4)}
        assert got(match.accepts_rows(df, "k", ["t"], F.col("s"), p), "k") == want


def test_many_segments_of_one_word(spark):
    """More segments than one row should gather, in random order: cells first, then the word; all folds agree."""
    c, n = Compiled(corpora.loop(1)), 130_000
    images = [list(map(int, c.maps.image(c.maps.run([int(c.dfa.classes.table[ord(x)])])))) for x in "05"]
    pick = F.when(F.col("id") % 2 == 0, F.array(*[F.lit(q) for q in images[0]])).otherwise(F.array(*[F.lit(q) for q in images[1]]))
    segments = spark.range(n).select(F.lit(7).alias("word_id"), F.col("id").cast("int").alias("lo"), F.col("id").cast("int").alias("hi"), pick.cast("array<int>").alias("image")).repartition(16, F.xxhash64("lo"))
    assert got(fold.fold_in_order(segments), "word_id", "end_state") == {7: 0}
    assert {r["word_id"]: r["image"][0] for r in fold.fold_tree(segments, 1024).collect()} == {7: 0}
    assert fold.carry_in(segments, cell=1000).where("entry <> lo % 2").count() == 0


def test_row_plans(words):
    c = Compiled(P)
    for plan in ("dfa_rows", "map_rows"):
        assert got(match.with_verdict(words, "text", c, plan=plan)) == WANT
    assert got(baselines.nfa_sets(words, "text", c)) == WANT
    assert got(baselines.dfa_rows(words, "text", c)) == WANT
    assert got(baselines.query_parallel(words, "text", c, 4)) == WANT
    assert got(words.select("id", match.accepts_expression(F.col("text"), c).alias("accepted"))) == WANT
    assert got(words.select("id", baselines.spark_rlike(F.col("text"), P).alias("accepted"))) == WANT
    assert {r["id"] for r in match.where_accepts(words, "text", c).collect()} == {i for i, v in WANT.items() if v}
    assert {r["id"] for r in match.where_accepts(words, "text", c, negate=True).collect()} == {i for i, v in WANT.items() if v is False}
    assert measure.mismatches(match.with_verdict(words, "text", c), baselines.nfa_sets(words, "text", c), "id") == 0


def test_cuts_and_gaps(spark, words):
    c = Compiled(P)
    some = words.where("text IS NOT NULL")
    pieces = chunks.cut_at(some, "id", "text", [0, 2, 2, 3, 500, 10_000]).repartition(5)
    found = match.accepts_segments(match.scan_chunks(pieces, c.scanner("maps")), c)
    assert got(found, "word_id") == {i: v for i, v in WANT.items() if v is not None}
    gap = spark.createDataFrame([(1, 0, "a"), (1, 2, "b")], "word_id long, chunk_ix int, payload string")
    assert [tuple(r) for r in fold.check_gaps(gap).collect()] == [(1, 2)]
    with pytest.raises(Exception, match="chunk gap"):
        match.accepts_segments(match.scan_chunks(gap, c.scanner("maps")), c).collect()


def test_folds_agree_for_many_small_segments(spark):
    c = Compiled(corpora.loop(3))
    text = "000999" * 200
    df = spark.createDataFrame([(1, text), (2, text + "0")], "id long, text string")
    pieces = chunks.chunk_words(df, "id", "text", 5).repartition(7)
    maps = fold.attach_images(match.scan_map_ids(pieces, c.maps), c.maps).select("word_id", F.col("chunk_ix").alias("lo"), F.col("chunk_ix").alias("hi"), "image")
    tree = {r["word_id"]: r["image"][0] for r in fold.fold_tree(maps, 4, 5).collect()}
    assert tree == got(fold.fold_in_order(maps), "word_id", "end_state") == got(fold.fold_in_order(maps, 0, 10, 3), "word_id", "end_state")
    for cell in (7, 10_000):
        entry = {(r["word_id"], r["lo"]): r["entry"] for r in fold.carry_in(maps, 0, cell).collect()}
        assert all(entry[1, i] == c.dfa.run([int(c.dfa.classes.table[ord(x)]) for x in text[: 5 * i]]) for i in range(240)) and len(entry) == 481


def test_relation_trees_are_the_product_in_order(spark):
    c = Compiled("(ab|ba)*a?")
    text = "abba" * 40
    pieces = chunks.chunk_words(spark.createDataFrame([(1, text), (2, text + "a"), (3, "bb")], "id long, text string"), "id", "text", 3).repartition(5)
    segments = match.scan_chunks(pieces, c.scanner("relations"), fold_runs=False)
    assert segments.count() == 54 + 54 + 1
    want = {i: sorted(nfa.bits(c.nfa.run([int(c.nfa.classes.table[ord(x)]) for x in t]))) for i, t in ((1, text), (2, text + "a"), (3, "bb"))}
    for in_order, fanout, rounds in ((True, 4, 3), (False, 4, 3), (False, 1 << 15, 2)):
        assert got(fold.fold_relations(segments, [0], in_order, fanout, rounds), "word_id", "end_states") == want


def test_match_ends(words):
    found = {r["word_id"]: r["n_ends"] for r in match.count_ends(words, "id", "text", ".*ab", 7).collect()}
    assert found == {i: 0 if t is None else t.count("ab") for i, t in ROWS}


def test_pattern_sets(spark, words):
    rules = [(1, ".*bb.*"), (2, "b.*"), (3, P)]
    want = {(i, k) for i, t in ROWS if t is not None for k, p in rules if re.fullmatch(p, t, re.S)}
    for cells in (8_000_000, 10):
        assert {tuple(r) for r in match.match_corpus(words, "id", "text", rules, cells=cells).collect()} == want
    texts = spark.createDataFrame([(10, "bb"), (20, "abb"), (30, "zz"), (40, None), (50, "é")], "name long, t string")
    found = {tuple(r) for r in match.match_texts(words, "id", "text", texts, "name", "t", block=2).collect()}
    assert found == {(i, n) for i, t in ROWS if t is not None for n, x in ((10, "bb"), (20, "abb"), (30, "zz"), (50, "é")) if x in t}
    hits = match.match_corpus(words, "id", "text", rules[:1])
    assert match.any_hit(words, "id", hits).count() + match.no_hit(words, "id", hits).count() == len(ROWS)


def test_distributed_closure(spark):
    for p in ("(ab)*", corpora.loop(3)):
        c = Compiled(p)
        rows = distributed.close_distributed(spark, c.dfa).collect()
        assert {tuple(r["image"]) for r in rows} == {tuple(map(int, i)) for i in c.maps.images}
        assert sum(r["final"] for r in rows) == int(c.maps.final.sum())


def test_sources_and_sinks(spark, tmp_path):
    c = Compiled("([0-4]{5}[5-9]{5})*", unit="byte")
    text = "0123456789" * 1000
    (tmp_path / "a.txt").write_text(text)
    (tmp_path / "b.txt").write_text(text + "5")
    pieces = tables.byte_ranges(spark, f"{tmp_path}/a.txt,{tmp_path}/b.txt", 777, 2000)
    assert got(match.accepts_segments(match.scan_chunks(pieces, c.scanner("maps")), c), "word_id") == {0: True, 1: False}
    sinks.save_automaton(spark, c.maps, f"{tmp_path}/auto")
    again = sinks.load_automaton(spark, f"{tmp_path}/auto")
    assert (again.delta == c.maps.delta).all() and again.accepts([0] * 5 + [1] * 5) == c.maps.accepts([0] * 5 + [1] * 5)
    assert sinks.map_delta(spark, c.maps).count() == c.maps.size * c.dfa.classes.k
    assert tables.whole(spark, f"{tmp_path}/*.txt").count() == 2 and tables.binary(spark, f"{tmp_path}/*.txt").count() == 2 and tables.lines(spark, f"{tmp_path}/a.txt").count() == 1


def test_sql_functions(spark, words):
    sqlapi.register(spark, {"abb": P})
    words.createOrReplaceTempView("words")
    assert got(spark.sql("SELECT id, abb_accepts(text) AS accepted FROM words")) == WANT
    assert spark.sql("SELECT count(*) FROM compile_pattern('(ab)*')").first()[0] == 6
    assert [r[0] for r in spark.sql("SELECT pos FROM match_ends('xabab', '.*ab') ORDER BY pos").collect()] == [3, 5]
    c = Compiled("(ab)*")
    parts = spark.createDataFrame([(i, w) for i, w in enumerate(("aba", "baba", "bab", "abab"))], "ix int, w string").select("ix", sqlapi.map_function(c)("w").alias("image"))
    both = parts.groupBy().agg(sqlapi.compose_ordered(F.col("ix"), F.col("image")).alias("a")).first()["a"]
    assert both == [0, 2, 2] == parts.groupBy(F.lit(1)).agg(sqlapi.compose_group("ix", "image").alias("b")).first()["b"]


def test_segments_in_any_order():
    c = Compiled(P)
    text, rng = "abab" * 20 + "abb", random.Random(5)
    pieces = [(i, text[i * 3 : i * 3 + 3]) for i in range(-(-len(text) // 3))]
    rng.shuffle(pieces)
    s = fold.Segments()
    for n, (i, w) in enumerate(pieces):
        assert s.complete(len(pieces)) is None or n == len(pieces)
        s.add(i, i, list(map(int, c.maps.image(c.maps.run([int(c.dfa.classes.table[ord(x)]) for x in w])))))
    assert c.dfa.final[s.complete(len(pieces))[0]]
    with pytest.raises(ValueError, match="overlap"):
        s.add(0, 0, [0])


def test_two_stacks():
    c, rng = Compiled(P), random.Random(2)
    images = [list(map(int, c.maps.image(rng.randrange(c.maps.size)))) for _ in range(40)]
    window = stream.TwoStacks(5, c.dfa.size)
    for i, image in enumerate(images):
        out = list(range(c.dfa.size))
        for g in images[max(0, i - 4) : i + 1]:
            out = [g[q] for q in out]
        assert window.push(image) == out


def test_stream_decides_what_the_batch_decides(spark, tmp_path):
    rng, rows = random.Random(1), []
    texts = {1: "abb" * 5, 2: "ab" * 9 + "b", 3: "ba" * 4, 4: "aabb"}
    for word, t in texts.items():
        pieces = [t[i : i + 2] for i in range(0, len(t), 2)]
        rows += [(word, i, len(pieces), p, 1_700_000_000 + word * 60 + i) for i, p in enumerate(pieces) if not (word == 4 and i == 1)]
    rows.append((9, 0, 2, "a", 1_800_000_000))
    rng.shuffle(rows)
    schema = "word_id long, chunk_ix int, chunks int, payload string, t long"
    df = spark.createDataFrame(rows, schema).select("word_id", "chunk_ix", "chunks", "payload", F.timestamp_seconds("t").alias("ts"))
    df.where("word_id <> 9").repartition(6).write.parquet(f"{tmp_path}/in")
    df.where("word_id = 9").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    source = spark.readStream.schema(df.schema).parquet(f"{tmp_path}/in")
    q = stream.match_stream(source, P, "1 hour").writeStream.format("memory").queryName("verdicts").outputMode("append").option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    q.awaitTermination()
    found = {r["word_id"]: r["status"] for r in spark.table("verdicts").collect()}
    want = {w: "accepted" if re.fullmatch(P, t) else "rejected" for w, t in texts.items() if w != 4}
    assert {w: s for w, s in found.items() if w < 4} == want and found.get(4) == "undecided"


def test_state_asof(spark):
    states = spark.createDataFrame([(1, 10, 5), (1, 20, 6)], "k long, t long, state int")
    probes = spark.createDataFrame([(1, 5), (1, 10), (1, 25), (2, 1)], "k long, t long")
    found = {(r["k"], r["t"]): r["state"] for r in stream.state_asof(states, probes, "k", "t").collect()}
    assert found == {(1, 5): None, (1, 10): 5, (1, 25): 6, (2, 1): None}


def test_index_rows_and_one_word_of_all_rows(spark):
    df = spark.range(1000).select((F.col("id") * 7 % 1000).alias("v"))
    rows = chunks.index_rows(df, ["v"], size=64)
    assert all(r["v"] == r["i"] for r in rows.collect())
    pieces = chunks.pack_one(rows, (F.col("i") % 10).cast("string")).orderBy("chunk_ix").collect()
    assert [r["chunk_ix"] for r in pieces] == list(range(len(pieces))) and "".join(r["payload"] for r in pieces) == "0123456789" * 100
    assert all(len(r["payload"]) <= 64 for r in pieces) and [r["offset"] for r in pieces] == [sum(len(x["payload"]) for x in pieces[:i]) for i in range(len(pieces))]
    # batches that end no piece, down to a single row
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 9)
    try:
        again = chunks.pack_one(rows, (F.col("i") % 10).cast("string")).orderBy("chunk_ix").collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert again == pieces
    plan = chunks.pack_one(rows, F.lit("x"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "partial_count" in plan  # the counts of the ranges alone


def test_corpus_reports(spark):
    rows = [(0, "x", "(ab)*", "full"), (1, "x", r"(a)\1", "full"), (2, "y", "abc", "search"), (3, "y", corpora.map_blowup(4), "full")]
    report = measure.corpus_sizes(spark.createDataFrame(rows, "pattern_id int, family string, pattern string, mode string"))
    by = {r["pattern_id"]: r for r in report.collect()}
    assert (by[0]["maps_live"], by[1]["status"], by[3]["over_cube"]) == (5, "unsupported", True)
    assert {r["family"]: r["used"] for r in measure.size_classes(report).collect()} == {"x": 1, "y": 2, None: 3}


def test_size_study_has_whole_passages_and_no_low_cap(spark, tmp_path, monkeypatch):
    from mapmatch.automata.pattern import escape
    from mapmatch.plans import workloads

    text = "In the winter (of 1902) the river froze as far as the bridge; nobody at the house remembered a longer, harsher season than that."
    spark.createDataFrame([(1, text)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([("a b", "T", "B#1")], "p_name string, p_type string, p_brand string").write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame([("https://a.example.com/b/1",)], "url string").write.parquet(f"{tmp_path}/pages.parquet")
    patterns = corpora.corpus(spark, str(tmp_path))
    found = {(r["family"], r["pattern"]) for r in patterns.collect()}
    assert ("passage", f".*{escape(text)}.*") in found and ("gap4", ".*In.*the.*winte.*of.*") in found
    assert measure.STUDY_MAPS > 1_001_000
    whole = measure.corpus_sizes(patterns.where("family = 'passage'")).first()
    assert whole["status"] == "ok" and whole["over_10k"]
    caps = []
    monkeypatch.setattr(measure, "corpus_sizes", lambda rows, max_maps=measure.STUDY_MAPS: caps.append(max_maps) or rows.select("pattern_id"))
    workloads._report(spark, str(tmp_path))
    assert caps == [measure.STUDY_MAPS]
