"""Every text operator against brute force, exact round trips or its SQL twin, on small tables with awkward rows."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import regex
import xxhash
from pyspark.sql import functions as F

from mapmatch.llm import components, language, mixing, packing, pii, queries, simhash, spotsigs, substring, token_files, topk, urls
from mapmatch.llm.expressions import literal_rows
from mapmatch.llm.tokens import Encoder

WORD = re.compile(r"[^\x20\x09-\x0D]+")
VOCAB = "the of and to in house river stone walks under bright morning le la de et dans maison fleuve der und die haus el los casa río".split()


def prose(rng, n):
    return " ".join(rng.choice(VOCAB) + rng.choice(["", "", "", ",", "."]) for _ in range(n))


def documents():
    """Rows of doc_id, text, lang, source: nulls, empties, a long text, near and exact copies, shared passages."""
    rng = random.Random(11)
    texts = [prose(rng, rng.randint(1, 400)) for _ in range(60)]
    passage = prose(rng, 80)
    for i in (3, 9, 12, 40):
        texts[i] = prose(rng, 20) + " " + passage + " " + prose(rng, rng.randint(0, 90))
    texts[20] = texts[5]
    texts[21] = texts[5]
    texts[22] = texts[6] + " end"
    texts += ["", None, " \n\t ", "x", "\u00a0\u2003", "...!!", prose(rng, 9000), "joe@site.com " * 3, "día 😀 Straße ÀÉ", None, "a\x1cb\x00c"]
    texts += [texts[3] + " tail", passage]
    langs = [["en", "fr", "de", None][i % 4] for i in range(len(texts))]
    sources = [["b", "a", None, "ü", "c", "a"][i % 6] for i in range(len(texts))]
    return [(i * 3, t, langs[i], sources[i]) for i, t in enumerate(texts)]


DOCS = documents()


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    """A folder of small tables with extra columns whose names clash with those the operators make."""
    folder = str(tmp_path_factory.mktemp("sf"))
    rows = [(*r, 7, "clash", [1.0], None) for r in DOCS]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, size int, key string, fp array<double>, n_chars long").repartition(5).write.parquet(f"{folder}/documents.parquet")
    urls_ = [
        "http://A.Example.net/en/x?q", "https://example.net/en/", "https://example.net/fr", "x://example.com/de/1#t", "http://sub.example.com/deep/de/", "ftp://org/fr/a", "http://o.org/fr/", "http://net", "http://net/",
        None, "", "no scheme", "http://evilnet/", "http://a..net/?x", "http://b.net:80/", "a://b://c.net/", "http://x.net/" + "a/" * 500, "http://" + "s." * 300 + "net/en/", "HTTP://EXAMPLE.NET/EN/", "://net/", "http://example.net/en/",
    ]
    spark.createDataFrame([(i if i else None, u, "h", "r") for i, u in enumerate(urls_)] + [(5, urls_[5], "h", "r")], "page_id long, url string, host string, rule string").write.parquet(f"{folder}/pages.parquet")
    rng = np.random.default_rng(4)
    vectors = [(i, (rng.normal(size=8) * rng.choice([0.1, 1, 5])).astype(float).tolist(), 1) for i in range(400)]
    vectors[50] = (50, [0.0] * 8, 1)
    vectors[60] = (60, vectors[7][1], 1)
    vectors += [(400, None, 1), (401, [1.0, None, *[0.0] * 6], 1), (402, [float("nan")] * 8, 1), (403, [float("inf")] * 8, 1), (None, [9.0] * 8, 1), (450, [-1.0] * 8, 1)]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>, score int").write.parquet(f"{folder}/embeddings.parquet")
    return folder


@pytest.fixture(scope="module")
def empty(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("empty"))
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([], "page_id long, url string, html string").write.parquet(f"{folder}/pages.parquet")
    spark.createDataFrame([], "vec_id long, embedding array<float>, label int").write.parquet(f"{folder}/embeddings.parquet")
    return folder


def rows_of(df):
    return [tuple(r) for r in df.collect()]


@pytest.mark.parametrize("name", list(queries.QUERIES))
def test_empty_tables(spark, empty, name):
    assert queries.QUERIES[name](spark, empty).collect() == []


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_sql_twins_on_awkward_rows(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "embeddings"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet/*.parquet'")
    want = con.sql(queries.ORACLES[name])
    found = queries.QUERIES[name](spark, sf)
    assert sorted(found.columns) == sorted(want.columns)
    tidy = lambda rows: sorted((tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows), key=repr)
    assert tidy(rows_of(found.select(*want.columns))) == tidy(want.fetchall())


def test_url_rules_by_brute_force_and_without_broadcast(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    rules = [*queries.URL_RULES, ("net", "/e", "allow"), ("a..net", "/", "block"), ("net", "/a/a/a", "block")]
    table = literal_rows(spark, rules, ["host", "path", "verdict"])

    def judge(url):
        host = path = ""
        if url and "://" in url:
            rest = url.split("://", 1)[1]
            host = re.split("[/?#]", rest, maxsplit=1)[0]
            path = re.split("[?#]", rest[len(host) :], maxsplit=1)[0]
            host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
        fits = [(len(h + p), len(h), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=(0, 0, None, "allow"))
        return host, path, best[2], best[3]

    want = Counter((r["page_id"], r["url"], *judge(r["url"])) for r in pages.collect())
    for limit in (1000, 0):
        assert Counter(rows_of(urls.judge(pages, table, broadcast_rules=limit))) == want


def test_tokenizer_is_the_librarys():
    mine = Encoder(queries.TOKENIZER, keep=50)
    assert mine.by_word
    texts = [t for _, t, _, _ in DOCS] + ["don't it's <|endoftext|> x<|endoftext|>y", "<|ENDOFTEXT|> É<|EndOfText|>", "Ünï ÅÄ ß ẞ İ ΑΣ. × a×b ÷", "日本語 ab12 __ --", "a" * 3000, "ÀÉ... à.b. \x1c x\u2003y", "e\u0301 É"]
    for size in (500, 10**6):
        for lo, hi, ids, edges in mine.slices(pa.array(texts, pa.string()), size):
            for i in range(lo, hi):
                assert ids[edges[i - lo] : edges[i - lo + 1]].tolist() == mine.library.encode(texts[i] or "", add_special_tokens=False).ids


def test_other_tokenizer_files_go_to_the_library():
    mine = Encoder(queries.public_tokenizers.path("byte_bpe_50k.json"))
    assert not mine.by_word
    for text in ("Two  spaces, Ünï and <|endoftext|>", "", "día 😀"):
        assert mine.encode(text).tolist() == mine.library.encode(text, add_special_tokens=False).ids


def token_ids(text, end):
    return Encoder.of(queries.TOKENIZER).library.encode(text or "", add_special_tokens=False).ids + [end]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def test_packing(spark, sf):
    found = queries.QUERIES["op2_best_fit_packing"](spark, sf).collect()
    want = Counter()
    for i, t, _, _ in DOCS:
        ids = token_ids(t, 1)
        for p, s in enumerate(range(0, len(ids), 4096)):
            want[i, p, s, len(ids[s : s + 4096]), crc(ids[s : s + 4096])] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in found) == want
    check_sequences(found, 4096)
    bins = len({r["sequence_id"] for r in found})
    assert bins == packing.lower_bound(np.array([r["length"] for r in found]), 4096)


def check_sequences(rows, capacity):
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity


def test_repacking_rounds_and_repeated_rows(spark):
    rng = random.Random(2)
    rows = [(i // 2 if i % 7 else None, prose(rng, rng.choice([20, 40, 45, 55, 60]))) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    found = packing.pack(docs, queries.TOKENIZER, capacity=128, per_partition=30).collect()
    check_sequences(found, 128)
    assert sum(r["length"] for r in found) == sum(len(token_ids(t, 1)) for _, t in rows)
    lengths = np.array([r["length"] for r in found])
    assert len({r["sequence_id"] for r in found}) <= 1.1 * packing.lower_bound(lengths, 128)


def test_bounds_never_pass_the_best_packing():
    rng = np.random.default_rng(1)
    for _ in range(200):
        lengths = rng.integers(1, 20, rng.integers(0, 30))
        bound, (bins, _, used) = packing.lower_bound(lengths, 20), packing.best_fit_decreasing(lengths, 20)
        assert bound <= used and (not len(lengths) or np.bincount(bins, weights=lengths).max() <= 20)
    assert packing.lower_bound(np.array([11] * 5), 20) == 5 and packing.lower_bound(np.array([7] * 6), 20) == 3


def brute_spans(text):
    patterns = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]
    out = []
    for k, (kind, p) in enumerate(patterns):
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m[0])
            luhn = sum(x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0
            good = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else False, "card": 14 <= len(d) <= 19 and luhn, "phone": 10 <= len(d) <= 15}[kind]
            if good:
                out.append((m.start(), k, m.end(), kind))
    return sorted(out)


def pii_texts():
    rng = random.Random(9)
    alphabet = ["@", ".", "a", "b1", "-", "+", "1", "25", "4111 1111 1111 1111", " ", "(", ")", "é", "😀", "192.168.1.1", "+1 (743) 555-3824", "x_y@z.de", "999.1.1.1", "5500-0000-0000-0004", "\n"]
    fuzz = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 40))) for _ in range(300)]
    return [*fuzz, None, "", "a@b.c_d@e.f", "a@b.c@d.e", "1.2.3.4.5.6.7.8", "+12", "+1" + " " * 2000 + "2", "1 " * 3000, "a." * 3000 + "@x.y", "@" * 500, "4111111111111111" * 3, "a@b" + ".c" * 5000]


def test_personal_data_base_spans(spark):
    texts = pii_texts()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r["doc_id"]: r for r in pii.find(df).collect()}
    for i, t in enumerate(texts):
        want = brute_spans(t or "")
        line = ",".join(f"{kind}:{a}:{b}" for a, _, b, kind in want)
        assert found[i]["base_sha256"] == hashlib.sha256(line.encode()).hexdigest(), t
        assert [found[i][f"n_{k}"] for k in pii.KINDS] == [sum(w[3] == k for w in want) for k in pii.KINDS]
        assert set(filter(None, line.split(","))) <= set(found[i]["spans"].split(","))


def test_personal_data_added_and_redacted(spark):
    texts = {
        1: ("write to joe (at) example (dot) com please", "write to [EMAIL] please"),
        2: ("tel. (030) 555-1234 today", "tel. [PHONE] today"),
        3: ("card 4111.1111.1111.1111 ok", "card [CARD] ok"),
        4: ("seen on 12.03.2020 at 12:30:45 and 2020-01-05", "seen on 12.03.2020 at 12:30:45 and 2020-01-05"),
        5: ("they met at noon. then we left", "they met at noon. then we left"),
        6: ("😀 a@b.com é 10.0.0.1", "😀 [EMAIL] é [IP]"),
    }
    df = spark.createDataFrame([(i, t, len(t), 3) for i, (t, _) in texts.items()] + [(9, None, None, 4)], "doc_id long, text string, n_chars long, _spans long").drop("_spans")
    found = {r["doc_id"]: r for r in pii.redact(df).collect()}
    assert {i: found[i]["text"] for i in texts} == {i: want for i, (_, want) in texts.items()}
    assert all(found[i]["n_chars"] == len(want) for i, (_, want) in texts.items()) and found[9]["text"] is None


@pytest.mark.parametrize("lengths", [1, 4, 1024])
def test_top_k_blocks_and_coordinates(spark, sf, lengths):
    vectors = topk.integer_vectors(spark.read.parquet(f"{sf}/embeddings.parquet"))
    data = {r["vec_id"]: np.array(r["v"]) for r in vectors.collect()}
    found = topk.top_k(vectors, vectors.where("vec_id % 9 = 0"), 7, block=37, query_block=11, lengths=lengths).collect()
    want = set()
    for q, x in data.items():
        if q % 9 == 0:
            ranked = sorted(((-int(x @ y), i) for i, y in data.items() if i != q))[:7]
            want |= {(q, n, i, -s) for n, (s, i) in enumerate(ranked, 1)}
    assert {(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in found} == want


def test_top_k_leaves_out_what_length_rules_out(spark, monkeypatch):
    """Blocks of short vectors are not sent to queries that longer ones already answer, and nothing is lost."""
    rng = np.random.default_rng(9)
    rows = [(i, np.floor(rng.normal(size=6) * (100_000 if i < 600 else 10)).tolist()) for i in range(6000)]
    df = spark.createDataFrame(rows, "vec_id long, v array<double>")
    met = []
    original = topk.stored
    monkeypatch.setattr(topk, "stored", lambda some, name: met.append((name, out := original(some, name))) or out)
    found = topk.top_k(df, df.where("vec_id % 50 = 0 AND vec_id < 600"), 5, block=500)
    by = defaultdict(list)
    for r in found.collect():
        by[r["query_id"]].append((r["rank"], r["vec_id"]))
    for q, ranks in by.items():
        best = sorted(((-np.dot(rows[q][1], v), i) for i, v in rows if i != q))[:5]
        assert [i for _, i in sorted(ranks)] == [i for _, i in best]
    pairs = [df for name, df in met if name == "pairs"][0]
    assert pairs.count() <= 3 and len(by) == 12


def test_top_k_beyond_doubles_and_fewer_than_k(spark):
    big = 2**30
    df = spark.createDataFrame([(0, [float(big), 1.0]), (1, [1.0, float(big)]), (2, [1.0, float(big) - 1])], "vec_id long, v array<double>")
    found = topk.top_k(df, df.where("vec_id = 0")).collect()
    assert [(r["vec_id"], r["score"]) for r in sorted(found, key=lambda r: r["rank"])] == [(1, 2 * big), (2, 2 * big - 1)]


def test_pii_added_spans_on_unseen_examples(spark):
    """Precision and recall of the spans that the model adds, on generated examples of a seed that training has not seen."""
    rows = pii.examples(seed=1234, each=40)
    docs = [(i, f"We saw this. {before}{span}{after} End of it.") for i, (_, span, before, after, _) in enumerate(rows)]
    found = {r["doc_id"]: r for r in pii.find(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    right = wrong = wanted = 0
    for i, (kind, span, before, _, label) in enumerate(rows):
        start = len("We saw this. " + before)
        spans = [x.split(":") for x in found[i]["spans"].split(",") if x]
        base = sum(found[i][f"n_{k}"] for k in pii.KINDS)
        hit = any(k == kind and int(a) < start + len(span) and start < int(b) for k, a, b in spans)
        if base:
            continue
        wanted += label
        right += label and hit
        wrong += (not label) and bool(spans)
    assert wanted > 100 and right / max(1, right + wrong) > 0.9 and right / wanted > 0.6, (right, wrong, wanted)


def test_pii_many_spans_in_one_text(spark):
    """A text with thousands of spans keeps them all, in order."""
    n = 3000
    text = " ".join(f"a{i}@b.org" for i in range(n))
    row = pii.find(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()
    spans = row["spans"].split(",")
    assert row["n_email"] == n == len(spans) and spans[0] == "email:0:8" and spans[-1].endswith(f":{len(text)}")


def test_mix_reaches_its_targets(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plan = mixing.plan(docs).collect()
    by = defaultdict(list)
    for r in plan:
        assert r["taken"] <= 2 * r["size"]
        by[r["source"]].append(r)
    total = sum(r["size"] for r in plan)
    assert abs(sum(rs[0]["target"] for rs in by.values()) - 1.5 * total) < 1e-6 * total
    for rs in by.values():
        assert abs(sum(r["taken"] for r in rs) - rs[0]["target"]) < 1
    assert sorted(map(tuple, plan), key=repr) == sorted(map(tuple, mixing.plan(docs.repartition(3)).collect()), key=repr)


def test_mixed_documents_hold_the_words_taken(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    taken = sum(r["taken"] for r in mixing.plan(docs).collect())
    mixed = mixing.mix(docs)
    assert mixed.columns == docs.columns
    longest = Counter()  # each source comes within half of one document of what the plan takes
    for _, t, _, source in DOCS:
        longest[source] = max(longest[source], len(WORD.findall(t or "")))
    assert abs(sum(len(WORD.findall(r["text"])) for r in mixed.collect()) - taken) <= sum(longest.values()) / 2
    twice = docs.unionByName(docs)
    again = sum(r["taken"] for r in mixing.plan(twice).collect())
    assert abs(sum(len(WORD.findall(r["text"])) for r in mixing.mix(twice).collect()) - again) <= sum(longest.values()) / 2


def brute_signatures(text):
    common, words = set(spotsigs.ANCHORS), [w for w in re.split(r"[^\w]+|_", text.lower()) if w]
    content = [(i, w) for i, w in enumerate(words) if w not in common]
    out = set()
    for i, w in enumerate(words):
        chain = [c for j, c in content if j > i][:3]
        if w in common and len(chain) == 3:
            out.add((w, *chain))
    return out


def test_spot_signatures(spark, sf):
    found = {r["doc_id"]: r for r in queries.QUERIES["op6_spotsigs"](spark, sf).collect()}
    line = sorted(((i, t or "") for i, t, _, _ in DOCS), reverse=True)
    same = lambda a, b: (len(a & b) / len(a | b)) if a or b else None
    for k, (i, t) in enumerate(line):
        after = line[(k + 1) % len(line)][1]
        gone = len(t) // 3
        edited = t[: len(t) - gone] + after[:gone]
        r = found[i]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        a, b, c = brute_signatures(t), brute_signatures(edited), brute_signatures(after)
        if a and b:
            assert r["near_edited"] == pytest.approx(same(a, b)) and len(r["fingerprint"]) == 8 * len(a)
        if a and c:
            assert r["near_next"] == pytest.approx(same(a, c))
        if t == after:
            assert r["near_next"] == 1
    prints = defaultdict(set)
    for i, t in line:
        prints[t].add(found[i]["fingerprint"])
    assert all(len(p) == 1 for p in prints.values()) and len({p for s in prints.values() for p in s}) >= len(prints) - 1


def test_neighbours_over_many_ranges(spark, monkeypatch):
    monkeypatch.setattr(spotsigs, "_ROWS_PER_RANGE", 7)
    rng = random.Random(8)
    rows = [(rng.choice([rng.randrange(10**12), 5, None]), f"t{i}") for i in range(150)] + [(5, "t1")] * 3
    found = spotsigs.with_next(spark.createDataFrame(rows, "doc_id long, text string")).where("closing = 0").collect()
    assert Counter((r["doc_id"], r["text"]) for r in found) == Counter(rows)
    key = lambda r: (r["doc_id"] is None, -(r["doc_id"] or 0), -r["h"])
    line = sorted(found, key=key)
    for a, b in zip(line, [*line[1:], line[0]], strict=True):
        assert a["next_text"] == b["text"] or sum(key(x) == key(a) for x in line) > 1


def test_near_pairs_by_signatures(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    pairs, members = spotsigs.near_pairs(docs, 0.5)
    sets = {i: brute_signatures(t or "") for i, t, _, _ in DOCS}
    of = {r["doc_id"]: r["class_id"] for r in members.collect()}
    found = {(r["a"], r["b"]) for r in pairs.collect()}
    for i, a in sets.items():
        for j, b in sets.items():
            if i < j and a and b and a != b and len(a & b) / len(a | b) >= 0.5:
                assert tuple(sorted((of[i], of[j]))) in found


def test_token_files(spark, sf):
    found = sorted(queries.QUERIES["op7_token_files"](spark, sf).collect())
    at = 0
    for r, (i, t, _, _) in zip(found, DOCS, strict=True):
        ids = token_ids(t, 2)
        assert tuple(r) == (i, at, len(ids), crc(ids))
        at += len(ids)


def test_token_files_in_many_shards(spark, tmp_path):
    rng = random.Random(3)
    rows = [(rng.choice([None, i % 9, i]), prose(rng, rng.randint(0, 50))) for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    manifest = token_files.write(docs, queries.TOKENIZER, str(tmp_path), shard_tokens=100)
    found = sorted(token_files.read(manifest, str(tmp_path)).collect(), key=lambda r: r["start"])
    assert Counter((r["doc_id"], tuple(np.frombuffer(r["ids"], "<u4").tolist())) for r in found) == Counter((i, tuple(token_ids(t, 2))) for i, t in rows)
    ids = [r["doc_id"] for r in found]
    assert ids == sorted(ids, key=lambda x: (x is not None, x or 0)) and found[0]["start"] == 0
    assert all(a["start"] + a["n_tokens"] == b["start"] for a, b in zip(found, found[1:], strict=False))


def test_byte_code_round_trip():
    rng = np.random.default_rng(0)
    for n in (0, 1, 3, 4, 1001):
        values = rng.integers(0, 1 << 32, n, dtype=np.uint64) >> rng.integers(0, 32, n).astype(np.uint64)
        control, data = token_files.encode(values)
        assert (token_files.decode(control, data, n) == values).all() and len(control) == -(-n // 4)


def brute_fingerprint(text):
    words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes)) if hashes else 0


def brute_components(prints, bits):
    ids = sorted(prints)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for n, i in enumerate(ids):
        for j in ids[n + 1 :]:
            if (prints[i] ^ prints[j]).bit_count() <= bits and (a := find(i)) != (b := find(j)):
                root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_simhash(spark, sf):
    prints = {i: brute_fingerprint(t) for i, t, _, _ in DOCS}
    comp = brute_components(prints, 4)
    found = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in queries.QUERIES["op8_simhash"](spark, sf).collect()}
    assert found == {i: (f"{p:016x}", comp[i]) for i, p in prints.items()}
    kept = simhash.representatives(spark.read.parquet(f"{sf}/documents.parquet"))
    assert {r["doc_id"] for r in kept.collect()} == set(comp.values()) and "size" in kept.columns


@pytest.mark.parametrize("group", [5, 8192])
def test_simhash_links_of_planted_fingerprints(spark, group):
    rng = random.Random(6)
    prints = {}
    for c in range(40):
        base = rng.getrandbits(64)
        for _ in range(rng.choice([1, 3, 30])):
            x = base
            for b in rng.sample(range(64), rng.randint(0, 3)):
                x ^= 1 << b
            prints[len(prints)] = x
            if c < 5:
                base = x
    distinct = sorted(set(prints.values()))
    df = spark.createDataFrame([(simhash._signed(x),) for x in distinct], "fp long")
    roots = {r["node"]: r["root"] for r in components.connected(simhash.links(df, 4, group)).collect()}
    comp = brute_components(dict(enumerate(distinct)), 4)
    groups = lambda of: {frozenset(v) for v in of.values()}
    mine, want = defaultdict(set), defaultdict(set)
    for n, x in enumerate(distinct):
        mine[roots.get(simhash._signed(x), simhash._signed(x))].add(x)
        want[comp[n]].add(x)
    assert groups(mine) == groups(want)


def test_simhash_nulls_and_repeated_ids(spark):
    df = spark.createDataFrame([(None, "a b c d e"), (4, "a b c d e"), (4, "a b c d e"), (None, "z y x"), (2, None), (3, "")], "doc_id long, text string")
    found = Counter((r["doc_id"], r["component_id"]) for r in simhash.near_duplicates(df).collect())
    assert found == Counter({(None, 4): 1, (4, 4): 2, (None, None): 1, (2, 2): 1, (3, 2): 1})
    assert Counter(r["doc_id"] for r in simhash.representatives(df).collect()) == Counter({4: 1, None: 1, 2: 1})


@pytest.mark.parametrize(("segment_blocks", "bucket_bytes"), [(substring.SEGMENT_BLOCKS, substring.BUCKET_BYTES), (3, 5000)])
def test_substring_with_one_segment_and_many(spark, sf, segment_blocks, bucket_bytes):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    words = {i: WORD.findall(t or "") for i, t, _, _ in DOCS}
    first = {}
    for i in sorted(words):
        for s in range(len(words[i]) - 49):
            first.setdefault(tuple(words[i][s : s + 50]), i)
    found = {r["doc_id"]: r for r in substring.remove_repeats(docs, segment_blocks=segment_blocks, bucket_bytes=bucket_bytes).collect()}
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("mapmatch_")]
    gone = 0
    for i, w in words.items():
        cover = set()
        for s in range(len(w) - 49):
            if first[tuple(w[s : s + 50])] < i:
                cover |= set(range(s, s + 50))
        assert (found[i]["n_words"], found[i]["n_removed"]) == (len(w), len(cover))
        assert found[i]["kept"] == " ".join(x for n, x in enumerate(w) if n not in cover)
        gone += len(cover)
    assert gone > 500


def test_substring_nulls_and_repeated_ids(spark):
    long = prose(random.Random(1), 120)
    df = spark.createDataFrame([(None, long), (7, long), (7, long), (7, long + " x"), (9, "y " + long)], "doc_id long, text string")
    found = sorted(((r["doc_id"] or 0, r["n_words"], r["n_removed"]) for r in substring.remove_repeats(df).collect()))
    assert found == [(0, 120, 0), (7, 120, 0), (7, 120, 0), (7, 121, 0), (9, 121, 120)]


def test_language_held_out_accuracy(spark):
    found = queries.QUERIES["op10_language_id"](spark, "/root/testdata/sf0.01")
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang", "text")
    rows = found.join(docs, "doc_id").where("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in rows]) > 0.98
    assert all((zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in rows)


def test_language_of_awkward_texts(spark, sf):
    found = {r["doc_id"]: r for r in queries.QUERIES["op10_language_id"](spark, sf).collect()}
    for i, t, _, _ in DOCS:
        letters = any(c.isalpha() for c in t or "")
        assert (found[i]["lang_pred"] != "und") == letters and 0 <= found[i]["score"] <= 1
        assert found[i]["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2)
    kept = language.keep_identified(spark.read.parquet(f"{sf}/documents.parquet"), language.Model(counted({})))
    assert kept.count() == 0


def counted(words):
    """{language: {word: n}} as a table of counts."""
    rows = [(lang, w, n) for lang, found in words.items() for w, n in found.items()]
    return pa.table({c: pa.array([r[i] for r in rows], kind) for i, (c, kind) in enumerate((("lang", pa.string()), ("word", pa.string()), ("n", pa.int64())))})


def test_language_backs_off():
    scorer = language.Scorer(language.Model(counted({"en": {"there": 5, "the": 9}, "de": {"schnee": 5, "der": 9}})))
    found, score = scorer.predict(pa.array(["thereof", "schneeig", "42 !", "中文", None]))
    assert found == ["en", "de", "und", "de", "und"] and score.tolist()[2:] == [0, 0.5, 0]


class BruteLanguage:
    """The definition, word by word: known words, then the longest n-grams of which any is known."""

    def __init__(self, rows):
        self.languages = sorted({lang for _, lang in rows})
        counts = {lang: Counter() for lang in self.languages}
        for text, lang in rows:
            counts[lang].update(regex.findall(r"\p{L}+", text.lower()))
        grams = [{lang: Counter() for lang in self.languages} for _ in range(5)]
        for lang, found in counts.items():
            for w, n in found.items():
                for size in range(1, 5):
                    for g in self.grams(w, size):
                        grams[size][lang][g] += n
        self.words, self.tables = self.logs(counts), [None, *(self.logs(g) for g in grams[1:])]

    @staticmethod
    def grams(word, size):
        padded = f" {word} " if size > 1 else word
        return [padded[i : i + size] for i in range(len(padded) - size + 1)]

    def logs(self, counts):
        entries = set().union(*counts.values())
        totals = {lang: sum(c.values()) + 0.5 * max(1, len(entries)) for lang, c in counts.items()}
        raw = {e: np.array([np.log(counts[lang][e] + 0.5) - np.log(totals[lang]) for lang in self.languages]) for e in entries}
        return {e: x - x.mean() for e, x in raw.items()}

    def score(self, word):
        if word in self.words:
            return self.words[word]
        for size in range(4, 0, -1):
            hits = [self.tables[size][g] for g in self.grams(word, size) if g in self.tables[size]]
            if hits:
                return np.mean(hits, axis=0)
        return None

    def predict(self, text):
        words = regex.findall(r"\p{L}+", (text or "").lower())
        if not words:
            return "und", 0.0
        scores = [x for w in words if (x := self.score(w)) is not None]
        mean = np.mean(scores, axis=0) if scores else np.zeros(len(self.languages))
        best = int(np.argmax(mean))
        return self.languages[best], 1 / np.exp(4 * (mean - mean[best])).sum()


@pytest.mark.parametrize("keep", [language.KEEP, 3])
def test_language_by_brute_force(spark, sf, monkeypatch, keep):
    """Every prediction and score, with repeated rows, ties and words outside the training alphabet; a tiny memory of unseen words changes nothing."""
    monkeypatch.setattr(language, "SLICE_CHARS", 2000)
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang")
    more = [(1000 + i, t, None) for i, t in enumerate(["thereof housed", "Flüsse größer", "中文 ok", "Ωμέγα", "casas ríos", "x1y2", "the der le el", "a b c"] * 2)]
    docs = docs.unionByName(spark.createDataFrame(more, docs.schema)).unionByName(docs.limit(10))
    brute = BruteLanguage([(r["text"], r["lang"]) for r in docs.collect() if r["text"] is not None and r["lang"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 4 != 2])
    scorer = language.Scorer(language.train(language.learnable(docs)), keep)
    rows = docs.collect()
    found, score = scorer.predict(pa.array([r["text"] for r in rows], pa.string()))
    for r, lang, s in zip(rows, found, score.tolist(), strict=True):
        want = brute.predict(r["text"])
        assert lang == want[0] and abs(s - want[1]) < 1e-9, r
    if keep == language.KEEP:
        by = Counter((r["doc_id"], r["lang_pred"], round(r["score"], 9)) for r in language.identify(docs).collect())
        assert by == Counter((r["doc_id"], lang, round(s, 9)) for r, lang, s in zip(rows, found, score.tolist(), strict=True))


def test_language_sample_is_bounded_and_has_rare_languages(spark):
    """One text with a third of the rows and a language with few: at most ``sample`` documents each, the rare one whole."""
    rows = [(i, "the same old text", "en") for i in range(400)] + [(1000 + i, f"wort{'abcdefghij'[i % 10]} haus", "de") for i in range(400)] + [(5000, "maison", "fr"), (None, "nada", "es")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.train(language.learnable(df), sample=30)
    assert model.languages == ["de", "en", "fr"]
    monkeyed = []
    original, language.word_counts = language.word_counts, lambda some, most: monkeyed.append(some.groupBy("lang").count().collect()) or original(some, most)
    try:
        language.train(language.learnable(df), sample=30)
    finally:
        language.word_counts = original
    assert {r["lang"]: r["count"] for r in monkeyed[0]} == {"de": 30, "en": 30, "fr": 1}
    assert len(language.train(language.learnable(df), most=2).words) <= 2


def test_components_of_a_long_chain(spark):
    edges = [(i, i + 1) for i in range(300)] + [(1000, i) for i in range(1001, 1400)] + [(5, 5)]
    random.Random(1).shuffle(edges)
    found = {r["node"]: r["root"] for r in components.connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(found[i] == 0 for i in range(1, 301)) and all(found[i] == 1000 for i in range(1001, 1400))


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").withColumn("lang", F.lit("en"))
    counts = []
    for name, stage in corpus_pipeline.STAGES:
        docs, columns = stage(spark, docs, sf), docs.columns
        docs = docs.cache()
        counts.append(docs.count())
        if name != "packing":
            assert docs.columns == columns
        if name == "language_id":
            assert all(any(c.isalpha() for c in r["text"]) for r in docs.collect())
        if name == "simhash_near_dedup":
            assert len({r["text"] for r in docs.collect()}) == counts[-1] < counts[0]
        if name == "pii":
            assert not any("joe@site.com" in r["text"] for r in docs.collect()) and counts[-1] == counts[-2]
    check_sequences(docs.collect(), 4096)


def test_pipeline_of_an_empty_table(spark, empty):
    import corpus_pipeline

    found = corpus_pipeline.run(spark, empty)
    assert found.collect() == [] and "sequence_id" in found.columns


def test_pipeline_run_is_its_stages(spark, sf, tmp_path):
    """run() gives what the stages give one after another on a table with nulls, repeated rows and extra columns."""
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    docs.unionByName(docs.limit(7)).write.parquet(f"{tmp_path}/documents.parquet")
    now = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, str(tmp_path)).cache()
    columns = ["doc_id", "piece", "start", "length", "ids_crc32"]
    found = corpus_pipeline.run(spark, str(tmp_path))
    assert Counter(rows_of(found.select(columns))) == Counter(rows_of(now.select(columns))) and found.count() > 20


def test_mix_keeps_documents_whole(spark):
    df = spark.createDataFrame([(i, "s", f"w{i} " * 10, 40) for i in range(9)] + [(20, "t", "v " * 500, 1000), (21, "t", None, 0), (20, "t", "v " * 500, 1000)], "doc_id long, source string, text string, n_chars long")
    rows = rows_of(mixing.mix(df))
    whole = set(rows_of(df))
    assert rows and set(rows) <= whole and not any(t is None for _, _, t, _ in rows)
    taken = {r["source"]: r["target"] for r in mixing.plan(df).collect()}
    for source, largest in (("s", 10), ("t", 500)):
        assert abs(sum(len(t.split()) for _, x, t, _ in rows if x == source) - taken[source]) <= largest


def brute_near_copies(texts, words=5):
    """The smallest index of each component of texts with at least four fifths of their shingles in common."""

    def shingles(text):
        ws = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        return {tuple(ws[i : i + words]) for i in range(max(1, len(ws) - words + 1))} if ws else set()

    sets, root = [shingles(t) for t in texts], list(range(len(texts)))
    for i, a in enumerate(sets):
        for j in range(i):
            if 5 * len(a & sets[j]) >= 4 * len(a | sets[j]) and root[i] != root[j]:
                p, q = sorted((root[i], root[j]))
                root = [p if r == q else r for r in root]
    return set(root)


@pytest.mark.parametrize("common", [100_000, 0])
def test_pipeline_drops_planted_near_copies(spark, monkeypatch, common):
    import corpus_pipeline
    from mapmatch.llm import near_copies

    monkeypatch.setattr(near_copies, "COMMON", common)
    rng = random.Random(8)
    line = prose(rng, 30)
    texts = [None, "", "Two words", "two  WORDS", "two", line]
    for _ in range(25):
        base = (prose(rng, rng.randint(6, 200)) + " " + line * rng.randint(0, 1)).split()
        for edits in (0, 1, 2, 3, 5, 8):
            copy = list(base)
            for _ in range(edits):
                copy[rng.randrange(len(copy))] = f"edit{rng.randrange(10**6)}"
            texts.append(" ".join(copy))
    group = prose(rng, 120).split()
    texts += [" ".join([*group[:i], f"own{i}", *group[i + 1 :]]) for i in range(120)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    want = brute_near_copies(texts)
    prints = [simhash.fingerprint(t) for t in texts]
    apart = [i for i in range(6, len(texts)) if i not in want and all((prints[i] ^ p).bit_count() > 4 for j, p in enumerate(prints) if j != i)]
    assert apart  # near copies that fingerprints four bits apart do not find
    stage = dict(corpus_pipeline.STAGES)["simhash_near_dedup"]
    assert {r["doc_id"] for r in stage(spark, df, "").collect()} == want


def test_near_copies_come_from_fingerprints_and_groups(spark, monkeypatch):
    """Close fingerprints are searched first; then a group of texts alike below four fifths leaves as many links as texts, and blocks lose none."""
    from mapmatch.llm import near_copies

    rng = random.Random(5)
    base = prose(rng, 300).split()
    texts = []
    for i in range(90):  # some thirty edits apart: alike by about two thirds, with a close copy of every third
        copy = list(base)
        for at in rng.sample(range(300), 6):
            copy[at] = f"edit{i}x{at}"
        texts += [" ".join(copy)] + ([" ".join([*copy, f"more{i}"])] if i % 3 == 0 else [])
    df = spark.createDataFrame(list(enumerate(texts)), "node long, text string").repartition(3)
    searched, candidates = [], []
    search, meet = near_copies.fingerprint_links, near_copies._candidates
    monkeypatch.setattr(near_copies, "fingerprint_links", lambda distinct: searched.append(distinct.count()) or search(distinct))
    monkeypatch.setattr(near_copies, "_candidates", lambda rest: candidates.append(meet(rest)) or candidates[-1])
    dropped = near_copies.drop_stored
    monkeypatch.setattr(near_copies, "drop_stored", lambda df: None)
    want = brute_near_copies(texts)

    def left():
        root = {r["node"]: r["root"] for r in near_copies.connected(near_copies.links(df)).collect()}
        return {i for i in range(len(texts)) if root.get(i, i) == i}

    assert left() == want and searched[0] > 50 and len(want) > 30
    assert candidates[0].count() < 40 * len(texts)  # of some 7000 pairs
    settle = near_copies._settled
    monkeypatch.setattr(near_copies, "_settled", lambda texts, groups: settle(texts, groups, 7))
    monkeypatch.setattr(near_copies, "_candidates", lambda rest: meet(rest, 5))
    assert left() == want
    assert dropped
