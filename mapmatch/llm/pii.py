"""Personal data by candidate generation and gradient boosting, in SQL functions alone.

Base patterns find e-mail addresses, IPv4 addresses, card and phone numbers in their plain forms; valid ones always
count. High-recall generators propose further spans that may overlap: written-out addresses, IPv6 addresses, numbers
in other groupings, phone numbers without a plus. Each proposal is described by its format (digits, groups,
separators, check digit) and its context (cue words just before it, letters or digits touching it). Boosted trees
score the description; a score must pass its kind's calibrated threshold, and what overlaps a base span or a better
proposal of another reading is left out. The trees are SQL expressions.

The trees are fitted in the driver to a fixed set of generated examples (see ``examples``), described by the same SQL;
a third of them, held back, sets the thresholds: the least score from which on precision is at least 0.95.

Defined results: null text is empty and has no spans; a text in which nothing is found has empty strings and zero
counts; repeated rows give repeated results; other columns are ignored by ``find`` and kept by ``redact``.
"""

from __future__ import annotations

import json
import math
import random
from functools import lru_cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .expressions import let, matches

KINDS = ("email", "ip", "card", "phone")

#: The base patterns, written so that they never go back (runs are taken whole) and meet the same spans.
BASE = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][ -])(?=(?:[0-9][ -]?){14})[0-9]++(?:[ -][0-9]++)*+",
    "phone": r"\+[0-9](?:[ ().-]*+[0-9])++",
}
_GUARD = {"email": "@", "ip": r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]", "card": r"(?:[0-9][ -]?){14}", "phone": r"\+[0-9]"}
_OCTET = r"0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"

#: High-recall generators: kind, pattern, and what a text must hold for the pattern to be tried.
GENERATORS = [
    ("email", r"(?i)(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++ ?(?:\(at\)|\[at\]|\{at\}| at ) ?[A-Za-z0-9-]++(?: ?(?:\(dot\)|\[dot\]|\{dot\}| dot |\.) ?[A-Za-z0-9-]++)++", r"(?i)(?:\(at\)|\[at\]|\{at\}| at )"),
    ("ip", r"(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}:){2,7}(?::?[0-9A-Fa-f]{1,4})(?::[0-9A-Fa-f]{1,4}){0,5}(?![0-9A-Za-z:])", r"[0-9A-Fa-f]:[0-9A-Fa-f:]"),
    ("card", r"(?<![0-9])[0-9]{4}(?:[./_]| {2,3}| ?- ?)[0-9]{4,6}(?:[./_]| {2,3}| ?- ?)[0-9]{4,5}(?:(?:[./_]| {2,3}| ?- ?)[0-9]{1,7})?(?![0-9])", r"[0-9]{4}[ ./_-]{1,3}[0-9]{4}"),
    ("phone", r"(?<![0-9+(.-])(?:\([0-9]{2,4}\) ?|00[1-9][0-9]{0,2}[ .-]|[0-9]{2,4}[ ./-])[0-9]{2,4}[ .-]?[0-9]{3,4}(?:[ .-]?[0-9]{2,4})?(?![0-9])", r"[0-9)][ ./-]?[0-9]"),
]

_CUES = {
    "email": r"(?i)(?:mail|contact|contacto|kontakt|write|reach|courriel|correo|adresse)[^\n]{0,16}$",
    "ip": r"(?i)(?:\bip|addr|host|server|client|from|login|gateway)[^\n]{0,12}$",
    "card": r"(?i)(?:card|karte|carte|tarjeta|visa|master|amex|credit|payment|pan)[^\n]{0,16}$",
    "phone": r"(?i)(?:tel|phone|call|fon|mobil|cell|fax|m[oó]vil|portable|whatsapp|anruf|appel)[^\n]{0,16}$",
}
FEATURES = ("kind", "digits", "groups", "length", "cue", "luhn", "parens", "letters", "marks", "touch", "zero", "date", "year", "domain")


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _as_kind(kind: str, with_match: bool = False):
    def span(s: Column) -> Column:
        more = [s["m"].alias("m")] if with_match else []
        return F.struct(s["start"].alias("start"), F.lit(KINDS.index(kind)).alias("k"), s["stop"].alias("stop"), F.lit(kind).alias("kind"), *more)

    return span


def _is_kind(kind: str):
    return lambda s: s["kind"] == kind


def base_spans(text: Column) -> Column:
    """Valid base spans as structs (start, k, stop, kind), by start, then kind."""
    valid = {
        "email": lambda s: F.lit(True),
        "ip": lambda s: s["m"].rlike(rf"\A{_OCTET}(?:\.{_OCTET}){{3}}\z"),
        "card": lambda s: F.length(_digits(s["m"])).between(14, 19) & F.call_function("luhn_check", _digits(s["m"])),
        "phone": lambda s: F.length(_digits(s["m"])).between(10, 15),
    }
    none = F.array().cast("array<struct<start:int,k:int,stop:int,kind:string>>")
    found = []
    for kind in KINDS:
        met = F.filter(matches(text, BASE[kind]), valid[kind])
        spans = F.transform(met, _as_kind(kind))
        guard = F.contains(text, F.lit("@")) if kind == "email" else text.rlike(_GUARD[kind])
        found.append(F.when(guard, spans).otherwise(none))
    return F.array_sort(F.concat(*found))


def describe(kind: Column, m: Column, before: Column, after: Column) -> Column:
    """The features of a proposal as doubles, in the order of FEATURES."""
    cue = F.lit(False)
    for name in KINDS:
        cue = F.when(kind == name, before.rlike(_CUES[name])).otherwise(cue)
    k = F.lit(0)
    for i, name in enumerate(KINDS):
        k = F.when(kind == name, F.lit(i)).otherwise(k)
    digits = _digits(m)
    columns = [
        k,
        F.length(digits),
        F.size(F.regexp_extract_all(m, F.lit("[0-9A-Za-z]+"), F.lit(0))),
        F.length(m),
        cue,
        F.call_function("luhn_check", digits),
        F.contains(m, F.lit("(")),
        F.length(F.regexp_replace(m, "[^A-Za-z]", "")),
        F.length(F.regexp_replace(m, "[^:/._]", "")),
        before.rlike(r"[\p{L}\p{N}_.,/-]\z") | after.rlike(r"\A(?:[\p{L}\p{N}_/]|[.,-][0-9])"),
        F.startswith(m, F.lit("0")) | F.startswith(m, F.lit("(0")),
        m.rlike(r"\A(?:[0-3]?[0-9][./ -][01]?[0-9][./ -](?:19|20)[0-9]{2}|(?:19|20)[0-9]{2}[./ -][01]?[0-9][./ -][0-3]?[0-9])"),
        m.rlike(r"\A(?:19|20)[0-9]{2}[./ -]"),
        m.rlike(r"(?i)(?:\.|dot\W? ?)(?:com|net|org|de|fr|es|io|edu|info|eu|uk)\z"),
    ]
    return F.array(*[F.coalesce(c.cast("double"), F.lit(0.0)) for c in columns])


def examples(seed: int = 7, each: int = 60) -> list[tuple[str, str, str, str, int]]:
    """(kind, span, before, after, label): generated spans of each kind and look-alikes that are none."""
    r = random.Random(seed)
    number = lambda n: "".join(r.choice("0123456789") for _ in range(n))
    name = lambda: "".join(r.choice("abcdefghijklmnoprstuvwy") for _ in range(r.randint(3, 8)))
    plain = lambda: r.choice(["", "and ", "they met ", "la suite ", "der Wert ", "en total ", "page "])

    def card() -> str:
        head = r.choice("456") + number(14)
        total = sum(d if i % 2 else (2 * d - 9 if d > 4 else 2 * d) for i, d in enumerate(map(int, head)))
        return head + str(-total % 10)

    fours = lambda s, sep: sep.join(s[i : i + 4] for i in range(0, 16, 4))
    rows = []
    for _ in range(each):
        at, dot = r.choice([("(at)", "(dot)"), ("[at]", "[dot]"), (" at ", " dot "), ("{at}", "."), (" (at) ", ".")])
        cue = r.choice(["mail: ", "contact ", "Kontakt: ", plain()])
        rows.append(("email", f"{name()}{at}{name()}{dot}{r.choice(['com', 'net', 'org', 'de', 'fr'])}", cue, r.choice(["", " or"]), 1))
        rows.append(("email", f"{name()} at {name()}. {name()}", plain(), r.choice([" ", ", and"]), 0))
        groups = [f"{r.randrange(16**4):x}" for _ in range(r.randint(5, 8))]
        rows.append(("ip", ":".join(groups[:2]) + "::" + groups[2] if r.random() < 0.3 else ":".join(groups), r.choice(["host ", "IP ", plain()]), r.choice(["", " is"]), 1))
        rows.append(("ip", f"{r.randrange(24):02d}:{r.randrange(60):02d}:{r.randrange(60):02d}", r.choice(["at ", plain()]), r.choice(["", " h"]), 0))
        rows.append(("card", fours(card(), r.choice([".", "  ", " - ", "/", "_"])), r.choice(["card ", "Visa: ", "carte ", plain()]), r.choice(["", " exp"]), 1))
        rows.append(("card", fours(number(15) + r.choice("0123456789"), r.choice([".", "/", "_", " - "])), r.choice(["ref ", "order ", "serial ", plain()]), "", 0))
        phone = r.choice([f"({number(3)}) {number(3)}-{number(4)}", f"{r.randint(200, 989)}-{number(3)}-{number(4)}", f"0049 {number(3)} {number(7)}", f"0{number(2)} {number(4)} {number(4)}", f"{r.randint(200, 989)}.{number(3)}.{number(4)}"])
        rows.append(("phone", phone, r.choice(["tel. ", "phone: ", "call ", "Telefon ", plain()]), r.choice(["", ". "]), 1))
        other = r.choice([f"{r.randint(1, 28)}.{r.randint(1, 12)}.{r.randint(1950, 2030)}", f"{r.randint(1950, 2030)}-{r.randint(1, 12):02d}-{r.randint(1, 28):02d}", f"{r.randint(10, 99)} {number(3)} {number(3)}", f"{r.randint(1900, 2020)} {r.randint(1900, 2020)}", f"{number(4)}-{number(4)}"])
        rows.append(("phone", other, r.choice(["in ", "dated ", "figures ", "EUR ", plain()]), r.choice(["", "."]), 0))
    return rows


def _fit(x: list[list[float]], y: list[int], rounds: int = 24, rate: float = 0.4) -> list[tuple]:
    """Trees of depth two (feature, cut, (feature, cut, low, high), (feature, cut, low, high)) for the logistic loss."""
    score, trees = [0.0] * len(y), []
    cuts = [sorted(set(col))[:-1][:: max(1, len(set(col)) // 12)] for col in zip(*x, strict=True)]

    def split(rows: list[int], g: list[float], h: list[float]) -> tuple[float, int, float] | None:
        all_g, all_h = sum(g[i] for i in rows), sum(h[i] for i in rows)
        best = None
        for f, values in enumerate(cuts):
            for c in values:
                low = [i for i in rows if x[i][f] <= c]
                if len(low) < 3 or len(rows) - len(low) < 3:
                    continue
                a, b = sum(g[i] for i in low), sum(h[i] for i in low)
                gain = a * a / (b + 1) + (all_g - a) ** 2 / (all_h - b + 1) - all_g**2 / (all_h + 1)
                if best is None or gain > best[0] + 1e-12:
                    best = gain, f, c
        return best

    for _ in range(rounds):
        p = [1 / (1 + math.exp(-s)) for s in score]
        g, h = [t - q for t, q in zip(y, p, strict=True)], [q * (1 - q) for q in p]
        root = split(list(range(len(y))), g, h)
        if root is None or root[0] < 1e-6:
            break
        branches = []
        for side in (True, False):
            rows = [i for i in range(len(y)) if (x[i][root[1]] <= root[2]) == side]
            leaf = lambda some: rate * sum(g[i] for i in some) / (sum(h[i] for i in some) + 1)
            _, f, c = split(rows, g, h) or (0, 0, -1.0)
            branches.append((f, c, leaf([i for i in rows if x[i][f] <= c]), leaf([i for i in rows if x[i][f] > c])))
        trees.append((root[1], root[2], *branches))
        score = [s + apply((trees[-1],), v) for s, v in zip(score, x, strict=True)]
    return trees


def apply(trees, v: list[float]) -> float:
    total = 0.0
    for f, c, low, high in trees:
        branch = low if v[f] <= c else high
        total += branch[2] if v[branch[0]] <= branch[1] else branch[3]
    return total


@lru_cache(maxsize=1)
def _model(rows: tuple) -> tuple[tuple, tuple[float, ...]]:
    kept = [i for i in range(len(rows)) if i % 3]
    trees = _fit([list(rows[i][1]) for i in kept], [rows[i][2] for i in kept])
    thresholds = []
    for k in range(len(KINDS)):
        held = sorted((-apply(trees, rows[i][1]), rows[i][2]) for i in range(0, len(rows), 3) if rows[i][1][0] == k)
        least, right = math.inf, 0
        for n, (s, label) in enumerate(held, 1):
            right += label
            if label and right / n >= 0.95:
                least = -s
        thresholds.append(max(least, 0.0) if least < math.inf else 1e9)
    return tuple(trees), tuple(thresholds)


def model(spark: SparkSession) -> tuple[tuple, tuple[float, ...]]:
    """Trees and the thresholds of the kinds, fitted to the generated examples."""
    names = ["kind", "m", "before", "after", "label"]
    listed = json.dumps([dict(zip(names, row, strict=True)) for row in examples()])
    rows = spark.range(1).select(F.explode(F.from_json(F.lit(listed), "array<struct<kind:string,m:string,before:string,after:string,label:int>>")).alias("e")).select("e.*")
    rows = rows.select(describe(F.col("kind"), F.col("m"), F.col("before"), F.col("after")).alias("x"), "label").collect()
    return _model(tuple(sorted((i * 7919 % 104729, tuple(r["x"]), r["label"]) for i, r in enumerate(rows))))


def _score(trees: tuple, x: Column) -> Column:
    def leaf(branch: tuple) -> Column:
        return F.when(F.get(x, F.lit(branch[0])) <= branch[1], F.lit(branch[2])).otherwise(F.lit(branch[3]))

    total = F.lit(0.0)
    for f, c, low, high in trees:
        total = total + F.when(F.get(x, F.lit(f)) <= c, leaf(low)).otherwise(leaf(high))
    return total


def _unclashed(items: Column, others: Column, rules_out) -> Column:
    """The items, sorted by start, that no overlapping one of the others rules out. Both have start and stop.

    Items are taken in blocks of about the root of their number, each against the others that overlap it, so that a text
    with very many spans costs that number times its root and not its square.
    """

    def blocks(s: Column) -> Column:
        n = F.size(s["items"])
        width = F.greatest(F.lit(16), F.ceil(F.sqrt(n.cast("double"))).cast("int"))

        def one(block: Column) -> Column:
            ends = F.struct(F.get(block, F.lit(0))["start"].alias("lo"), F.array_max(F.transform(block, lambda x: x["stop"])).alias("hi"))
            near = let(ends, lambda e: F.filter(s["others"], lambda o: (o["start"] < e["hi"]) & (o["stop"] > e["lo"])))
            return let(near, lambda os: F.filter(block, lambda p: ~F.exists(os, lambda o: (o["start"] < p["stop"]) & (p["start"] < o["stop"]) & rules_out(o, p))))

        cut = let(width, lambda w: F.transform(F.sequence(F.lit(0), F.floor((n - 1) / w).cast("int")), lambda b: F.slice(s["items"], b * w + 1, w)))
        return F.flatten(F.transform(cut, one))

    return let(F.struct(items.alias("items"), others.alias("others")), lambda s: F.when(F.size(s["items"]) == 0, s["items"]).otherwise(blocks(s)))


def added_spans(text: Column, base: Column, fitted: tuple) -> Column:
    """Spans that the model adds: structs (start, k, stop, kind)."""
    trees, thresholds = fitted
    none = F.array().cast("array<struct<start:int,k:int,stop:int,kind:string,m:string>>")
    found = []
    for kind, pattern, guard in GENERATORS:
        met = F.transform(matches(text, pattern), _as_kind(kind, True))
        found.append(F.when(text.rlike(guard), met).otherwise(none))
    free = _unclashed(F.array_sort(F.concat(*found)), base, lambda o, p: F.lit(True))
    proposed = let(F.struct(free.alias("new"), text.alias("t")), lambda s: F.transform(s["new"], lambda c: F.struct(c.alias("c"), describe(c["kind"], c["m"], F.substr(s["t"], F.greatest(c["start"] - 27, F.lit(1)), F.least(c["start"], F.lit(28))), F.substr(s["t"], c["stop"] + 1, F.lit(4))).alias("x"))))
    scored = F.transform(proposed, lambda p: F.struct(p["c"]["start"].alias("start"), p["c"]["k"].alias("k"), p["c"]["stop"].alias("stop"), p["c"]["kind"].alias("kind"), _score(trees, p["x"]).alias("score")))
    reach = F.array(*[F.lit(t) for t in thresholds])
    passed = F.filter(scored, lambda p: p["score"] >= F.get(reach, p["k"]))
    better = lambda a, b: (a["score"] > b["score"]) | ((a["score"] == b["score"]) & ((a["start"] < b["start"]) | ((a["start"] == b["start"]) & (a["k"] < b["k"]))))
    alone = let(passed, lambda ps: _unclashed(ps, ps, better))
    return F.transform(alone, lambda p: F.struct(p["start"].alias("start"), p["k"].alias("k"), p["stop"].alias("stop"), p["kind"].alias("kind")))


def listed(spans: Column) -> Column:
    """kind:start:end of every span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")


def with_spans(documents: DataFrame, text: str = "text") -> DataFrame:
    """The input with _base and _spans, the base spans and all spans."""
    fitted = model(documents.sparkSession)
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    spans = let(F.struct(whole.alias("t"), base_spans(whole).alias("b")), lambda s: F.struct(s["b"].alias("base"), F.array_sort(F.concat(s["b"], added_spans(s["t"], s["b"], fitted))).alias("spans")))
    return documents.withColumn("_found", spans).withColumn("_base", F.col("_found.base")).withColumn("_spans", F.col("_found.spans")).drop("_found")


def find(documents: DataFrame) -> DataFrame:
    """doc_id, counts of base spans by kind, base_sha256, spans of every document."""
    rows = with_spans(documents.select("doc_id", "text"))
    counts = [F.size(F.filter("_base", _is_kind(kind))).cast("long").alias(f"n_{kind}") for kind in KINDS]
    return rows.select("doc_id", *counts, F.sha2(listed(F.col("_base")), 256).alias("base_sha256"), listed(F.col("_spans")).alias("spans"))


def redact(documents: DataFrame) -> DataFrame:
    """The documents with every span replaced by its kind in brackets; n_chars follows the text. Null text stays null."""
    columns = documents.columns
    rows = with_spans(documents)

    def step(acc: Column, s: Column) -> Column:
        piece = F.concat(F.substr(F.col("text"), acc["at"] + 1, s["start"] - acc["at"]), F.lit("["), F.upper(s["kind"]), F.lit("]"))
        return F.when(s["start"] >= acc["at"], F.struct(s["stop"].alias("at"), F.concat(acc["out"], F.array(piece)).alias("out"))).otherwise(F.struct(F.greatest(acc["at"], s["stop"]).alias("at"), acc["out"].alias("out")))

    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))
    clean = F.aggregate("_spans", start, step, lambda acc: F.concat(F.array_join(acc["out"], ""), F.substr(F.col("text"), acc["at"] + 1, F.length("text"))))
    rows = rows.withColumn("text", F.when(F.size("_spans") > 0, clean).otherwise(F.col("text")))
    if "n_chars" in columns:
        rows = rows.withColumn("n_chars", F.when(F.size("_spans") > 0, F.length("text")).otherwise(F.col("n_chars")).cast(documents.schema["n_chars"].dataType))
    return rows.select(*columns)
