"""The worked examples, sizes and laws of the automata, without Spark."""

import itertools
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from mapmatch.automata import dfa as dfas
from mapmatch.automata import maps, nfa, pattern
from mapmatch.automata.alphabet import from_sets
from mapmatch.operators import kernels, measure
from mapmatch.operators.match import Compiled, TextSet
from mapmatch.plans import corpora, planner

AB = Compiled("(ab)*")
A, B = (int(AB.dfa.classes.table[ord(c)]) for c in "ab")
PATTERNS = ["(ab)*", "a|b*", "(a|b)*abb", "a?b+c{2,3}", "(a(b|c)*)+", ".*ab.*c", "[^a]*a[^a]*", "(a{2}b{2})*", "a*?b", "()|abc"]


def word(c: Compiled, text: str) -> list[int]:
    return [int(c.nfa.classes.table[ord(x)]) for x in text]


def test_map_table_of_ab():
    images = {tuple(map(int, i)) for i in AB.maps.images}
    assert images == {(0, 1, 2), (1, 2, 2), (2, 0, 2), (2, 2, 2), (0, 2, 2), (2, 1, 2)}
    assert (AB.dfa.size, AB.dfa.live, AB.maps.size, AB.maps.live) == (3, 2, 6, 5)


def test_trace_of_abab():
    m, seen = 0, []
    for c in (A, B, A, B):
        m = int(AB.maps.delta[m, c])
        seen.append(tuple(map(int, AB.maps.image(m))))
    assert seen == [(1, 2, 2), (0, 2, 2), (1, 2, 2), (0, 2, 2)] and AB.maps.final[m]


def test_four_chunks():
    parts = [AB.maps.image(AB.maps.run(word(AB, w))) for w in ("aba", "baba", "bab", "abab")]
    left, right = maps.compose_fun(parts[0], parts[1]), maps.compose_fun(parts[2], parts[3])
    assert left.tolist() == [1, 2, 2] and right.tolist() == [2, 0, 2]
    assert maps.compose_fun(left, right).tolist() == [0, 2, 2]
    q = 0
    for image in parts:
        q = int(image[q])
    assert q == 0


@pytest.mark.parametrize(("p", "live", "maps_live"), [(corpora.loop(5), 10, 109), (corpora.loop(50), 100, 10099), (corpora.alternating(), 10, 21), (corpora.loop_or_run(5), 12, 110), (corpora.loop_or_run(20), 42, 1640)])
def test_published_sizes(p, live, maps_live):
    c = Compiled(p)
    assert (c.dfa.live, c.maps.live) == (live, maps_live)


def test_blowups():
    for n in range(2, 6):
        c = Compiled(corpora.subset_blowup(n))
        assert c.dfa.size == 2**n and c.maps.size == c.relations.size
        assert Compiled(corpora.map_blowup(n)).maps.live == n**n


@pytest.mark.parametrize("p", PATTERNS + list(corpora.RULES.values())[:9])
def test_bounds(p):
    c = Compiled(p)
    assert np.log2(c.maps.size) <= measure.bound_log2("functions", c.dfa.size) + 1e-9
    assert np.log2(c.raw_dfa.size) <= measure.bound_log2("dfa", c.nfa.size)


@pytest.mark.parametrize("p", PATTERNS)
def test_all_machines_agree_with_the_library(p):
    c, lazy = Compiled(p), dfas.LazySubset(Compiled(p).nfa)
    expression = re.compile(f"(?:{p})", re.S)
    for n in range(7):
        for letters in itertools.product("abc", repeat=n):
            text = "".join(letters)
            w, want = word(c, text), expression.fullmatch(text) is not None
            assert [m.accepts(w) for m in (c.nfa, c.raw_dfa, c.dfa, c.maps, c.relations, lazy)] == [want] * 6, (p, text)


@settings(max_examples=60, deadline=None)
@given(st.sampled_from(PATTERNS), st.text("abcé", max_size=40), st.lists(st.integers(0, 40), max_size=6))
def test_any_division_gives_the_same_map(p, text, cuts):
    c = Compiled(p)
    whole = c.maps.image(c.maps.run(word(c, text)))
    edges = [0, *sorted(cuts), len(text)]
    out = np.arange(c.dfa.size)
    for a, b in zip(edges, edges[1:], strict=False):
        out = maps.compose_fun(out, c.maps.image(c.maps.run(word(c, text[min(a, len(text)) : b]))))
    assert (out == whole).all()


def test_composition_laws():
    images = [np.array(i) for i in AB.maps.images]
    for f, g, h in itertools.product(images, repeat=3):
        assert (maps.compose_fun(maps.compose_fun(f, g), h) == maps.compose_fun(f, maps.compose_fun(g, h))).all()
    a, b = AB.maps.image(AB.maps.run([A])), AB.maps.image(AB.maps.run([B]))
    assert maps.compose_fun(a, b).tolist() != maps.compose_fun(b, a).tolist()
    table = maps.compose_table(AB.maps)
    for f, g in itertools.product(range(6), repeat=2):
        assert (AB.maps.image(table[f, g]) == maps.compose_fun(images[f], images[g])).all()


def test_kernels_agree():
    rng = random.Random(3)
    words = ["".join(rng.choice("abc") for _ in range(rng.randint(0, 60))) for _ in range(50)] + ["", "é€😀", "a" * 300]
    column = pa.array([*words, None])
    for p in PATTERNS:
        c = Compiled(p)
        want = [list(map(int, c.maps.image(c.maps.run(word(c, w))))) for w in words] + [list(range(c.dfa.size))]
        for kind in ("maps", "lazy", "speculate", "merge", "halve"):
            assert c.scanner(kind).images(column) == want, (p, kind)
        assert [i for i in c.scanner("relations").images(column)][0] == list(c.relations.image(c.relations.run(word(c, words[0]))))


def test_long_words_are_walked_as_several_lanes(monkeypatch):
    monkeypatch.setattr(kernels, "LANE", 7)
    monkeypatch.setattr(kernels.chopped, "__defaults__", (7,))
    test_kernels_agree()


def test_lazy_maps_are_few_and_survive_flushing():
    c = Compiled(corpora.loop(20))
    lanes = kernels.lanes_of(pa.array(["0" * 20 + "9" * 20, "1" * 7]), c.dfa.classes.table, "codepoint")
    lazy = maps.LazyMaps(c.dfa)
    kernels.walk_lazy(lanes, lazy)
    assert lazy.made <= lanes.symbols() + 1
    small = maps.LazyMaps(c.dfa, keep=4)
    assert [small.listed(m) for m in kernels.walk_lazy(lanes, small).tolist()] == kernels.walk_all_states(lanes, c.dfa).tolist() and small.flushes


def test_lazy_relations_need_no_deterministic_automaton():
    """The subset automaton passes its cap, the relation maps too; what a word meets stays small."""
    c = Compiled("[ab]*a[ab]{14}", max_dfa=1000)
    with pytest.raises(dfas.TooLarge):
        _ = c.dfa
    rng = random.Random(5)
    words = ["".join(rng.choice("ab") for _ in range(n)) for n in (0, 1, 14, 15, 16, 60, 200)]
    scanner = c.scanner("lazy_relations")
    for w, image in zip(words, scanner.images(pa.array(words)), strict=True):
        assert bool(maps.end_states(tuple(image), c.nfa.initial) & c.nfa.final) == (len(w) >= 15 and w[-15] == "a")
    assert scanner.lazy.made <= sum(map(len, words)) + 1
    small = maps.LazyMaps(c.nfa, keep=8)
    lanes = kernels.lanes_of(pa.array(words), c.nfa.classes.table, "codepoint")
    assert [small.listed(m) for m in kernels.walk_lazy(lanes, small).tolist()] == scanner.images(pa.array(words)) and small.flushes


def test_state_sets_of_many_words():
    """Simulation with more states than a machine word holds, against the library."""
    p = "(a|b)*(a(a|b){70}|b(a|b){65}a)"
    c, rng = Compiled(p), random.Random(6)
    words = ["".join(rng.choice("ab") for _ in range(rng.randint(60, 140))) for _ in range(60)]
    lanes = kernels.lanes_of(pa.array([*words, "", None]), c.nfa.classes.table, "codepoint")
    assert kernels.walk_state_sets(lanes, kernels.SetSteps(c.nfa)).tolist() == [re.fullmatch(p, w) is not None for w in words] + [False, False]


def test_steps_over_several_symbols():
    """Wide tables and narrow ones end in the same states from any start, for all lengths around a block."""
    rng = np.random.default_rng(2)
    for p in (corpora.loop(3), "(ab)*", corpora.RULES["email"], corpora.loop(50)):
        c = Compiled(p)
        lengths = [0, 1, 2, 3, 255, 256, 257, 511, 512, 700]
        classes = rng.integers(0, c.dfa.classes.k, sum(lengths)).astype(np.uint8)
        lanes = kernels.Lanes(classes, np.cumsum(lengths) - lengths, np.array(lengths), np.ones(len(lengths), bool))
        starts = rng.integers(0, c.dfa.size, len(lengths))
        want = [c.dfa.run(classes[s : s + n].tolist(), int(q)) for s, n, q in zip(lanes.start, lanes.length, starts, strict=True)]
        assert kernels.walk_table(lanes, c.dfa.delta, starts).tolist() == want
    assert kernels.Steps(AB.dfa.delta).m > 1 and kernels.Steps(Compiled(corpora.loop(50)).maps.delta, 1).m == 1


def test_match_ends_by_lane():
    c = Compiled("(ab)*")
    lanes = kernels.lanes_of(pa.array(["abab", "", "ba", "ab"]), c.dfa.classes.table, "codepoint")
    lane, pos = kernels.match_ends(lanes, c.dfa, np.zeros(4, np.int32))
    assert list(zip(lane.tolist(), pos.tolist(), strict=True)) == [(0, 2), (0, 4), (3, 2)]


@pytest.mark.parametrize("depth", [1, 3, 24])
def test_text_sets_find_all(depth):
    rng = random.Random(8)
    texts = [(i, "".join(rng.choice("abé") for _ in range(rng.randint(1, 9)))) for i in range(60)] + [(60, "a"), (61, "ab"), (62, "x" * 50), (63, "")]
    words = ["".join(rng.choice("abé😀") for _ in range(rng.randint(0, 200))) for _ in range(40)] + ["", None, "y" + "x" * 80, "é"]
    found = TextSet(texts, depth).find(pa.array(words), 16)
    assert found == [[] if w is None else sorted(i for i, t in texts if t in w) for w in words]


def test_sliced_columns_and_bytes():
    c = Compiled("[a-zé]*", unit="codepoint")
    column = pa.array(["x", "éa", "b1", None, "z"]).slice(1, 4)
    lanes = kernels.lanes_of(column, c.dfa.classes.table, "codepoint")
    assert c.dfa.final[kernels.walk_table(lanes, c.dfa.delta)].tolist() == [True, False, True, True] and lanes.valid.tolist() == [True, True, False, True]
    b = Compiled("(é)*", unit="byte")
    lanes = kernels.lanes_of(pa.array(["éé".encode(), b"\xc3"], pa.binary()), b.dfa.classes.table, "byte")
    assert b.dfa.final[kernels.walk_table(lanes, b.dfa.delta)].tolist() == [True, False]


def test_lookups_are_one_or_as_many_as_states():
    c = Compiled("(ab)*")
    for kind, each in (("maps", 1), ("speculate", 3)):
        s = c.scanner(kind)
        s.images(pa.array(["abab", "ba"]))
        assert s.counts["lookups"] == each * 6
    s = c.scanner("merge")
    s.images(pa.array(["abab" * 10]))
    assert 40 <= s.counts["lookups"] < 120


def test_relation_maps_need_many_symbols():
    """Two-state machines over boolean matrices: the best 1, 2 and 3 symbols reach 3, 12 and 16 maps."""
    classes = from_sets({((97, 97),), ((98, 98),)})
    matrices = list(itertools.product(range(4), repeat=2))

    def reach(symbols):
        step = tuple(tuple([m[q] for m in symbols] + [0] * (classes.k - len(symbols))) for q in range(2))
        machine = nfa.Nfa(tuple(row[: len(symbols)] for row in step), 1, 2, from_sets({((i, i),) for i in range(97, 96 + len(symbols))}))
        return maps.close_relations(machine).size

    assert max(reach([m]) for m in matrices) == 3
    assert max(reach(p) for p in itertools.combinations(matrices, 2)) == 12
    assert max(reach(p) for p in itertools.combinations(matrices, 3)) == 16


def test_byte_and_code_point_modes_agree():
    """Either the same verdict on every word or a refusal: classes beyond ASCII are refused in byte mode, negated too."""
    words = ["", "a", "é", "aé", "€", "ab", "\U0001f600"]
    for p in ("(é)*", ".*é.*", "[a-z]*", "a.*", "é|€", "[^é]*", "[é]", r"[\W]*", "[^a]*"):
        c = Compiled(p, unit="byte")
        try:
            d = c.dfa
        except pattern.Unsupported:
            assert "[" in p
            continue
        lanes = kernels.lanes_of(pa.array([w.encode() for w in words], pa.binary()), d.classes.table, "byte")
        got = d.final[kernels.walk_table(lanes, d.delta)].tolist()
        assert got == [re.fullmatch(p, w, re.S) is not None for w in words], p


@pytest.mark.parametrize("p", [r"\xg1", r"\x4", r"\u12", "a{3,1}", "a{", "[b-a]", "x{2"])
def test_bad_patterns_are_refused(p):
    assert measure.compile_status(p) == "unsupported"


@pytest.mark.parametrize(("p", "status"), [(r"(a)\1", "unsupported"), ("a(?=b)", "unsupported"), (r"\bx", "unsupported"), ("a++", "unsupported"), ("[ab]*a[ab]{14}", "dfa_cap"), (corpora.map_blowup(5), "ok"), ("a(b", "unsupported")])
def test_status(p, status):
    assert measure.compile_status(p) == status


def test_map_cap():
    assert measure.compile_status(corpora.loop(20), max_maps=100) == "map_cap"


def test_equivalence_and_complexity():
    assert dfas.equivalent(Compiled("(ab)*").dfa, Compiled("(ab)*(ab)*").dfa) == (True, None)
    same, witness = dfas.equivalent(Compiled("(ab)*").dfa, Compiled("(ab)*|abb").dfa)
    assert not same and "".join(map(chr, witness)) == "abb"
    assert measure.syntactic_complexity("(ab)*") == measure.syntactic_complexity("(ab)*(ab)*") == 6


@pytest.mark.parametrize("p", [*PATTERNS, corpora.loop(7), corpora.subset_blowup(6), corpora.map_blowup(4), *list(corpora.RULES.values())[:8]])
def test_both_ways_of_minimising(p, monkeypatch):
    raw = Compiled(p).raw_dfa
    a = dfas.minimize(raw)
    monkeypatch.setattr(dfas, "FEW_CELLS", 0)
    b = dfas.minimize(raw)
    assert (a.delta == b.delta).all() and (a.final == b.final).all() and dfas.equivalent(a, raw) == (True, None)
    assert a.size == len(np.unique(dfas._split_by_rounds(a))) == len(set(dfas._split_one_by_one(a).tolist()))


def test_completion_and_lengths():
    c = AB.dfa.classes
    partial = np.array([[1, -1, -1], [-1, 0, -1]])
    assert dfas.equivalent(dfas.complete(partial, np.array([True, False]), c), AB.dfa)[0]
    assert Compiled("a{2,5}").dfa.lengths() == (2, 5) and AB.dfa.lengths() == (0, None) and Compiled("a[^\\x00-\\u0fff]").dfa.lengths()[0] == 2


def test_planner():
    assert planner.choose(AB, 100).plan == "rows"
    assert planner.choose(AB, 1 << 30).plan == "maps"
    assert planner.choose(Compiled(corpora.loop(20), max_maps=100), 1 << 30).plan == "lazy"
    assert planner.choose(Compiled("[ab]*a[ab]{14}", max_dfa=100), 1 << 30).plan == "lazy_relations"
    assert planner.choose(AB).plan == "maps" and planner.choose(AB, table_budget=10).plan == "lazy"
    assert [planner.contained_text(pattern.parse(p)) for p in (".*ab c.*", ".*a+b.*", "ab", "[ab].*", ".*a.*b.*", ".*.*")] == ["ab c", None, None, None, None, ""]
    assert planner.required_literal(pattern.parse(".*ab.*cde.*")) == "cde"


def test_working_set_is_small_on_a_run():
    c = Compiled(corpora.loop_or_run(20))
    run = np.full(1000, c.dfa.classes.table[ord("a")])
    assert measure.maps_touched(c, run) == 1 and c.maps.size > 1600
    assert measure.fold_work(c, 8, "in_order") == (8, 8) and measure.fold_work(c, 8, "tree") == (7, 7 * c.dfa.size)


def test_search_mode_and_dot():
    assert Compiled("b", mode="search").dfa.accepts(word(Compiled("b", mode="search"), "abc"))
    strict = Compiled("a.b", dotall=False)
    assert not strict.dfa.accepts(word(strict, "a\nb"))
