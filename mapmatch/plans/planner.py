"""Choosing a plan for a pattern and an input, and conditions that cheaply rule words out."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..automata import pattern
from ..automata.dfa import TooLarge

#: Bytes of a table worth broadcasting; characters of a word from which cutting it pays; maps worth making beforehand;
#: nondeterministic states up to which relations are held as matrices.
TABLE_BUDGET, MIN_PARALLEL, EAGER_MAPS, MATRIX_STATES = 32 << 20, 32 << 20, 200_000, 512


@dataclass(frozen=True)
class Choice:
    """rows: a word a lane; maps, lazy or lazy_relations: chunks of words. reason says why."""

    plan: str
    reason: str


def sent_bytes(auto) -> int:
    """What the broadcast of a map automaton takes: its table, the way to each map, and the images that are kept."""
    images = 2 * auto.size * auto.base.size if auto.images is not None else 0
    return auto.delta.nbytes + auto.parent.nbytes + auto.via.nbytes + images


def choose(c, longest: int | None = None, table_budget: int = TABLE_BUDGET, min_parallel: int = MIN_PARALLEL, deterministic: bool = False) -> Choice:
    """The plan for a compiled pattern and, if known, the length of the longest word.

    deterministic: the caller needs states of the deterministic automaton, so its cap is an error.
    """
    if longest is not None and longest < min_parallel:
        return Choice("rows", "no word is long enough to be worth cutting")
    try:
        states = c.dfa.size
    except TooLarge:
        if deterministic or c.nfa.size > MATRIX_STATES:
            raise
        return Choice("lazy_relations", "the deterministic automaton passes its cap, so maps are made over the nondeterministic one as words meet them")
    try:
        size = sent_bytes(c.maps_up_to(EAGER_MAPS))
    except TooLarge:
        return Choice("lazy", f"the maps over {states} states pass their cap")
    if size > table_budget:
        return Choice("lazy", f"the table of {size} bytes passes its budget")
    return Choice("maps", f"a table of {size} bytes")


def _sequence(tree) -> list:
    return list(tree[1]) if tree[0] == "cat" else [tree]


def required_literal(tree) -> str:
    """The longest text that every accepted word must contain, as far as the top-level sequence shows."""
    best = now = ""

    def one(part) -> str | None:
        if part[0] == "set" and len(part[1]) == 1 and part[1][0][0] == part[1][0][1]:
            return chr(part[1][0][0])
        return None

    def flat(part):
        for p in _sequence(part):
            if p[0] == "cat":
                yield from flat(p)
            else:
                yield p

    for part in flat(tree):
        if (c := one(part)) is not None:
            now += c
        else:
            best, now = max(best, now, key=len), ""
    return max(best, now, key=len)


def contained_text(tree) -> str | None:
    """The text that a pattern looks for anywhere in a word, if it does nothing else."""
    parts = list(tree[1]) if tree[0] == "cat" else []
    if len(parts) < 2 or any(p[0] != "rep" or p[1] != ("set", ((0, pattern.TOP["codepoint"]),)) or p[2:] != (0, None) for p in (parts[0], parts[-1])):
        return None
    text = required_literal(("cat", tuple(parts[1:-1])))

    def size(part) -> int | None:
        if part[0] == "cat":
            sizes = [size(p) for p in part[1]]
            return None if None in sizes else sum(sizes)
        return 1 if part[0] == "set" and len(part[1]) == 1 and part[1][0][0] == part[1][0][1] else None

    return text if size(("cat", tuple(parts[1:-1]))) == len(text) else None


def prefilter(c, column: Column) -> Column:
    """A condition that every accepted word meets: a literal it must contain, and bounds on its length."""
    least, most = c.dfa.lengths()
    condition = F.length(column) >= max(least, 0) if c.unit == "codepoint" else F.lit(True)
    if most is not None and c.unit == "codepoint":
        condition = condition & (F.length(column) <= most)
    literal = required_literal(pattern.parse(c.text, c.unit, c.mode, c.dotall)) if c.unit == "codepoint" else ""
    return condition & F.contains(column, F.lit(literal)) if literal else condition
