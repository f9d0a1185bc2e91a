"""Label patterns: propositional formulas over the set of labels on a path."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce
from itertools import combinations, product

from pyspark.sql import Column
from pyspark.sql import functions as F


class PatternError(ValueError):
    """A text that is no pattern; ``position`` is where reading stopped."""

    def __init__(self, message: str, position: int) -> None:
        super().__init__(f"{message} at position {position}")
        self.position = position


@dataclass(frozen=True)
class Label:
    name: str


@dataclass(frozen=True)
class Not:
    part: object


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


@dataclass(frozen=True)
class Const:
    value: bool


TRUE, FALSE = Const(True), Const(False)


def all_of(names) -> object:
    return And(tuple(Label(n) for n in names))


def any_of(names) -> object:
    return Or(tuple(Label(n) for n in names))


def none_of(names) -> object:
    return And(tuple(Not(Label(n)) for n in names))


def allowed_to_pattern(allowed, alphabet, expanded: bool = False, most: int = 12) -> object:
    """The pattern of paths that use allowed labels only.

    Plain, none of the other labels; ``expanded`` gives the disjunction over the subsets of ``allowed`` that are exactly the path's
    labels: the same answers from exponentially many clauses, so at most ``most`` allowed labels.
    """
    allowed, alphabet = set(allowed), set(alphabet)
    others = sorted(alphabet - allowed)
    if not expanded:
        return none_of(others)
    allowed = sorted(allowed & alphabet)
    if len(allowed) > most:
        raise ValueError(f"expanded form of {len(allowed)} labels would have 2**{len(allowed)} clauses")
    return Or(tuple(And((*(Label(x) for x in s), *(Not(Label(x)) for x in sorted(set(allowed) - set(s))), *(Not(Label(x)) for x in others))) for n in range(len(allowed) + 1) for s in combinations(allowed, n)))


_TOKEN = re.compile(r"\s*(?:(?P<group>ALL|ANY|NONE|ONLY)\s*\{(?P<items>[^}]*)\}|(?P<op>\(|\)|&&?|\|\|?|!|∧|∨|¬)|\"(?P<quoted>[^\"]*)\"|(?P<word>[^\s()&|!∧∨¬{}\"]+))")
_NAMED = {"AND": "&", "OR": "|", "NOT": "!", "∧": "&", "∨": "|", "¬": "!", "&&": "&", "||": "|"}


def parse_pattern(text: str, alphabet=None) -> object:
    """Read a pattern: AND OR NOT (or & | ! and the logic signs), parentheses, labels (quoted where
    they hold signs), TRUE, FALSE, ALL{..} ANY{..} NONE{..}, and ONLY{..} where ``alphabet`` is given."""
    tokens, at = [], 0
    while text[at:].strip():
        m = _TOKEN.match(text, at)
        if not m:
            raise PatternError("unexpected character", at)
        tokens.append((m, at))
        at = m.end()

    def peek() -> str | None:
        if not tokens:
            return None
        m = tokens[0][0]
        word = m["op"] or (m["word"] if m["word"] in _NAMED else None)
        return _NAMED.get(word, word)

    def joined(sign: str, kind, below):
        parts = [below()]
        while peek() == sign:
            tokens.pop(0)
            parts.append(below())
        return parts[0] if len(parts) == 1 else kind(tuple(parts))

    def atom():
        if not tokens:
            raise PatternError("unexpected end", len(text))
        sign = peek()
        m, pos = tokens.pop(0)
        if sign == "!":
            return Not(atom())
        if sign == "(":
            inside = disjunction()
            if peek() != ")":
                raise PatternError("missing )", tokens[0][1] if tokens else len(text))
            tokens.pop(0)
            return inside
        if sign is not None:
            raise PatternError(f"unexpected {sign}", pos)
        if m["group"]:
            items = [x.strip().strip('"') for x in m["items"].split(",") if x.strip()]
            if m["group"] == "ONLY":
                if alphabet is None:
                    raise PatternError("ONLY needs the alphabet", pos)
                return allowed_to_pattern(items, alphabet)
            return {"ALL": all_of, "ANY": any_of, "NONE": none_of}[m["group"]](items)
        if m["word"] in ("TRUE", "FALSE"):
            return Const(m["word"] == "TRUE")
        return Label(m["quoted"] if m["quoted"] is not None else m["word"])

    def conjunction():
        return joined("&", And, atom)

    def disjunction():
        return joined("|", Or, conjunction)

    if not tokens:
        raise PatternError("empty pattern", 0)
    out = disjunction()
    if tokens:
        raise PatternError("unexpected text", tokens[0][1])
    return out


def labels_of(p) -> set[str]:
    if isinstance(p, Label):
        return {p.name}
    if isinstance(p, Not):
        return labels_of(p.part)
    return set() if isinstance(p, Const) else set().union(*map(labels_of, p.parts), set())


def to_nnf(p, negated: bool = False) -> object:
    """Negations moved down to labels."""
    if isinstance(p, Const):
        return Const(p.value != negated)
    if isinstance(p, Label):
        return Not(p) if negated else p
    if isinstance(p, Not):
        return to_nnf(p.part, not negated)
    flip = isinstance(p, And) == negated
    return (Or if flip else And)(tuple(to_nnf(x, negated) for x in p.parts))


@dataclass(frozen=True)
class Clause:
    """A conjunction: labels that must occur and labels that must not."""

    req: frozenset
    forb: frozenset

    def residual(self, seen) -> frozenset:
        return self.req - frozenset(seen)

    def holds(self, present) -> bool:
        return self.req <= set(present) and not self.forb & set(present)


class TooManyClauses(ValueError):
    """The normal form would exceed the bound."""


def to_dnf(p, max_clauses: int = 64) -> list[Clause]:
    """Simplified clauses whose disjunction is the pattern; none for a contradiction."""

    def walk(x) -> set[Clause]:
        if isinstance(x, Const):
            return {Clause(frozenset(), frozenset())} if x.value else set()
        if isinstance(x, Label):
            return {Clause(frozenset([x.name]), frozenset())}
        if isinstance(x, Not):
            return {Clause(frozenset(), frozenset([x.part.name]))}
        parts = [walk(y) for y in x.parts]
        if isinstance(x, Or):
            return absorb(set().union(*parts))
        out = {Clause(frozenset(), frozenset())}
        for part in parts:
            out = absorb({c for a, b in product(out, part) if not (c := Clause(a.req | b.req, a.forb | b.forb)).req & c.forb})
        return out

    def absorb(cs: set[Clause]) -> set[Clause]:
        kept = {c for c in cs if not any(d != c and d.req <= c.req and d.forb <= c.forb for d in cs)}
        if len(kept) > max_clauses:
            raise TooManyClauses(f"more than {max_clauses} clauses")
        return kept

    return sorted(walk(to_nnf(p)), key=lambda c: (sorted(c.req), sorted(c.forb)))


def to_cnf(p, max_clauses: int = 64) -> list[Clause]:
    """Clauses of which each must have a required label present or a forbidden one absent."""
    return [Clause(c.forb, c.req) for c in to_dnf(Not(p), max_clauses)]


def simplify(p, alphabet) -> object:
    """Constants folded; labels outside the alphabet never occur."""
    if isinstance(p, Label):
        return p if p.name in alphabet else FALSE
    if isinstance(p, Not):
        x = simplify(p.part, alphabet)
        return Const(not x.value) if isinstance(x, Const) else x.part if isinstance(x, Not) else Not(x)
    if isinstance(p, Const):
        return p
    decisive = isinstance(p, Or)
    parts = list(dict.fromkeys(simplify(x, alphabet) for x in p.parts))
    if any(isinstance(x, Const) and x.value == decisive for x in parts):
        return Const(decisive)
    parts = [x for x in parts if not isinstance(x, Const)]
    return Const(not decisive) if not parts else parts[0] if len(parts) == 1 else type(p)(tuple(parts))


def holds(p, present) -> bool:
    """The pattern on a set of labels."""
    if isinstance(p, Const):
        return p.value
    if isinstance(p, Label):
        return p.name in present
    if isinstance(p, Not):
        return not holds(p.part, present)
    return (all if isinstance(p, And) else any)(holds(x, present) for x in p.parts)


def pattern_column(p, present: Column) -> Column:
    """The pattern on an array of labels, as built-in expressions."""
    if isinstance(p, Const):
        return F.lit(p.value)
    if isinstance(p, Label):
        return F.array_contains(present, p.name)
    if isinstance(p, Not):
        return ~pattern_column(p.part, present)
    return reduce(lambda a, b: a & b if isinstance(p, And) else a | b, [pattern_column(x, present) for x in p.parts], F.lit(isinstance(p, And)))


def pattern_mask_column(p, words: list[Column], bits: dict[str, int]) -> Column:
    """The pattern on a mask with a bit for each label; labels without a bit are absent."""
    if isinstance(p, Label):
        if p.name not in bits:
            return F.lit(False)
        w, i = divmod(bits[p.name], 62)
        return words[w].bitwiseAND(F.lit(1 << i)) != 0
    if isinstance(p, Const):
        return F.lit(p.value)
    if isinstance(p, Not):
        return ~pattern_mask_column(p.part, words, bits)
    return reduce(lambda a, b: a & b if isinstance(p, And) else a | b, [pattern_mask_column(x, words, bits) for x in p.parts], F.lit(isinstance(p, And)))


def to_sql(p, array: str) -> str:
    """SQL text of the pattern on an array expression."""
    if isinstance(p, Const):
        return str(p.value).upper()
    if isinstance(p, Label):
        return "array_contains({}, '{}')".format(array, p.name.replace("'", "''"))
    if isinstance(p, Not):
        return f"(NOT {to_sql(p.part, array)})"
    return "(" + (" AND " if isinstance(p, And) else " OR ").join(to_sql(x, array) for x in p.parts) + ")" if p.parts else str(isinstance(p, And)).upper()


def register_pattern(spark, name: str, text: str) -> None:
    """A temporary SQL function ``name(labels)`` that tells whether the pattern holds."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(labels ARRAY<STRING>) RETURNS BOOLEAN RETURN {to_sql(parse_pattern(text), 'labels')}")
