"""Predicates on attributes (M30), and which cells pass them."""

from __future__ import annotations

import bisect
import datetime
import re
from dataclasses import dataclass

from packvec.operators.attributes import Attribute

FAIL, PASS, STRADDLE = 0, 1, 2


@dataclass(frozen=True)
class Condition:
    """attribute op lo [hi]; op is one of < <= = >= > between."""

    attribute: str
    op: str
    lo: object
    hi: object = None

    def sql(self) -> str:
        def lit(v: object) -> str:
            if isinstance(v, str):
                return "'" + v.replace("'", "''") + "'"
            if isinstance(v, datetime.datetime):
                return f"timestamp_ntz '{v}'"
            if isinstance(v, datetime.date):
                return f"date '{v}'"
            return str(v)

        if self.op == "between":
            return f"`{self.attribute}` BETWEEN {lit(self.lo)} AND {lit(self.hi)}"
        return f"`{self.attribute}` {self.op} {lit(self.lo)}"


class P:
    """P("price") < 15, P("price").between(3, 5), P("kind") == "a" make conditions."""

    def __init__(self, name: str):
        self.name = name

    def __lt__(self, v):
        return Condition(self.name, "<", v)

    def __le__(self, v):
        return Condition(self.name, "<=", v)

    def __gt__(self, v):
        return Condition(self.name, ">", v)

    def __ge__(self, v):
        return Condition(self.name, ">=", v)

    def __eq__(self, v):  # noqa: D105
        return Condition(self.name, "=", v)

    def between(self, lo, hi):
        return Condition(self.name, "between", lo, hi)

    __hash__ = None


Clause = tuple[Condition, ...]
#: A predicate is a list of clauses; a row passes if all conditions of any clause hold. No clauses: everything passes.
Predicate = tuple[Clause, ...]


def any_of(*clauses: Condition | Clause) -> Predicate:
    return tuple(c if isinstance(c, tuple) else (c,) for c in clauses)


def all_of(*conditions: Condition) -> Predicate:
    return (tuple(conditions),)


def to_sql(predicate: Predicate) -> str:
    if not predicate:
        return "true"
    return " OR ".join("(" + (" AND ".join(c.sql() for c in clause) or "true") + ")" for clause in predicate)


_WORD = re.compile(r"""\s*(?:(?P<and>AND\b)|(?P<or>OR\b)|(?P<name>[A-Za-z_]\w*)\s*(?:(?P<op><=|>=|<|>|=)\s*(?P<v>'(?:[^']|'')*'|[-+.\w]+)|BETWEEN\s+(?P<lo>'(?:[^']|'')*'|[-+.\w]+)\s+AND\s+(?P<hi>'(?:[^']|'')*'|[-+.\w]+)))""", re.I)


def parse(text: str) -> Predicate:
    """A predicate from SQL-like text: conditions joined by AND, and such clauses joined by OR, without brackets."""
    def value(v: str) -> object:
        if v.startswith("'"):
            return v[1:-1].replace("''", "'")
        return float(v)

    clauses: list[list[Condition]] = [[]]
    at = 0
    while text[at:].strip():
        m = _WORD.match(text, at)
        if not m:
            raise ValueError(f"cannot read the predicate from: {text[at:]!r}")
        at = m.end()
        if m["or"]:
            clauses.append([])
        elif m["name"]:
            clauses[-1].append(Condition(m["name"], m["op"], value(m["v"])) if m["op"] else Condition(m["name"], "between", value(m["lo"]), value(m["hi"])))
    return tuple(tuple(c) for c in clauses) if text.strip() else ()


@dataclass(frozen=True)
class Interval:
    lo: float
    lo_open: bool
    hi: float
    hi_open: bool

    def holds(self, x: float) -> bool:
        return (x > self.lo if self.lo_open else x >= self.lo) and (x < self.hi if self.hi_open else x <= self.hi)


def _number(v: object) -> float:
    if isinstance(v, datetime.datetime):
        return (v - datetime.datetime(1970, 1, 1)) / datetime.timedelta(microseconds=1)
    if isinstance(v, datetime.date):
        return float((v - datetime.date(1970, 1, 1)).days)
    return float(v)


def interval(c: Condition, a: Attribute) -> Interval:
    """The condition on the attribute's number line; a category's operands lie at or between ranks."""
    def at(v: object) -> float:
        if a.kind == "numeric":
            return _number(v)
        i = bisect.bisect_left(a.values, str(v))
        return float(i) if i < len(a.values) and a.values[i] == str(v) else i - 0.5

    lo, inf = at(c.lo), float("inf")
    return {
        "<": lambda: Interval(-inf, False, lo, True), "<=": lambda: Interval(-inf, False, lo, False), "=": lambda: Interval(lo, False, lo, False),
        ">=": lambda: Interval(lo, False, inf, False), ">": lambda: Interval(lo, True, inf, False), "between": lambda: Interval(lo, False, at(c.hi), False),
    }[c.op]()


def cell_pass(c: Condition, a: Attribute) -> list[int]:
    """FAIL, PASS or STRADDLE of each cell [edge, next edge); the last one is closed, a category's cell is its rank."""
    i = interval(c, a)
    if a.kind == "category":
        return [PASS if i.holds(float(r)) else FAIL for r in range(a.cells)]
    out = []
    for n, (lo, hi) in enumerate(zip(a.edges, a.edges[1:])):
        closed = n == len(a.edges) - 2
        above = hi < i.lo or (hi == i.lo and (i.lo_open or not closed))
        below = lo > i.hi or (lo == i.hi and i.hi_open)
        inside = i.holds(lo) and (i.holds(hi) if closed else hi <= i.hi)
        out.append(FAIL if above or below else PASS if inside else STRADDLE)
    return out
