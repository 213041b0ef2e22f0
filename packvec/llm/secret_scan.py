"""Operator 5: secrets in texts: fixed patterns, and credential-context values that would cost many guesses.

The guess cost of a value is the smallest sum of the logarithms of its segments' costs over all ways to cut it into
words, dates, repeats, keyboard walks and brute-force spans, found by dynamic programming over its positions. A value
next to a credential word whose cost reaches GUESS_LIMIT becomes a span of kind "guess" unless it meets a base span.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

KINDS = ("assign", "access", "hex", "guess")
#: Logarithm to base 10 of the guesses from which a value counts as a secret, and its least length.
GUESS_LIMIT, GUESS_LENGTH = 12.0, 8

ASSIGN = re.compile(r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
ASSIGN_STEMS = ("passw", "secret", "token", "apikey", "api_key")
CONTEXT = re.compile(r"""(?ai)(?:pass(?:word|wd|phrase|code)?|pwd|secret|token|credentials?|api[_-]?key|(?:access|private|signing|encryption)[_-]?key|bearer|authorization)["']?(?:\x20*(?:[:=]|=>)|\x20+is)\x20*["']?([^\s"'<>,;]+)""")
CONTEXT_STEMS = ("pass", "pwd", "secret", "token", "credential", "key", "bearer", "authorization")

#: Common words and passwords by falling frequency; the rank is the cost.
WORDS = """password admin welcome login letmein monkey dragon master shadow sunshine princess football baseball superman
batman trustno love secret hello freedom whatever starwars summer winter spring autumn flower cookie cheese computer
internet service server test guest user root default change changeme example sample demo value string token key pass
none null true false your here insert replace placeholder database mysecret company office money bank phone mobile
michael jordan jennifer thomas robert daniel andrew joshua george charlie the and this that with from""".split()
RANKS = {w: i + 1 for i, w in enumerate(WORDS)}
#: Rows of a keyboard.
ROWS = ("1234567890", "qwertyuiop", "asdfghjkl", "zxcvbnm", "abcdefghijklmnopqrstuvwxyz")
LEET = str.maketrans("013457@$!", "oleastasi")
DATE = re.compile(r"(?:19|20)\d\d(?:[-/._]?(?:0[1-9]|1[0-2])(?:[-/._]?(?:0[1-9]|[12]\d|3[01]))?)?|(?:0[1-9]|[12]\d|3[01])[-/._]?(?:0[1-9]|1[0-2])[-/._]?(?:19|20)?\d\d")
LONGEST_WORD, LONGEST_UNIT = max(map(len, WORDS)), 8
NEXT = {a + b for row in ROWS for r in (row, row[::-1]) for a, b in zip(r, r[1:])}


def alphabet(value: str) -> int:
    return max(10, 26 * bool(re.search("[a-z]", value)) + 26 * bool(re.search("[A-Z]", value)) + 10 * bool(re.search("[0-9]", value)) + 33 * bool(re.search("[^A-Za-z0-9]", value)))


def _run_ends(true: list[bool]) -> list[int]:
    """For each place, where the run of true that begins there ends (the place itself if it is not true)."""
    out, end = [0] * len(true), len(true)
    for i in range(len(true) - 1, -1, -1):
        if not true[i]:
            end = i
        out[i] = end
    return out


@lru_cache(maxsize=20_000)
def guess_cost(value: str) -> float:
    """Logarithm to base 10 of the guesses for a value; 0 for an empty one."""
    n, low = len(value), value.lower()
    plain, each = low.translate(LEET), math.log10(alphabet(value))
    walk = _run_ends([low[i] + low[i + 1] in NEXT for i in range(n - 1)])
    again = [_run_ends([value[i] == value[i + unit] for i in range(n - unit)]) for unit in range(1, min(LONGEST_UNIT, n // 2) + 1)]
    best = [0.0] + [math.inf] * n
    fixed = 0.3  # each further segment doubles the ways to order them
    for i in range(n):
        at = best[i]

        def reach(j: int, cost: float) -> None:
            if at + cost < best[j]:
                best[j] = at + cost

        reach(i + 1, each)
        for j in range(i + 3, min(n, i + LONGEST_WORD) + 1):
            rank = RANKS.get(low[i:j]) or RANKS.get(plain[i:j])
            if rank:
                odd = sum(a != b for a, b in zip(value[i:j], plain[i:j]))
                reach(j, fixed + math.log10(rank + 1) + 0.3 * odd)
        if found := DATE.match(value, i):
            reach(found.end(), fixed + math.log10(365 * 60))
        j = walk[i] + 1 if i < n - 1 else n
        if j - i >= 3:
            reach(j, fixed + math.log10(len(ROWS) * 20 * (j - i)))
        for unit, ends in enumerate(again[: (n - i) // 2], 1):
            times = (ends[i] + unit - i) // unit
            if times >= 2 and times * unit >= 3:
                reach(i + times * unit, fixed + unit * each + math.log10(times))
    return best[n]


def spans_of(text: str | None) -> list[tuple[str, int, int, float]]:
    """(kind, start, end, cost) by start, then kind as listed. Offsets are code points, the end exclusive."""
    if not text:
        return []
    low, out = text.lower(), []
    if any(x in low for x in ASSIGN_STEMS) or not low.isascii():
        out += [("assign", m.start(), m.end(), 0.0) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [("access", m.start(), m.end(), 0.0) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [("hex", m.start(), m.end(), 0.0) for m in HEX.finditer(text)]
    if any(x in low for x in CONTEXT_STEMS):
        base = sorted(x[1:3] for x in out)
        for m in CONTEXT.finditer(text):
            s, e = m.span(1)
            value = m[1].rstrip(".:!?)]}")
            e = s + len(value)
            if len(value) >= GUESS_LENGTH and not any(a < e and s < b for a, b in base) and (cost := guess_cost(value)) >= GUESS_LIMIT:
                out.append(("guess", s, e, cost))
    return sorted(out, key=lambda x: (x[1], KINDS.index(x[0]), x[2]))


def joined(spans: list[tuple[str, int, int, float]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e, _ in spans)


RESULT = "n_assign long, n_access long, n_hex long, n_guess long, base_sha256 string, spans string"


def scan(df: DataFrame, id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per text: its id, spans found, counts by kind and a digest of the base spans.

    Edge cases: null and empty texts have no spans; long texts are scanned whole; repeated rows give repeated results;
    other columns are not read; an empty table gives an empty result.
    """
    kind = df.schema[id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [spans_of(x.as_py()) for x in batch.column(1)]
            count = lambda k: pa.array([sum(s[0] == k for s in r) for r in rows], pa.int64())
            base = [hashlib.sha256(joined([s for s in r if s[0] != "guess"]).encode()).hexdigest() for r in rows]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(count(k) for k in KINDS), pa.array(base, pa.string()), pa.array([joined(r) for r in rows], pa.string())], names=["id", "n_assign", "n_access", "n_hex", "n_guess", "base_sha256", "spans"])

    return df.select(id, text).mapInArrow(run, f"id {kind}, {RESULT}").withColumnRenamed("id", id)
