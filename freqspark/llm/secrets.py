"""Secret scans behind a trigram index.

Each rule is a regex. Its syntax tree gives a Boolean query over trigrams that every match must
hold. A batch of texts is a segment of the index: one pass over its bytes makes, for each trigram
that some rule asks for, the posting list of rows that hold it. A rule's query is answered by
intersecting and uniting postings, and only those rows meet the regex. A rule without a mandatory
trigram is run on every row.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property
from itertools import product
from re import _constants as sre  # the names of the nodes that re's own parser makes
from re import _parser as parser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from ._blocks import blocks, table, text_column

#: A set of literal strings is followed while it has no more members than this.
MOST_LITERALS = 32


@dataclass(frozen=True)
class Rule:
    """A kind of secret: its regex and the least length of a match, or of a group of it."""

    kind: str
    pattern: str
    least: int = 0
    group: int = 0
    any_case: bool = False
    base: bool = False

    @cached_property
    def regex(self) -> re.Pattern:
        return re.compile(self.pattern, re.ASCII | (re.IGNORECASE if self.any_case else 0))

    def spans(self, text: str) -> Iterator[tuple[int, int]]:
        """Matches from the left that don't overlap; those too short are dropped afterwards."""
        for m in self.regex.finditer(text):
            if m.end(self.group) - m.start(self.group) >= self.least:
                yield m.start(), m.end()

    @cached_property
    def query(self):
        return trigram_query(self.pattern)


#: The three base rules, in the order in which ties are listed, then the added ones.
RULES = (
    Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 12, 2, True, True),
    Rule("access", r"AKIA[A-Z0-9]+", 18, 0, False, True),
    Rule("hex", r"[0-9a-f]+", 16, 0, False, True),
    Rule("pem", r"-----BEGIN (?:RSA |EC |DSA |OPENSSH |PGP )?PRIVATE KEY(?: BLOCK)?-----"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{30,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("url", r"[a-z][a-z0-9+.-]{1,20}://[^\s/:@]{1,64}:[^\s/:@]{3,64}@[A-Za-z0-9.-]+"),
)

# A query is True (no condition), a trigram, ("and", parts) or ("or", parts).


def _all(parts):
    parts = [p for p in dict.fromkeys(parts) if p is not True]
    return True if not parts else parts[0] if len(parts) == 1 else ("and", tuple(parts))


def _any(parts):
    parts = list(dict.fromkeys(parts))
    return True if True in parts or not parts else parts[0] if len(parts) == 1 else ("or", tuple(parts))


def _of_string(s: str):
    return _all(s[i : i + 3] for i in range(len(s) - 2))


def _of_strings(strings):
    return _any(_of_string(s) for s in sorted(strings)) if strings else True


def trigram_query(pattern: str):
    """The condition on lower-cased trigrams that any text with a match fulfils.

    Walks the parse tree and keeps, as long as they are few, the exact strings that the walked part
    can stand for; where they become too many or unknown, their trigrams join the condition and
    the walk starts afresh behind.
    """

    def walk(nodes) -> tuple[set[str] | None, object]:
        """Exact strings (None: unknown), condition on what was left behind."""
        exact: set[str] | None = {""}
        conditions = []

        def cut(after: set[str] | None) -> None:
            nonlocal exact
            if exact is not None:
                conditions.append(_of_strings(exact))
            exact = after

        known = True
        for op, arg in nodes:
            strings, condition = node(op, arg)
            conditions.append(condition)
            if strings is None:
                cut({""})
                known = False
            elif len(joined := {a + b for a, b in product(exact, strings)}) > MOST_LITERALS:
                cut(strings)
                known = False
            else:
                exact = joined
        if known:
            return exact, _all(conditions)
        cut(None)
        return None, _all(conditions)

    def node(op, arg) -> tuple[set[str] | None, object]:
        if op is sre.LITERAL:
            return ({chr(arg).lower()}, True) if arg < 128 else (None, True)
        if op is sre.IN:
            chars = set()
            for kind, x in arg:
                if kind is sre.LITERAL and x < 128:
                    chars.add(chr(x).lower())
                elif kind is sre.RANGE and x[1] < 128 and x[1] - x[0] < MOST_LITERALS:
                    chars.update(chr(c).lower() for c in range(x[0], x[1] + 1))
                else:
                    return None, True
            return (chars, True) if len(chars) <= MOST_LITERALS else (None, True)
        if op is sre.SUBPATTERN:
            return walk(arg[-1])
        if op is sre.BRANCH:
            found = [walk(x) for x in arg[1]]
            if all(s is not None for s, _ in found) and sum(len(s) for s, _ in found) <= MOST_LITERALS:
                return set().union(*(s for s, _ in found)), True
            return None, _any(_all([c, _of_strings(s) if s is not None else True]) for s, c in found)
        if op in (sre.MAX_REPEAT, sre.MIN_REPEAT, sre.POSSESSIVE_REPEAT):
            least, most, inner = arg
            strings, condition = walk(inner)
            if (least, most) == (0, 1) and strings is not None and len(strings) < MOST_LITERALS:
                return strings | {""}, True
            if least == most == 1 or (least == most and strings is not None and len(strings) == 1):
                return ({s * least for s in strings} if strings is not None else None), condition
            if least and strings is not None:
                return None, _all([condition, _of_strings({s * min(least, 8) for s in strings}) if len(strings) == 1 else _of_strings(strings)])
            return None, condition if least else True
        if op in (sre.AT, sre.ASSERT, sre.ASSERT_NOT):
            return {""}, True
        return None, True

    strings, condition = walk(parser.parse(pattern))
    return _all([condition, _of_strings(strings) if strings is not None else True])


def trigrams(query) -> set[str]:
    """The trigrams that a query names."""
    return set() if query is True else {query} if isinstance(query, str) else set().union(*(trigrams(q) for q in query[1]))


class TrigramIndex:
    """Posting lists of one segment for the trigrams that a set of rules asks for."""

    def __init__(self, names: list[str]):
        self.names = names
        self.lower = np.arange(256, dtype=np.uint8)
        self.lower[65:91] += 32
        self.slot = np.zeros(1 << 21, np.uint8)  # trigrams of ASCII, 7 bits a byte
        for i, name in enumerate(names, 1):
            a, b, c = name.encode("ascii")
            self.slot[a << 14 | b << 7 | c] = i
        assert len(names) < 255

    def postings(self, data: np.ndarray, at: np.ndarray) -> dict[str, np.ndarray]:
        """Sorted row numbers for each trigram; a trigram does not reach over the end of a row."""
        found: dict[str, np.ndarray] = {}
        if len(data) < 3:
            return found
        x = self.lower[data]
        odd = x >= 128
        x = x.astype(np.int32)
        code = (x[:-2] << 14 | x[1:-1] << 7 | x[2:]) & 0x1FFFFF
        slots = self.slot[code]
        slots[odd[:-2] | odd[1:-1] | odd[2:]] = 0
        where = np.flatnonzero(slots)
        rows = np.searchsorted(at, where, "right") - 1
        whole = where + 3 <= at[rows + 1]
        pairs = np.unique(slots[where[whole]].astype(np.int64) << 32 | rows[whole])
        for i, name in enumerate(self.names, 1):
            lo, hi = np.searchsorted(pairs, [i << 32, (i + 1) << 32])
            if hi > lo:
                found[name] = pairs[lo:hi] & 0xFFFFFFFF
        return found


def answer(query, postings: dict[str, np.ndarray], n: int) -> np.ndarray:
    """Row numbers that fulfil a query: intersections and unions of posting lists."""
    none = np.zeros(0, np.int64)
    if query is True:
        return np.arange(n)
    if isinstance(query, str):
        return postings.get(query, none)
    parts = [answer(q, postings, n) for q in query[1]]
    if query[0] == "or":
        return np.unique(np.concatenate(parts))
    parts.sort(key=len)
    out = parts[0]
    for p in parts[1:]:
        out = np.intersect1d(out, p, assume_unique=True) if len(out) else none
    return out


def listed(spans: list[tuple[str, int, int]], order: dict[str, int]) -> str:
    """kind:start:end by start, then by the rules' order."""
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (s[1], order[s[0]], s[2])))


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Find secrets: key, a count n_<kind> for each base rule, base_sha256, spans (code points, end exclusive).

    A null text counts as empty; no spans give an empty list and the digest of nothing. Each row is
    scanned by itself, so that repeated rows, null keys and very long texts need nothing special.
    """
    base = [r.kind for r in rules if r.base]
    fields = [T.StructField(key, docs.schema[key].dataType), *(T.StructField(f"n_{k}", T.LongType()) for k in base), T.StructField("base_sha256", T.StringType()), T.StructField("spans", T.StringType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = TrigramIndex(sorted(set().union(*(trigrams(r.query) for r in rules))))
        order = {r.kind: i for i, r in enumerate(rules)}
        for batch in batches:
            texts = text_column(batch.column(1))
            for lo, hi, data, at in blocks(texts):
                values = texts.slice(lo, hi - lo).to_pylist()
                postings = index.postings(data, at)
                found: list[list[tuple[str, int, int]]] = [[] for _ in values]
                for rule in rules:
                    for row in answer(rule.query, postings, len(values)).tolist():
                        found[row] += ((rule.kind, a, b) for a, b in rule.spans(values[row]))
                of_base = [[s for s in row if s[0] in base] for row in found]
                cols = [batch.column(0).slice(lo, hi - lo)]
                cols += [pa.array([sum(s[0] == k for s in row) for row in of_base], pa.int64()) for k in base]
                cols += [pa.array([hashlib.sha256(listed(row, order).encode()).hexdigest() for row in of_base]), pa.array([listed(row, order) for row in found], pa.string())]
                yield pa.RecordBatch.from_arrays(cols, [f.name for f in fields])

    return docs.select(key, text).mapInArrow(run, T.StructType(fields))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op6: secrets in every document."""
    return scan(table(spark, sf_dir, "documents"))
