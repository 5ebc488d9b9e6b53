"""Boolean trigram queries from regular expressions.

A query is True (nothing is known: every text is a candidate), a trigram of folded bytes, or ("and" | "or", set
of queries). For each part of the expression the analysis keeps the set of strings it can match, while that set
is small, and else what its matches must hold: their possible prefixes and suffixes, and a query.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from itertools import product

try:
    from re import _constants as c
    from re import _parser as parser
except ImportError:  # older Pythons
    import sre_constants as c
    import sre_parse as parser

#: Strings that a part may match before only its ends are kept, and characters of a class that are spelt out.
MOST_STRINGS, MOST_CHARS = 32, 6


def every(parts) -> object:
    parts = {p for p in parts if p is not True}
    flat = {q for p in parts for q in (p[1] if isinstance(p, tuple) and p[0] == "and" else (p,))}
    return True if not flat else flat.pop() if len(flat) == 1 else ("and", frozenset(flat))


def some(parts) -> object:
    parts = list(parts)
    if any(p is True for p in parts) or not parts:
        return True
    flat = {q for p in parts for q in (p[1] if isinstance(p, tuple) and p[0] == "or" else (p,))}
    return flat.pop() if len(flat) == 1 else ("or", frozenset(flat))


def grams(strings: set[bytes]) -> object:
    """What a text must hold if it holds one of the strings."""
    return some(every(s[i : i + 3] for i in range(len(s) - 2)) for s in strings)


@dataclass
class Part:
    """exact: all strings the part can match, or None; else the starts and ends of its matches (b"" : any)."""

    exact: set[bytes] | None = None
    starts: set[bytes] = field(default_factory=lambda: {b""})
    ends: set[bytes] = field(default_factory=lambda: {b""})
    query: object = True

    def loose(self) -> Part:
        if self.exact is None:
            return self
        return Part(None, {s[:2] for s in self.exact}, {s[-2:] for s in self.exact}, every([self.query, grams(self.exact)]))

    def needs(self) -> object:
        return every([self.query, grams(self.exact) if self.exact is not None else True])


def fold(char: int) -> bytes:
    return chr(char).lower().encode()


def chars(items) -> set[bytes] | None:
    out: set[bytes] = set()
    for op, value in items:
        if op is c.LITERAL:
            out.add(fold(value))
        elif op is c.RANGE and value[1] - value[0] < MOST_CHARS * 2:
            out |= {fold(x) for x in range(value[0], value[1] + 1)}
        else:
            return None
        if len(out) > MOST_CHARS:
            return None
    return out


def follow(a: Part, b: Part) -> Part:
    if a.exact is not None and b.exact is not None and len(a.exact) * len(b.exact) <= MOST_STRINGS:
        return Part({x + y for x, y in product(a.exact, b.exact)})
    ends_a = a.exact if a.exact is not None else a.ends
    starts_b = b.exact if b.exact is not None else b.starts
    across = True
    if len(ends_a) * len(starts_b) <= MOST_STRINGS * MOST_CHARS:
        across = grams({x[-2:] + y[:2] for x, y in product(ends_a, starts_b)})
    la, lb = a.loose(), b.loose()
    starts = {(x + y)[:2] for x, y in product(a.exact, starts_b)} if a.exact is not None else la.starts
    ends = {(x + y)[-2:] for x, y in product(ends_a, b.exact)} if b.exact is not None else lb.ends
    return Part(None, starts, ends, every([la.query, lb.query, across]))


def alternative(parts: list[Part]) -> Part:
    if all(p.exact is not None for p in parts) and sum(len(p.exact) for p in parts) <= MOST_STRINGS:
        return Part(set().union(*(p.exact for p in parts)))
    loose = [p.loose() for p in parts]
    return Part(None, set().union(*(p.starts for p in loose)), set().union(*(p.ends for p in loose)), some(p.query for p in loose))


def analyse(tree) -> Part:
    whole = Part({b""})
    for op, value in tree:
        if op is c.LITERAL:
            part = Part({fold(value)})
        elif op is c.IN:
            found = None if value and value[0][0] is c.NEGATE else chars(value)
            part = Part(found) if found else Part()
        elif op is c.SUBPATTERN:
            part = analyse(value[3])
        elif op is c.BRANCH:
            part = alternative([analyse(x) for x in value[1]])
        elif op in (c.MAX_REPEAT, c.MIN_REPEAT) or str(op) == "POSSESSIVE_REPEAT":
            low, high, inner = value
            one = analyse(inner)
            if (low, high) == (0, 1):
                part = alternative([Part({b""}), one]) if one.exact is not None else Part()
            elif low == 0:
                part = Part()
            else:
                part = Part({b""})
                for _ in range(min(low, 4)):
                    part = follow(part, one)
                if high != low or low > 4:
                    part = part.loose()
                    part = Part(None, part.starts, {b""}, part.query)
        elif op in (c.AT, c.ASSERT, c.ASSERT_NOT):
            part = Part({b""})
        else:
            part = Part()
        whole = follow(whole, part)
    return whole


def trigram_query(pattern: str) -> object:
    """The query that every text with a match satisfies, over bytes in lower case (A-Z folded)."""
    return analyse(parser.parse(pattern)).needs()


def trigrams(query: object) -> set[bytes]:
    if query is True:
        return set()
    return {query} if isinstance(query, bytes) else set().union(*(trigrams(q) for q in query[1]))


def compile_rule(pattern: str) -> re.Pattern:
    return re.compile(pattern)
