"""Secret scans over a trigram inverted index.

Each rule is a regular expression; its Boolean trigram query is derived from it. A task indexes its texts block
by block: from each trigram that some query names to the postings of texts that hold it (bytes with A-Z folded,
found in one pass over the block). Queries are intersections and unions of postings; only candidates are given
to the regular expression. Rules without mandatory trigrams scan every text of the block.

The base rules are found leftmost and not overlapping, each kind for itself, and matches that are too short are
dropped after matching. Further kinds add spans. Null and empty texts hold none.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks
from boxsum.llm.trigram_query import trigram_query, trigrams


@dataclass(frozen=True)
class Rule:
    """kind, expression, the group whose length counts and its least length."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1


def either(word: str) -> str:
    """The expression of a word in either case."""
    return "".join(f"[{x.lower()}{x.upper()}]" if x.isalpha() else x for x in word)


# The base rules, and public formats of further credentials.
NAMES = "|".join([either("password"), either("passwd"), either("secret"), either("token"), either("api") + "_?" + either("key")])
BASE = (
    Rule("assign", rf"""({NAMES})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 16),
    Rule("hex", r"[0-9a-f]+", 0, 32),
)
# A key runs to its END line, of which no other BEGIN stands before; where that is missing, over its header fields and
# runs of base64 to a last, shorter line of it. Line breaks may be written as escapes, as in JSON.
BREAK, LINE_BREAK = r"(?:\\[rn]|\s)", r"(?:\\[rn]|[\r\n])+[ \t]*"
WHOLE = r"(?:[^-]|-(?!----BEGIN ))*?-----END [A-Z ]*PRIVATE KEY-----"
CUT_OFF = rf"(?:{BREAK}+(?:Proc-Type|DEK-Info|Version|Comment):[^\r\n\\]*)*(?:{BREAK}*[A-Za-z0-9+/]{{24,}}={{0,2}}(?![A-Za-z0-9+/=_-]))*(?:{LINE_BREAK}[A-Za-z0-9+/]+={{0,2}}(?=[ \t]*(?:\\[rn]|[\r\n\"']|$)))?"
FURTHER = (
    Rule("private_key", rf"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:{WHOLE}|{CUT_OFF})"),
    Rule("source_host", r"gh[pousr]_[A-Za-z0-9]{36}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("web_token", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
    Rule("map_key", r"AIza[0-9A-Za-z_-]{35}"),
    Rule("payment", r"sk_live_[0-9A-Za-z]{16,}"),
    Rule("url_login", r"[a-z]{3,10}://[^\s/:@]+:[^\s/:@]{3,}@[A-Za-z0-9.-]+"),
)
RULES = (*BASE, *FURTHER)
Span = tuple[int, int, int]


class Index:
    """Postings of the trigrams that the rules' queries name, over the texts of a block."""

    def __init__(self, texts: list[bytes], wanted: np.ndarray):
        # wanted: 2**24 flags, by a trigram's three bytes as a number
        sizes = np.fromiter(map(len, texts), np.int64, len(texts)) + 1
        flat = np.frombuffer(b"\0".join(texts) + b"\0\0\0", np.uint8).astype(np.uint32)
        codes = flat[:-2] << 16 | flat[1:-1] << 8 | flat[2:]
        at = np.flatnonzero(wanted[codes])
        pairs = np.unique(codes[at].astype(np.int64) << 32 | np.searchsorted(np.cumsum(sizes), at, "right"))
        found, starts = np.unique(pairs >> 32, return_index=True)
        self.texts = np.arange(len(texts))
        self.postings = dict(zip(found.tolist(), np.split(pairs & 0xFFFFFFFF, starts[1:]), strict=False)) if len(found) else {}

    def candidates(self, query: object) -> np.ndarray:
        if query is True:
            return self.texts
        if isinstance(query, bytes):
            return self.postings.get(int.from_bytes(query, "big"), self.texts[:0])
        parts = sorted((self.candidates(q) for q in query[1]), key=len)
        if query[0] == "or":
            return np.unique(np.concatenate(parts))
        out = parts[0]
        for p in parts[1:]:
            out = np.intersect1d(out, p, assume_unique=True)
        return out


class Scanner:
    def __init__(self, rules: tuple[Rule, ...] = RULES):
        self.rules = rules
        self.queries = [trigram_query(r.pattern) for r in rules]
        # A run of a class is maximal where it matches, so a shorter one can be passed over while matching.
        self.find = [re.compile(r.pattern[:-1] + f"{{{r.least},}}" if re.fullmatch(r"\[[^\]]+\]\+", r.pattern) else r.pattern).finditer for r in rules]
        self.wanted = np.zeros(1 << 24, bool)
        for q in self.queries:
            for t in trigrams(q):
                self.wanted[int.from_bytes(t, "big")] = True

    def scan(self, texts: list[str | None]) -> list[list[Span]]:
        """Of each text (start, end, rule number) in code points, by start and then rule."""
        texts = [t or "" for t in texts]
        index = Index([t.encode("utf-8", "surrogatepass").lower() for t in texts], self.wanted)
        out: list[list[Span]] = [[] for _ in texts]
        for k, (rule, query, find) in enumerate(zip(self.rules, self.queries, self.find, strict=True)):
            group, least = rule.group, rule.least
            for i in index.candidates(query).tolist():
                out[i] += [(m.start(), m.end(), k) for m in find(texts[i]) if m.end(group) - m.start(group) >= least]
        for spans in out:
            spans.sort(key=lambda s: (s[0], s[2]))
        return out


@lru_cache(maxsize=4)
def scanner(rules: tuple[Rule, ...]) -> Scanner:
    return Scanner(rules)


def _map(docs: DataFrame, id_col: str, text_col: str, rules: tuple[Rule, ...], schema: str, columns: Callable) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by = scanner(rules)
        for b in blocks(batches, "text"):
            yield columns(b.column("id"), by.scan(b.column("text").to_pylist()), rules)

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, {schema}").withColumnRenamed("id", id_col)


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(id, spans array<struct<kind, start, end>>): all spans of each text, in code points, the end exclusive."""

    def columns(ids, found, rules):
        spans = [[{"kind": rules[k].kind, "start": a, "end": b} for a, b, k in s] for s in found]
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        return pa.RecordBatch.from_arrays([ids, pa.array(spans, kind)], ["id", "spans"])

    return _map(docs, id_col, text_col, rules, "spans array<struct<kind: string, start: int, end: int>>", columns)


def summarise(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(id, n_assign, n_access, n_hex, base_sha256, spans): counts and digest of the base spans; all spans as a string."""

    def columns(ids, found, rules):
        out = []
        for s in found:
            base = [x for x in s if x[2] < len(BASE)]
            show = lambda xs: ",".join(f"{rules[k].kind}:{a}:{b}" for a, b, k in xs)
            out.append((*(sum(x[2] == k for x in base) for k in range(len(BASE))), hashlib.sha256(show(base).encode()).hexdigest(), show(s)))
        return pa.RecordBatch.from_arrays([ids, *(pa.array(x, pa.int64() if i < len(BASE) else pa.string()) for i, x in enumerate(zip(*out, strict=True)))], ["id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return _map(docs, id_col, text_col, rules, "n_assign long, n_access long, n_hex long, base_sha256 string, spans string", columns)


def redact(docs: DataFrame, text_col: str = "text", rules: tuple[Rule, ...] = RULES, mark: str = "[secret]", length_col: str | None = None) -> DataFrame:
    """docs with each span of its text replaced by a mark; overlapping spans are one.

    Other columns, and null texts, stay; length_col, if given, gets the new length of each text that changed.
    """
    at, count = docs.columns.index(text_col), docs.columns.index(length_col) if length_col else None
    types = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by = scanner(rules)
        for b in blocks(batches, text_col):
            texts = b.column(at).to_pylist()
            sizes = b.column(count).to_pylist() if count is not None else None
            for i, spans in enumerate(by.scan(texts)):
                if not spans:
                    continue
                parts, done = [], 0
                for a, e, _ in spans:
                    if a >= done:
                        parts += [texts[i][done:a], mark]
                    done = max(done, e)
                texts[i] = "".join([*parts, texts[i][done:]])
                if sizes is not None:
                    sizes[i] = len(texts[i])
            cols = list(b.columns)
            if sizes is not None:
                cols[count] = pa.array(sizes, b.schema.field(count).type)
            cols[at] = pa.array(texts, b.schema.field(at).type)
            yield pa.RecordBatch.from_arrays(cols, schema=b.schema)

    return docs.mapInArrow(run, types)
