"""Byte-level BPE by merge replay over the words of a block of documents.

Each task replays the merges over all new words of a block at once. An inverted index leads from a token
pair to the positions where it stands; pairs are taken in rank order from a heap, and each merge touches only
the two neighbours of its position. A pair made by a merge always ranks later than that merge, so every rank is
visited once. Words that were replayed stay in a bounded cache of the worker; a full cache is emptied, which
costs time and changes nothing in the result.

Null and empty texts have no tokens. Repeated rows are encoded each. Nothing but the named columns is read.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks

#: Replayed words that a worker keeps.
CACHE_WORDS = 300_000
#: Bytes of text whose new words are replayed together.
BLOCK = 16 << 20
#: The same pieces as the tokenizer's pattern, for text of ASCII only.
ASCII_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r A-Za-z0-9]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+"


class MergeReplay:
    """A vocabulary of ranks and the replay of its merges."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, cache_words: int = CACHE_WORDS):
        self.ranks, self.cache_words = ranks, cache_words
        self.tokens = {i: t for t, i in ranks.items()}
        self.split_any = regex.compile(pattern.replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")).findall
        self.split_ascii = re.compile(ASCII_PATTERN).findall
        # (left token << 32 | right token) -> the token both become, for every way to halve a token
        self.pairs = {ranks[t[:i]] << 32 | ranks[t[i:]]: r for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks}
        self.keys = np.array(sorted(self.pairs), np.int64)
        self.made = np.array([self.pairs[k] for k in self.keys.tolist()], np.int64)
        self.byte = np.array([ranks[bytes([i])] for i in range(256)], np.int64)
        size = max(self.tokens) + 1
        self.lengths = np.array([len(self.tokens.get(i, b"")) for i in range(size)], np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(self.lengths)[:-1]])
        self.bytes = np.frombuffer(b"".join(self.tokens.get(i, b"") for i in range(size)), np.uint8)
        self.digits = [f" {i}" for i in range(size)]
        self.cache: dict[str, bytes] = {}
        self.shown: dict[str, str] = {}

    def words(self, text: str) -> list[str]:
        return (self.split_ascii if text.isascii() else self.split_any)(text)

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The token that each pair becomes, or -1."""
        keys = left << 32 | right
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, self.made[at], -1)

    def replay(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Token ids of all words and where each word's begin, by all merges in rank order over all words together."""
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        lengths = np.fromiter(map(len, raw), np.int64, len(raw))
        ends = np.cumsum(lengths)
        size = int(ends[-1]) if len(ends) else 0
        # Chains of positions: plain buffers for single merges, with numpy views of the same memory for many at once.
        chain = [array("q", bytes(8 * size)) for _ in range(4)]
        token, before, after, rank = chain
        token_n, before_n, after_n, rank_n = views = [np.frombuffer(x, np.int64) for x in chain] if size else [np.zeros(0, np.int64)] * 4
        del views
        if size:
            token_n[:] = self.byte[np.frombuffer(b"".join(raw), np.uint8)]
            before_n[:], after_n[:] = np.arange(-1, size - 1), np.arange(1, size + 1)
            before_n[(ends - lengths)[lengths > 0]] = -1
            after_n[ends[lengths > 0] - 1] = -1
            rank_n[:-1] = self.rank_of(token_n[:-1], token_n[1:])
            rank_n[after_n < 0] = -1
        held = np.flatnonzero(rank_n >= 0)
        held = held[np.argsort(rank_n[held], kind="stable")]
        first, at = np.unique(rank_n[held], return_index=True)
        index: dict[int, list[int] | list] = {}
        for made, places in zip(first.tolist(), np.split(held, at[1:]), strict=False):
            index[made] = [places]
        heap = first.tolist()
        pairs = self.pairs.get

        def note(made: int, place) -> None:
            if made in index:
                index[made].append(place)
            else:
                index[made] = [place]
                heapq.heappush(heap, made)

        while heap:
            made = heapq.heappop(heap)
            entry = index.pop(made)
            many = sum(1 if isinstance(x, int) else len(x) for x in entry) > 24
            if many:
                places = np.sort(np.concatenate([np.atleast_1d(x) for x in entry]))
                places = places[(rank_n[places] == made) & (np.diff(places, prepend=-1) > 0)]
                many = len(places) > 24 and not (after_n[places[:-1]] == places[1:]).any()
                entry = places.tolist()
            else:
                entry = sorted({y for x in entry for y in ((x,) if isinstance(x, int) else x.tolist())})
            if many:
                then = after_n[places]
                follow = after_n[then]
                token_n[places], token_n[then], rank_n[then] = made, -1, -1
                after_n[places] = follow
                inner = follow >= 0
                before_n[follow[inner]] = places[inner]
                rank_n[places] = -1
                rank_n[places[inner]] = self.rank_of(token_n[places[inner]], token_n[follow[inner]])
                prior = before_n[places]
                prior = prior[prior >= 0]
                rank_n[prior] = self.rank_of(token_n[prior], token_n[after_n[prior]])
                touched = np.concatenate([places[inner], prior])
                ranks = rank_n[touched]
                touched, ranks = touched[ranks >= 0], ranks[ranks >= 0]
                if len(touched):
                    order = np.argsort(ranks, kind="stable")
                    new, at = np.unique(ranks[order], return_index=True)
                    for r, places in zip(new.tolist(), np.split(touched[order], at[1:]), strict=True):
                        note(r, places)
                continue
            for at in entry:
                if rank[at] != made:  # stale: one of both has gone into another merge meanwhile
                    continue
                then = after[at]
                follow = after[then]
                token[at], token[then], rank[then], rank[at] = made, -1, -1, -1
                after[at] = follow
                if follow >= 0:
                    before[follow] = at
                    if (new := pairs(made << 32 | token[follow])) is not None:
                        rank[at] = new
                        note(new, at)
                if (prior := before[at]) >= 0:
                    if (new := pairs(token[prior] << 32 | made)) is not None:
                        rank[prior] = new
                        note(new, prior)
                    else:
                        rank[prior] = -1
        live = token_n >= 0
        cuts = np.concatenate([[0], np.cumsum(live)])[np.concatenate([[0], ends]).astype(np.int64)]
        return token_n[live].astype("<u4"), cuts

    def learn(self, texts: list[list[str]]) -> None:
        """Replay what the cache lacks of these words."""
        words = set().union(*texts) if texts else set()
        new = words.difference(self.cache)
        if self.cache and len(self.cache) + len(new) > self.cache_words:
            self.cache.clear()
            self.shown.clear()
            new = words
        new = list(new)
        ids, cuts = self.replay(new)
        raw, digits, cuts = ids.tobytes(), list(map(self.digits.__getitem__, ids.tolist())), cuts.tolist()
        self.cache.update((w, raw[4 * a : 4 * b]) for w, a, b in zip(new, cuts, cuts[1:], strict=False))
        self.shown.update((w, "".join(digits[a:b])) for w, a, b in zip(new, cuts, cuts[1:], strict=False))

    def encode_batch(self, texts: list[str | None]) -> list[np.ndarray]:
        return [ids for ids, _ in self.encode_shown(texts)]

    def encode_shown(self, texts: list[str | None]) -> Iterator[tuple[np.ndarray, str]]:
        """Of each text the ids and the same in decimal, joined by one space."""
        split = [self.words(t or "") for t in texts]
        self.learn(split)
        for words in split:
            yield np.frombuffer(b"".join(map(self.cache.__getitem__, words)), "<u4"), "".join(map(self.shown.__getitem__, words))[1:]

    def decode(self, ids) -> bytes:
        ids = np.asarray(ids, np.int64)
        sizes = self.lengths[ids]
        starts = np.cumsum(sizes) - sizes
        return self.bytes[np.repeat(self.offsets[ids] - starts, sizes) + np.arange(int(sizes.sum()))].tobytes()


@lru_cache(maxsize=4)
def load(path: str, pattern: str) -> MergeReplay:
    with open(path, "rb") as f:
        return MergeReplay({base64.b64decode(t): int(r) for t, r in map(bytes.split, filter(None, f.read().splitlines()))}, pattern)


def encode(docs: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids array<int>): the tokens of each row's whole text. `vocabulary`: a rank file every worker has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(vocabulary, pattern)
        for b in blocks(batches, "text", BLOCK):
            ids = [x.astype(np.int32) for x in bpe.encode_batch(b.column("text").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(ids, pa.list_(pa.int32()))], ["id", "ids"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, ids array<int>").withColumnRenamed("id", id_col)


def decode(encoded: DataFrame, vocabulary: str, pattern: str, ids_col: str = "ids", out: str = "decoded") -> DataFrame:
    """The rows with one more column, the bytes that their ids stand for (null ids: null). `out` must be a new name."""
    if out in encoded.columns:
        raise ValueError(f"column {out} is there already")
    from pyspark.sql.types import BinaryType, StructType

    schema = StructType([*encoded.schema.fields]).add(out, BinaryType())
    at = encoded.columns.index(ids_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(vocabulary, pattern)
        for b in batches:
            raw = [None if ids is None else bpe.decode(ids) for ids in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(raw, pa.binary())], [*b.schema.names, out])

    return encoded.mapInArrow(run, schema)


def round_trip(docs: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256): encode, decode, and digest both in one pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(vocabulary, pattern)
        for b in blocks(batches, "text", BLOCK):
            out = [(len(ids), hashlib.sha256(shown.encode()).hexdigest(), hashlib.sha256(bpe.decode(ids)).hexdigest()) for ids, shown in bpe.encode_shown(b.column("text").to_pylist())]
            n, ids_hash, raw_hash = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(n, pa.int64()), pa.array(ids_hash), pa.array(raw_hash)], ["id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, n_tokens long, ids_sha256 string, decoded_sha256 string").withColumnRenamed("id", id_col)
