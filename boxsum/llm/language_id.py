"""Language identification by language-bitmask n-gram filters.

A text is lowered, every run of non-letters becomes one space, and its character n-grams are hashed. A language
contains an n-gram if its training texts hold it at least `least` times and at least `share` as often, per
n-gram, as the language where it is most frequent. All languages' Bloom filters lie bit-sliced in one table: a
row is a mask with a bit for each language, and the conjunction of an n-gram's rows is the set of all languages
that (but for false positives) contain it. A text's hits are counted for each language and corrected for the
language's rate of false positives, fill ** hashes; the most corrected hits decide, ties by more training
n-grams, then by name. The score is the winner's share of all corrected hits.

The score compares the languages with each other. Whether a text is in any of them at all is told by its known
part: of its own n-grams the share that some language holds, corrected likewise. A text in several languages
is known as a whole. Each language's floor is a part of the median known part of its training texts.

A text that is null or has no letter is `und` with score 0. Without a training text all others are `und` too.
Training takes all texts of a language, or a sample by hash of about `per_language` of them.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import cached_property, lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks, cut

N, LEAST, SHARE, HASHES, LOG_ROWS = 4, 3, 0.25, 2, 20
#: Training texts of a language, about; which ones depends on a hash of their ids alone.
PER_LANGUAGE = 3000
#: A language's floor, as a part of the median known part of its training texts.
FLOOR = 0.5
WORD = 60  # languages in a mask word
#: Most languages that a model can have: the driver holds a row for each.
LANGUAGES = 4096
MIX = np.uint64(0x9E3779B97F4A7C15)


@lru_cache(maxsize=1)
def letters() -> np.ndarray:
    """Flags of all code points; surrogates and the like are none."""
    return np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


def ngrams(texts: list[str | None], n: int = N) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all n-grams of all texts, how many each text has, and whether each has a letter."""
    joined = "".join((t or "").lower().replace("\n", " ") + "\n" for t in texts)
    codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    newline = codes == 10
    letter = letters()[codes]
    # one space for each run of others, the end of a text among them
    keep = letter.copy()
    keep[1:] |= letter[:-1]
    text = np.cumsum(newline) - newline
    clean, owner = np.where(letter, codes, 32)[keep].astype(np.uint64), text[keep]
    has = np.bincount(text[letter], minlength=len(texts)) > 0
    starts = np.searchsorted(owner, np.arange(len(texts)))
    # a space before each text and enough after it
    pad = np.full(n, 32, np.uint64)
    clean = np.insert(clean, np.repeat(starts, n), np.tile(pad, len(texts)))
    owner = np.insert(owner, np.repeat(starts, n), np.repeat(np.arange(len(texts)), n))
    clean, owner = np.concatenate([clean, pad]), np.concatenate([owner, np.full(n, len(texts))])
    size = len(clean) - n + 1
    h = np.zeros(size, np.uint64)
    letter_in = np.zeros(size, bool)
    for k in range(n):
        h = (h ^ clean[k : k + size]) * MIX
        h ^= h >> np.uint64(29)
        letter_in |= clean[k : k + size] != 32
    own = letter_in & (owner[:size] == owner[n - 1 :]) & (owner[:size] < len(texts))
    return h[own], np.bincount(owner[:size][own], minlength=len(texts)), has


def rows_of(h: np.ndarray, hashes: int, log_rows: int) -> list[np.ndarray]:
    mixed = h * MIX
    return [(((mixed >> np.uint64(32)) + np.uint64(k) * (mixed & np.uint64(0xFFFFFFFF) | np.uint64(1))) & np.uint64((1 << log_rows) - 1)).astype(np.int64) for k in range(hashes)]


@dataclass
class LanguageModel:
    languages: list[str]  # most training n-grams first
    masks: list[np.ndarray]  # for each word of languages, a mask for each row
    rates: np.ndarray  # of false positives
    n: int = N
    hashes: int = HASHES
    floors: np.ndarray | None = None  # least known part of a text, by its language

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        langs, scores, _ = self.judge(texts)
        return langs, scores

    @cached_property
    def known_rate(self) -> float:
        """The rate at which an n-gram of no language is held by one: rows far apart stand for those of two hashes."""
        known = np.zeros(len(self.masks[0]), bool)
        for masks in self.masks:
            found = masks
            for k in range(1, self.hashes):
                found = found & np.roll(masks, k * len(masks) // (2 * self.hashes) + k)
            known |= found != 0
        return float(known.mean())

    def above_floor(self, langs: list[str], known: list[float]) -> list[bool]:
        floors = dict(zip(self.languages, [0.0] * len(self.languages) if self.floors is None else self.floors.tolist(), strict=True))
        return [lang != "und" and x >= floors[lang] for lang, x in zip(langs, known, strict=True)]

    def judge(self, texts: list[str | None]) -> tuple[list[str], list[float], list[float]]:
        """Language, score and known part of each text."""
        if not self.languages:
            return ["und"] * len(texts), [0.0] * len(texts), [0.0] * len(texts)
        h, counts, has = ngrams(texts, self.n)
        hits = np.zeros((len(texts), len(self.languages)))
        known = np.zeros(len(texts))
        filled = np.flatnonzero(counts)
        if len(filled):
            starts = (np.cumsum(counts) - counts)[filled]
            at = rows_of(h, self.hashes, int(np.log2(len(self.masks[0]))))
            in_any = np.zeros(len(h), bool)
            for w, masks in enumerate(self.masks):
                found = masks[at[0]]
                for rows in at[1:]:
                    found = found & masks[rows]
                in_any |= found != 0
                for bit in range(min(WORD, len(self.languages) - w * WORD)):
                    hits[filled, w * WORD + bit] = np.add.reduceat(((found >> found.dtype.type(bit)) & found.dtype.type(1)).astype(np.int64), starts)
            rate = self.known_rate
            known[filled] = np.maximum(0, np.add.reduceat(in_any.astype(np.int64), starts) / counts[filled] - rate) / max(1 - rate, 1e-9)
        right = np.maximum(0, (hits - counts[:, None] * self.rates) / np.maximum(1 - self.rates, 1e-9))
        best = right.argmax(axis=1)
        total = right.sum(axis=1)
        score = np.where(total > 0, right[np.arange(len(texts)), best] / np.maximum(total, 1e-9), 0.0)
        return [self.languages[b] if ok else "und" for b, ok in zip(best, has, strict=True)], [float(s) if ok else 0.0 for s, ok in zip(score, has, strict=True)], known.tolist()


def _counted(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches, "text"):
        langs = np.array(b.column("lang").to_pylist(), object)
        texts = b.column("text").to_pylist()
        for lang in sorted(set(langs)):
            h, _, _ = ngrams([texts[i] for i in np.flatnonzero(langs == lang)], n)
            grams, counts = np.unique(h, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(grams), pa.string()), pa.array(grams.view(np.int64)), pa.array(counts, pa.int64())], ["lang", "gram", "n"])


def _by_language(counts: DataFrame) -> dict[str, int]:
    """(lang, n) on the driver; more than LANGUAGES are an error."""
    rows = counts.limit(LANGUAGES + 1).collect()
    if len(rows) > LANGUAGES:
        raise ValueError(f"more than {LANGUAGES} languages")
    return {r["lang"]: r["n"] for r in rows}


def _training(docs: DataFrame, id_col: str, text_col: str, lang_col: str, per_language: int | None) -> DataFrame:
    """(id, text, lang): the rows whose language is not null, or the sample of them."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang")).where("lang is not null")
    if per_language is None:
        return rows
    have = _by_language(rows.groupBy("lang").agg(F.count("*").alias("n")))
    if not have:
        return rows
    rate = F.coalesce(F.create_map(*(F.lit(x) for lang, k in have.items() for x in (lang, min(1.0, per_language / k))))[F.col("lang")], F.lit(1.0))
    return rows.where(F.pmod(F.xxhash64(F.coalesce(F.col("id").cast("string"), F.lit("")), F.lit(11)), F.lit(1_000_003)) < rate * 1_000_003)


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int | None = PER_LANGUAGE, n: int = N, least: int = LEAST, share: float = SHARE, hashes: int = HASHES, log_rows: int = LOG_ROWS) -> LanguageModel:
    """Fit on rows whose language is not null. The driver gets one number per filled row of the filter, 2**log_rows at most."""
    rows = _training(docs, id_col, text_col, lang_col, per_language)
    counts = cut(rows.select("text", "lang").mapInArrow(lambda it: _counted(it, n), "lang string, gram long, n long").groupBy("gram", "lang").agg(F.sum("n").alias("n")))
    totals = _by_language(counts.groupBy("lang").agg(F.sum("n").alias("n")))
    languages = sorted(totals, key=lambda x: (-totals[x], x))
    if not languages:
        return LanguageModel([], [], np.zeros(0), n, hashes)
    place = F.create_map(*(F.lit(x) for i, lang in enumerate(languages) for x in (lang, i)))[F.col("lang")]
    density = F.col("n") / F.create_map(*(F.lit(x) for lang in languages for x in (lang, float(totals[lang]))))[F.col("lang")]
    dense = counts.select("gram", place.alias("k"), "n", density.alias("d"))
    top = dense.groupBy("gram").agg(F.max("d").alias("top"), F.collect_list(F.struct("k", "n", "d")).alias("all"))  # one entry a language
    inside = top.select("gram", F.explode("all").alias("x"), "top").where((F.col("x.n") >= least) & (F.col("x.d") >= share * F.col("top"))).select("gram", F.col("x.k").alias("k"))
    grams = inside.groupBy("gram", F.floor(F.col("k") / WORD).cast("int").alias("word")).agg(F.sum(F.expr(f"shiftleft(1L, k % {WORD})")).alias("mask"))

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for rows in rows_of(np.asarray(b.column("gram")).view(np.uint64), hashes, log_rows):
                yield pa.RecordBatch.from_arrays([pa.array(rows), b.column("word"), b.column("mask")], ["row", "word", "mask"])

    filled = grams.mapInArrow(spread, "row long, word int, mask long").groupBy("row", "word").agg(F.bit_or("mask").alias("mask")).toArrow()
    words = -(-len(languages) // WORD)
    row, word, mask = (np.asarray(filled.column(c).combine_chunks()) for c in ("row", "word", "mask"))
    masks = [np.zeros(1 << log_rows, np.uint64) for _ in range(words)]
    for w in range(words):
        masks[w][row[word == w]] = mask[word == w].astype(np.uint64)
    fill = np.array([float(((masks[i // WORD] >> np.uint64(i % WORD)) & np.uint64(1)).mean()) for i in range(len(languages))])
    if len(languages) <= 8:
        masks = [m.astype(np.uint8) for m in masks]
    return LanguageModel(languages, masks, fill**hashes, n, hashes)


def with_floors(model: LanguageModel, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int | None = PER_LANGUAGE, part: float = FLOOR) -> LanguageModel:
    """The model with floors learned from the texts that it was trained on. The driver gets a number a language."""
    if not model.languages:
        return model
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            _, _, known = held.value.judge(b.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([b.column("lang"), pa.array(known, pa.float64())], ["lang", "known"])

    rows = _training(docs, id_col, text_col, lang_col, per_language).select("text", "lang").mapInArrow(run, "lang string, known double")
    # texts without a known n-gram, those without a letter among them, tell nothing of the others
    medians = {r["lang"]: r["m"] for r in rows.where("known > 0").groupBy("lang").agg(F.percentile_approx("known", 0.5).alias("m")).collect()}
    return replace(model, floors=np.array([part * medians.get(lang, 0.0) for lang in model.languages]))


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang_pred, score) of every row's whole text. The model is broadcast; its size is set by log_rows."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            langs, scores = held.value.predict(b.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], ["id", "lang_pred", "score"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, lang_pred string, score double").withColumnRenamed("id", id_col)


def keep_identified(docs: DataFrame, model: LanguageModel, least: float = 0.0, text_col: str = "text") -> DataFrame:
    """The rows whose text has a language by the model with at least that score, and reaches its floor if the model has floors.

    All their columns stay as they are.
    """
    held, schema = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, text_col):
            langs, scores, known = held.value.judge(b.column(at).to_pylist())
            yield b.filter(pa.array([ok and s >= least for ok, s in zip(held.value.above_floor(langs, known), scores, strict=True)], pa.bool_()))

    return docs.mapInArrow(run, schema)
