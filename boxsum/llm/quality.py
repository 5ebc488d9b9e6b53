"""Quality classifier by co-training of two views.

View one reads the text alone (shares of character classes, word statistics, repetition, compressibility over
the whole text); view two reads the metadata alone (source, language, recorded length, also as bins). Both are logistic
models fitted on labelled rows. In each round each view labels the unlabelled rows that it is most sure of, by
its calibrated probability, and hands them to the other; then both are fitted anew. At the end each view is
calibrated on labelled rows that no fit has seen, and the calibrated log-odds, each relative to the base rate,
are added up. A view that tells nothing is calibrated to the base rate and so neither labels nor decides.

Fitting uses bounded samples, `labelled` and `unlabelled` rows, chosen by a hash of the id; features leave the
executors, texts don't. Of rows that repeat an id, the one with the least features stands for it. Scores are for all rows and whole texts. Null or empty texts have score 0. Without both
classes among the labels every other row gets score 1.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.shared import blocks

#: Bounds of the samples that the views are fitted on.
LABELLED, UNLABELLED = 4000, 4000
ROUNDS, SURE, GIVEN, KEEP = 4, 0.97, 300, 0.5
BUCKETS = 64  # of hashed metadata values
LENGTHS = 24  # bins of a recorded length, each from a power of two to the next

_CLASSES = np.zeros((256, 8))
for _b in range(256):
    _c = chr(_b)
    _k = 0 if "a" <= _c <= "z" else 1 if "A" <= _c <= "Z" else 2 if "0" <= _c <= "9" else 3 if _c == " " else 4 if _c == "\n" else 5 if _c in ".,;:'\"?-()" else 6 if _b < 128 else 7
    _CLASSES[_b, _k] = 1


def text_features(text: str) -> list[float]:
    """Numbers that describe a whole text whatever its length."""
    raw = text.encode("utf-8", "surrogatepass")
    n = max(1, len(raw))
    shares = np.bincount(np.frombuffer(raw, np.uint8), minlength=256) @ _CLASSES / n
    words = text.split()
    k = max(1, len(words))
    lines = [x for x in text.split("\n") if x]
    again = sum(map(str.__eq__, words, words[1:])) / k
    odd = sum(not w[-1].isalnum() and w[-1] not in ".,;:'\"?-)" for w in words) / k
    upper = sum(map(str.isupper, words)) / k
    packed = len(zlib.compress(raw, 1)) / n
    return [*shares, again, odd, upper, packed, np.log1p(k), len(set(words)) / k ** 0.8, sum(map(len, words)) / k, 1 - len(set(lines)) / max(1, len(lines)), np.log1p(k / max(1, len(lines)))]


N_TEXT = len(text_features("a"))


def meta_features(source: str | None, lang: str | None, size: int | None) -> list[float]:
    out = [0.0] * (2 * BUCKETS + LENGTHS)
    out[zlib.crc32(str(source).encode()) % BUCKETS] = 1.0
    out[BUCKETS + zlib.crc32(str(lang).encode()) % BUCKETS] = 1.0
    out[2 * BUCKETS + min(LENGTHS - 1, max(0, size or 0).bit_length())] = 1.0
    return [*out, np.log1p(max(0, size or 0)), float(size is None)]


N_META = len(meta_features(None, None, None))


@dataclass
class Logistic:
    """L2-regularised logistic regression on standardised features, fitted by Newton steps."""

    ridge: float = 1.0
    mean: np.ndarray = field(default_factory=lambda: np.zeros(0))
    scale: np.ndarray = field(default_factory=lambda: np.ones(0))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def fit(self, x: np.ndarray, y: np.ndarray) -> Logistic:
        self.mean, self.scale = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-3)
        z = self._inputs(x)
        w, penalty = np.zeros(z.shape[1]), np.full(z.shape[1], self.ridge)
        penalty[-1] = 1e-6
        for _ in range(25):
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            step = np.linalg.solve((z.T * np.maximum(p * (1 - p), 1e-6)) @ z + np.diag(penalty), z.T @ (y - p) - penalty * w)
            w = w + step * min(1.0, 5 / max(1e-9, np.abs(step).max()))
            if np.abs(step).max() < 1e-6:
                break
        self.weights = w
        return self

    def _inputs(self, x: np.ndarray) -> np.ndarray:
        return np.column_stack([np.clip((x - self.mean) / self.scale, -10, 10), np.ones(len(x))])

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self._inputs(x) @ self.weights


@dataclass
class View:
    """A model and its calibration: log-odds = slope * margin + shift."""

    model: Logistic
    slope: float = 1.0
    shift: float = 0.0

    def calibrate(self, x: np.ndarray, y: np.ndarray) -> View:
        fitted = Logistic(ridge=1e-3).fit(self.model.margin(x)[:, None], y)
        self.slope = max(0.0, float(fitted.weights[0] / fitted.scale[0]))
        self.shift = float(fitted.weights[1] - fitted.weights[0] * fitted.mean[0] / fitted.scale[0]) if self.slope else float(np.log(max(y.mean(), 1e-6) / max(1 - y.mean(), 1e-6)))
        return self

    def log_odds(self, x: np.ndarray) -> np.ndarray:
        return self.slope * self.model.margin(x) + self.shift


@dataclass
class QualityModel:
    text: View | None
    meta: View | None
    base: float = 0.0  # log-odds of a good row
    handed: tuple[int, int] = (0, 0)  # pseudo-labels that each view gave in all

    def score(self, text: np.ndarray, meta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Calibrated probabilities of the text view, the metadata view, and of both."""
        if self.text is None:
            return (np.ones(len(text)),) * 3
        a, b = self.text.log_odds(text), self.meta.log_odds(meta)
        return tuple(1 / (1 + np.exp(-np.clip(v, -30, 30))) for v in (a, b, a + b - self.base))


def co_train(text: np.ndarray, meta: np.ndarray, y: np.ndarray, text_u: np.ndarray, meta_u: np.ndarray, rounds: int = ROUNDS, sure: float = SURE, given: int = GIVEN) -> QualityModel:
    """Two views from labelled and unlabelled features; a fourth of the labelled rows only calibrates."""
    if len(y) < 8 or y.min() == y.max():
        return QualityModel(None, None)
    held = np.arange(len(y)) % 4 == 3
    if y[held].min() == y[held].max() or y[~held].min() == y[~held].max():
        held = np.zeros(len(y), bool)
    fit, cal = ~held, held if held.any() else np.ones(len(y), bool)
    base = y[fit].mean()
    labels = [np.full(len(text_u), -1.0), np.full(len(text_u), -1.0)]  # what each view was given
    views: list[View] = []
    handed = [0, 0]
    for turn in range(rounds + 1):
        views = []
        for x, u, got in ((text, text_u, labels[0]), (meta, meta_u, labels[1])):
            has = got >= 0
            model = Logistic().fit(np.concatenate([x[fit], u[has]]), np.concatenate([y[fit], got[has]]))
            views.append(View(model).calibrate(x[cal], y[cal]))
        if turn == rounds or not len(text_u):
            break
        for giver, u, to in ((0, text_u, 1), (1, meta_u, 0)):
            p = 1 / (1 + np.exp(-np.clip(views[giver].log_odds(u), -30, 30)))
            for good, by, most in ((1.0, p, base), (0.0, 1 - p, 1 - base)):
                free = np.flatnonzero((labels[to] < 0) & (by >= sure))
                some = free[np.argsort(-by[free], kind="stable")[: max(1, round(given * most))]]
                labels[to][some] = good
                handed[giver] += len(some)
    rate = y.mean()
    return QualityModel(*views, float(np.log(rate / (1 - rate))), tuple(handed))


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices with their text and metadata features; columns text, source, lang, n_chars come by name."""
    for b in blocks(batches, "text"):
        texts = b.column("text").to_pylist()
        meta = zip(*(b.column(c).to_pylist() for c in ("source", "lang", "n_chars")), strict=True)
        yield b, np.array([text_features(t or "") for t in texts]), np.array([meta_features(*m) for m in meta])


def _inputs(docs: DataFrame, id_col: str, text_col: str, source_col: str, lang_col: str, size_col: str) -> DataFrame:
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.col(source_col).cast("string").alias("source"), F.col(lang_col).cast("string").alias("lang"), F.col(size_col).cast("long").alias("n_chars"))


COLUMNS = {"id_col": "doc_id", "text_col": "text", "source_col": "source", "lang_col": "lang", "size_col": "n_chars"}


def train(docs: DataFrame, labels: DataFrame, label_col: str = "quality", labelled: int = LABELLED, unlabelled: int = UNLABELLED, columns: dict[str, str] | None = None, **options) -> QualityModel:
    """Fit on at most `labelled` + `unlabelled` rows. labels: the ids and their classes, 1 for good; repeated ids count once."""
    columns = COLUMNS | (columns or {})
    rows = _inputs(docs, **columns)
    known = labels.select(F.col(columns["id_col"]).alias("id"), F.col(label_col).cast("double").alias("y")).where("id is not null and y is not null").groupBy("id").agg(F.max("y").alias("y"))
    order = lambda c: (F.xxhash64(c, F.lit(5)), c)
    chosen = known.orderBy(*order("id")).limit(labelled)
    others = rows.select("id").where("id is not null").join(known.select("id"), "id", "left_anti").orderBy(*order("id")).limit(unlabelled)
    picked = chosen.unionByName(others.withColumn("y", F.lit(-1.0)))  # as many rows as the two bounds allow

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, text, meta in _features(batches):
            both = pa.array(list(np.hstack([text, meta])), pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("y"), both], ["id", "y", "x"])

    kind = dict(rows.dtypes)["id"]
    featured = rows.join(F.broadcast(picked), "id").select("id", "text", "source", "lang", "n_chars", "y").mapInArrow(run, f"id {kind}, y double, x array<double>")
    # one row an id leaves the executors: of several, the one with the least features
    got = featured.groupBy("id").agg(F.min("y").alias("y"), F.min("x").alias("x")).toPandas().sort_values("id", kind="stable")
    x, y = np.stack(got["x"]) if len(got) else np.zeros((0, N_TEXT + N_META)), got["y"].to_numpy(float)
    text, meta, sure = x[:, :N_TEXT], x[:, N_TEXT:], y >= 0
    return co_train(text[sure], meta[sure], (y[sure] >= 0.5).astype(float), text[~sure], meta[~sure], **options)


def _decide(model: QualityModel, b: pa.RecordBatch, text: np.ndarray, meta: np.ndarray, keep: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    has = np.array([bool(t and t.strip()) for t in b.column("text").to_pylist()], bool)
    scores = tuple(np.where(has, s, 0.0) for s in model.score(text, meta))
    return (*scores, scores[2] >= keep)


def score(docs: DataFrame, model: QualityModel, keep: float = KEEP, columns: dict[str, str] | None = None) -> DataFrame:
    """(id, text_score, meta_score, score, kept) of every row."""
    columns = COLUMNS | (columns or {})
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, text, meta in _features(batches):
            yield pa.RecordBatch.from_arrays([b.column("id"), *map(pa.array, _decide(held.value, b, text, meta, keep))], ["id", "text_score", "meta_score", "score", "kept"])

    rows = _inputs(docs, **columns)
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, text_score double, meta_score double, score double, kept boolean").withColumnRenamed("id", columns["id_col"])


def keep_good(docs: DataFrame, model: QualityModel, keep: float = KEEP, columns: dict[str, str] | None = None) -> DataFrame:
    """The rows with at least that score; all their columns stay as they are."""
    columns = COLUMNS | (columns or {})
    held, schema = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    at = {"id": docs.columns.index(columns["id_col"]), "text": docs.columns.index(columns["text_col"]), "source": docs.columns.index(columns["source_col"]), "lang": docs.columns.index(columns["lang_col"]), "n_chars": docs.columns.index(columns["size_col"])}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in blocks(batches, columns["text_col"]):
            named = pa.RecordBatch.from_arrays([whole.column(i) for i in at.values()], list(at))
            for b, text, meta in _features(iter([named])):
                yield whole.filter(pa.array(_decide(held.value, b, text, meta, keep)[3]))

    return docs.mapInArrow(run, schema)
