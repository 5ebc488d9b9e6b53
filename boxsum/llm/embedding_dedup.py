"""Near duplicates among embeddings: rotated binary codes with correction factors, then exact recomputation.

Each distinct vector is normalised and turned by a fixed random rotation; its code is the signs of the turned
vector, packed; its factor the inner product f of the vector with its own code (scaled to length one). Codes and
factors are stored with the vectors, and pairs go through three tests:

1. The bits by which two codes differ, counted on the packed words. For vectors at an angle a each bit differs
   with probability a / pi; a pair is ruled out if more differ than at the threshold's angle by `epsilon` standard
   deviations.
2. With q the other turned vector and b = <code, q>, b / f estimates the cosine c without bias. Its error is
   sqrt(1 - f^2) / f * <rest, q>, rest a unit vector at right angles to the coded one, of which q holds a part of
   sqrt(1 - c^2); so a pair at or above the threshold t is under t - sqrt((1 - f^2)(1 - t^2) / (d - 1)) / f * e
   with a probability of at most exp(-e^2 / 2), and is ruled out there. What is surely below, by the angles of
   both vectors to the code, goes as well.
3. What is left is recomputed exactly, in double precision.

With the default epsilon a link is lost with a probability of about 1e-7; a test measures the recall.

Vectors are compared when their labels and lengths are equal. Null labels or vectors, vectors with null or
non-finite components, and zero vectors link with nothing. Equal vectors are compared once, as one of a weight.
Groups above `tile` distinct vectors are dealt in tiles by hash; each pair of tiles is a task of bounded size,
which returns a row per linked vector, never the pairs. Repeated ids are vectors of their own.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from boxsum.llm.components import components
from boxsum.llm.forest import roots
from boxsum.llm.shared import cut

THRESHOLD, TILE, EPSILON, SEED = 0.93, 2048, 6.0, 20_240_101
#: Rows of a tile whose bit counts are held at once, pairs that are estimated or recomputed at once, and tasks at most.
ROWS, PAIRS, TASKS = 512, 1 << 15, 100_000


@lru_cache(maxsize=8)
def rotation(d: int, seed: int = SEED) -> np.ndarray:
    """A random orthogonal matrix, the same in every task."""
    q, r = np.linalg.qr(np.random.default_rng((seed, d)).standard_normal((d, d)))
    return q * np.sign(np.diag(r))


def turn(x: np.ndarray) -> np.ndarray:
    """Unit vectors, turned."""
    x = np.asarray(x, np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True) @ rotation(x.shape[1]).T


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Packed sign codes of the turned vectors, in words of 64 bits, and their factors."""
    turned = turn(x)
    bits = np.packbits(turned > 0, axis=1)
    words = np.zeros((len(bits), -(-bits.shape[1] // 8) * 8), np.uint8)
    words[:, : bits.shape[1]] = bits
    return words.view(np.uint64), np.abs(turned).sum(axis=1) / np.sqrt(x.shape[1])


def most_bits(d: int, threshold: float, epsilon: float) -> float:
    """Differing bits above which a pair is not at the threshold, at a confidence of `epsilon` standard deviations."""
    p = np.arccos(np.clip(threshold, -1, 1)) / np.pi
    return d * p + epsilon * np.sqrt(d * p * (1 - p))


def estimates(code: np.ndarray, factor: np.ndarray, turned: np.ndarray) -> np.ndarray:
    """Of pairs (row by row) the unbiased estimates of their cosines, from a code and the other turned vector."""
    d = turned.shape[1]
    signs = np.unpackbits(code.view(np.uint8), axis=1, count=d).astype(np.float64) * 2 - 1
    return np.einsum("ij,ij->i", signs, turned) / np.sqrt(d) / np.clip(factor, 1e-6, 1)


def least_estimates(factor: np.ndarray, d: int, threshold: float, epsilon: float) -> np.ndarray:
    """Estimates below which a pair is not at the threshold at that confidence."""
    f = np.clip(factor, 1e-6, 1)
    return threshold - np.sqrt((1 - f * f) * max(0.0, 1 - threshold * threshold) / max(d - 1, 1)) / f * epsilon


def linked(x: np.ndarray, y: np.ndarray | None, code: np.ndarray, factor: np.ndarray, other_code: np.ndarray | None, threshold: float, epsilon: float = EPSILON) -> tuple[np.ndarray, np.ndarray, dict[str, int]]:
    """Positions of linked pairs between two tiles or within one (y is None), and how many pairs each test left."""
    other, codes = (x, code) if y is None else (y, other_code)
    turned, d = turn(other), x.shape[1]
    norm, norm2 = np.linalg.norm(x, axis=1), np.linalg.norm(other, axis=1)
    most, least = most_bits(d, threshold, epsilon), least_estimates(factor, d, threshold, epsilon)
    found, left = [(np.zeros(0, np.int64), np.zeros(0, np.int64))], {"pairs": 0, "bits": 0, "estimate": 0, "exact": 0}
    for i in range(0, len(x), ROWS):
        differ = np.zeros((len(code[i : i + ROWS]), len(codes)), np.uint16)
        for word in range(code.shape[1]):
            differ += np.bitwise_count(code[i : i + ROWS, word, None] ^ codes[None, :, word])
        a, b = np.nonzero(differ <= most)
        a = a + i
        if y is None:
            a, b = a[a < b], b[a < b]
            left["pairs"] += sum(max(0, len(x) - 1 - k) for k in range(i, min(i + ROWS, len(x))))
        else:
            left["pairs"] += differ.size
        left["bits"] += len(a)
        for k in range(0, len(a), PAIRS):
            s, t = a[k : k + PAIRS], b[k : k + PAIRS]
            f = np.clip(factor[s], 1e-6, 1)
            estimate = estimates(code[s], factor[s], turned[t])
            inner = np.clip(estimate * f, -1, 1)
            reach = f * inner + np.sqrt((1 - f * f) * (1 - inner * inner))
            near = (estimate >= least[s] - 1e-9) & (reach >= threshold - 1e-9)
            s, t = s[near], t[near]
            left["estimate"] += len(s)
            close = np.einsum("ij,ij->i", x[s], other[t]) / (norm[s] * norm2[t]) >= threshold
            left["exact"] += int(close.sum())
            found.append((s[close], t[close]))
    return np.concatenate([s for s, _ in found]), np.concatenate([t for _, t in found]), left


def _encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        d = np.asarray(batch.column("dim"))
        for dim in np.unique(d):
            b = batch.take(pa.array(np.flatnonzero(d == dim)))
            x = np.asarray(b.column("vec").flatten()).reshape(-1, dim)
            code, factor = quantise(x)
            raw = [r.tobytes() for r in x.astype(np.float64)]
            yield pa.RecordBatch.from_arrays([b.column("label"), b.column("dim"), b.column("rep"), b.column("weight"), pa.array(raw, pa.binary()), pa.array([r.tobytes() for r in code], pa.binary()), pa.array(factor)], ["label", "dim", "rep", "weight", "vec", "code", "factor"])


def _compare(threshold: float, epsilon: float):
    def task(t: pa.Table) -> pa.Table:
        t = t.combine_chunks().sort_by([("side", "ascending"), ("rep", "ascending")])
        col = lambda c: np.asarray(t.column(c).combine_chunks())
        side, rep, weight, factor = col("side"), col("rep"), col("weight"), col("factor")
        many = lambda c, kind: np.frombuffer(b"".join(t.column(c).to_pylist()), kind).reshape(len(rep), -1)
        x, code = many("vec", np.float64), many("code", np.uint64)
        middle = int(np.searchsorted(side, 1))
        if middle < len(rep):
            a, b, _ = linked(x[:middle], x[middle:], code[:middle], factor[:middle], code[middle:], threshold, epsilon)
            b = b + middle
        else:
            a, b, _ = linked(x, None, code, factor, None, threshold, epsilon)
        n = np.bincount(a, weight[b], len(rep)).astype(np.int64) + np.bincount(b, weight[a], len(rep)).astype(np.int64)
        order = np.argsort(rep, kind="stable")
        place = np.empty(len(rep), np.int64)
        place[order] = np.arange(len(rep))
        root = roots(len(rep), place[a], place[b])
        keep = np.flatnonzero(n)
        return pa.table({"rep": pa.array(rep[keep], pa.int64()), "root": pa.array(rep[order[root[place[keep]]]], pa.int64()), "n": pa.array(n[keep], pa.int64())})

    return task


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", threshold: float = THRESHOLD, tile: int = TILE, epsilon: float = EPSILON) -> DataFrame:
    """(id, n_links, component_id, kept) of every row. A row with a null id has no links and is kept under a null component."""
    v = F.col("vec")
    sound = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf")))) & F.exists(v, lambda e: e != 0) & F.col("label").isNotNull() & F.col("id").isNotNull()
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).alias("label"), F.col(vector_col).cast("array<double>").alias("vec"))
    rows = rows.withColumn("sound", F.coalesce(sound, F.lit(False)))
    # 128 bits stand for a vector where it is only compared with equal ones
    keyed = rows.where("sound").select("id", "label", "vec", F.size("vec").alias("dim"), F.xxhash64("vec").alias("h1"), F.xxhash64(F.lit(7), "vec").alias("h2"))
    grouped = keyed.groupBy("label", "dim", "h1", "h2").agg(F.min("id").alias("rep"), F.count("*").alias("weight"), F.first("vec").alias("vec"))
    members = keyed.groupBy("label", "dim", "h1", "h2").agg(F.min("id").alias("rep"), F.count("*").alias("weight"))
    label = dict(rows.dtypes)["label"]
    codes = grouped.select("label", "dim", "rep", "weight", "vec").mapInArrow(_encode, f"label {label}, dim int, rep long, weight long, vec binary, code binary, factor double")
    # the number of tiles of a group; as cheap as counting, and it is joined back split where a label is hot
    tiles = cut(keyed.groupBy("label", "dim").agg(F.ceil(F.count_distinct("h1") / F.lit(tile)).cast("int").alias("tiles")))
    work = F.col("tiles").cast("long") * (F.col("tiles") + 1) / 2
    todo = tiles.agg(F.coalesce(F.sum(work), F.lit(0)).cast("long")).first()[0]
    tiled = codes.join(tiles, ["label", "dim"]).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("tiles")).cast("int"))
    pairs = tiled.select("*", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("other"))
    tasks = pairs.select("label", "dim", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") > F.col("other")).cast("int").alias("side"), "rep", "weight", "vec", "code", "factor")
    # a task's rows are few and its work is their square, so tasks are dealt by their number, which bytes would pack together
    dealt = tasks.repartition(max(1, min(todo, TASKS)), "label", "dim", "i", "j")
    found = cut(dealt.groupBy("label", "dim", "i", "j").applyInArrow(_compare(threshold, epsilon), "rep long, root long, n long"))
    parts = components(found.select(F.col("rep").alias("a"), F.col("root").alias("b")))
    of_rep = found.groupBy("rep").agg(F.sum("n").alias("n")).join(parts.withColumnRenamed("node", "rep"), "rep", "left")
    of_key = members.join(of_rep, "rep", "left").select("label", "dim", "h1", "h2", (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    same = rows.withColumn("dim", F.size("vec")).withColumn("h1", F.when(F.col("sound"), F.xxhash64("vec"))).withColumn("h2", F.xxhash64(F.lit(7), "vec")).drop("vec")
    out = same.join(of_key, ["label", "dim", "h1", "h2"], "left")
    component = F.coalesce("component_id", "id")
    return out.select(F.col("id").alias(id_col), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("id") == component, F.lit(True)).alias("kept"))
