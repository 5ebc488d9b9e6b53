"""SimHash fingerprints, and all pairs of them within a radius, compared tile by tile.

Fingerprints of a text: A-Z in lower case, words between ASCII white space, shingles of `width` words, XXH64
with seed 42 of each shingle, and a bit for each bit set in over half the hashes. A text of fewer words is one
shingle; one without words, null or empty, has fingerprint zero and links as any other.

Links: equal fingerprints are one node. Two that differ in at most r bits agree in at least one of r + 1
segments, so the tiles are made of fingerprints that share a segment. A bucket above `tile` fingerprints is put in
order of population counts and cut into tiles, each a range of them; a pair of tiles is dealt to a task only if
their ranges are within the radius of each other, so pairs whose counts differ beyond it are skipped before
anything moves. Within a task rows lie in the same order and pieces further apart are skipped likewise; the rest
are compared whole by exclusive-or and bit counts. A task returns one row per linked fingerprint (its least
reachable one in the task), never the pairs.

Repeated ids are rows of their own and all get the same component; a null id gets its component as any row does.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxsum.llm.components import components
from boxsum.llm.forest import roots
from boxsum.llm.shared import blocks, cut

RADIUS, WIDTH, SEED = 3, 3, 42
#: Fingerprints of a bucket that one tile holds, and rows of a tile that are compared at once.
TILE, PIECE = 8192, 512
LANES = np.uint64(0x0101010101010101)


def hashes(text: str | None, width: int = WIDTH, seed: int = SEED) -> list[int]:
    """XXH64 of each shingle of a text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return []
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= width:
        return [digest(joined, seed)]
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(sizes)
    first, last = (ends - sizes)[: 1 - width or None].tolist(), (ends - 1)[width - 1 :].tolist()
    return [digest(joined[a:b], seed) for a, b in zip(first, last, strict=True)]


def majority(flat: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """For runs of hashes, `counts` of them each, the bits that are set in over half; 0 for an empty run.

    Bits are counted in eight byte lanes at once, 255 hashes at most a sum.
    """
    out = np.zeros(len(counts), np.uint64)
    if not len(flat):
        return out
    owner, starts, parts = np.flatnonzero(counts), np.cumsum(counts) - counts, -(-counts // 255)
    begins = np.repeat(starts, parts) + 255 * (np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts))
    part_of = np.searchsorted(begins, starts[owner])
    for bit in range(8):
        lanes = np.add.reduceat((flat >> np.uint64(bit)) & LANES, begins)
        for byte in range(8):
            ones = np.add.reduceat(((lanes >> np.uint64(8 * byte)) & np.uint64(255)).astype(np.int64), part_of)
            out[owner] |= (2 * ones > counts[owner]).astype(np.uint64) << np.uint64(8 * byte + bit)
    return out


def flattened(texts: list[str | None], width: int) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all texts' shingles, text by text, and how many each has."""
    each = [hashes(t, width) for t in texts]
    counts = np.fromiter(map(len, each), np.int64, len(each))
    return np.fromiter((h for hs in each for h in hs), np.uint64, int(counts.sum())), counts


def fingerprints(texts: list[str | None], width: int = WIDTH) -> np.ndarray:
    """Unsigned 64-bit fingerprints."""
    return majority(*flattened(texts, width))


def fingerprint_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """(id, fp long): the fingerprint's bits as a signed number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(fingerprints(b.column("text").to_pylist(), width).view(np.int64))], ["id", "fp"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, fp long")


def population(fp: np.ndarray) -> np.ndarray:
    counts = np.bitwise_count(fp)
    return counts if fp.ndim == 1 else counts.sum(axis=1, dtype=np.int64)


def near(left: np.ndarray, right: np.ndarray | None, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions of all pairs within the radius between two tiles, or within one (right is None).

    Both are sorted by population count; pieces whose counts are further apart than the radius are skipped.
    """
    other = left if right is None else right
    pops, pops2 = population(left), population(other)
    found_a, found_b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for i in range(0, len(left), PIECE):
        low, high = int(pops[i]) - radius, int(pops[min(i + PIECE, len(left)) - 1]) + radius
        begin, end = np.searchsorted(pops2, low, "left"), np.searchsorted(pops2, high, "right")
        begin = max(int(begin), i) if right is None else int(begin)
        for j in range(begin, int(end), PIECE):
            x, y = left[i : i + PIECE], other[j : min(j + PIECE, end)]
            if left.ndim == 1:
                differ = np.bitwise_count(x[:, None] ^ y[None, :])
            else:
                differ = np.zeros((len(x), len(y)), np.uint16)
                for word in range(left.shape[1]):
                    differ += np.bitwise_count(x[:, word, None] ^ y[None, :, word])
            a, b = np.nonzero(differ <= radius)
            a, b = a + i, b + j
            if right is None:
                a, b = a[a < b], b[a < b]
            found_a.append(a)
            found_b.append(b)
    return np.concatenate(found_a), np.concatenate(found_b)


def _compare(words: int, pairs_of: Callable, extra: int = 0):
    """Tasks over rows sorted by (bucket, tiles), one tile pair after another.

    A row's payload is its fingerprint (a long, or `words` of them in binary) and `extra` whole numbers; pairs_of
    gives the positions of linked pairs between two lists of such columns, or within one.
    """

    def task(side: np.ndarray, rep: np.ndarray, columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        order = np.lexsort((population(columns[0]), side))
        side, rep, columns = side[order], rep[order], [c[order] for c in columns]
        middle = int(np.searchsorted(side, 1))
        if 0 < middle < len(rep):
            a, b = pairs_of([c[:middle] for c in columns], [c[middle:] for c in columns])
            b = b + middle
        else:
            a, b = pairs_of(columns, None)
        if not len(a):
            return rep[:0], rep[:0]
        by_rep = np.argsort(rep, kind="stable")  # the least position is then the least representative
        place = np.empty(len(rep), np.int64)
        place[by_rep] = np.arange(len(rep))
        root = roots(len(rep), place[a], place[b])
        moved = np.flatnonzero(root != np.arange(len(rep)))
        return rep[by_rep[moved]], rep[by_rep[root[moved]]]

    def columns_of(b: pa.RecordBatch) -> list[np.ndarray]:
        plain = [b.column(k).to_numpy(zero_copy_only=False) for k in range(5)]
        if words == 1:
            prints = b.column(5).to_numpy(zero_copy_only=False).view(np.uint64)
        else:
            prints = np.frombuffer(b"".join(b.column(5).to_pylist()), np.uint64).reshape(-1, words)
        return [*plain, prints, *(b.column(6 + k).to_numpy(zero_copy_only=False) for k in range(extra))]

    def finish(cols: list[np.ndarray]) -> pa.RecordBatch:
        bucket, i, j, side, rep, *payload = cols
        change = np.flatnonzero((np.diff(bucket) != 0) | (np.diff(i) != 0) | (np.diff(j) != 0)) + 1
        starts, ends = np.concatenate([[0], change]), np.concatenate([change, [len(bucket)]])
        several = ends - starts > 1
        out = [task(side[s:e], rep[s:e], [c[s:e] for c in payload]) for s, e in zip(starts[several].tolist(), ends[several].tolist(), strict=True)]
        a = np.concatenate([x for x, _ in out]) if out else np.zeros(0, np.int64)
        b = np.concatenate([x for _, x in out]) if out else np.zeros(0, np.int64)
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[np.ndarray] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = columns_of(batch)
            if kept:
                cols = [np.concatenate(x) for x in zip(kept, cols, strict=True)]
            last = np.flatnonzero((cols[0] != cols[0][-1]) | (cols[1] != cols[1][-1]) | (cols[2] != cols[2][-1]))
            at = int(last[-1]) + 1 if len(last) else 0
            kept = [x[at:] for x in cols]  # the last task may go on in the next batch; it holds two tiles at most
            if at:
                yield finish([x[:at] for x in cols])
        if kept and len(kept[0]):
            yield finish(kept)

    return run


def links(nodes: DataFrame, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """(a, b): links that join all `nodes` (fp, rep) within the radius, as a forest per tile task; rep is a whole number."""
    segments = radius + 1
    edges = [round(64 * k / segments) for k in range(segments + 1)]
    # a segment's value, with the segment's number on top
    keys = [F.shiftrightunsigned("fp", a).bitwiseAND(F.lit((1 << (b - a)) - 1)).bitwiseOR(F.lit(k << 60)) if b - a < 60 else F.xxhash64("fp") for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False))]
    dealt = nodes.select("fp", "rep", F.bit_count("fp").alias("pop"), F.explode(F.array(*keys)).alias("bucket"))
    found = dealt.join(tiles_of(dealt, tile), "bucket")
    return _tasks(found, radius, ["fp"]).mapInArrow(_compare(1, lambda a, b: near(a[0], None if b is None else b[0], radius)), "a long, b long")


def tiles_of(dealt: DataFrame, tile: int) -> DataFrame:
    """(bucket, ranges, tiles) of the buckets with several rows of (bucket, pop).

    Rows in order of population count fill the tiles one after another; ranges (one entry for each count that
    occurs) has the tiles `first`..`last` that rows of a count lie in. Tiles hold an eighth of their bucket, but
    neither more than `tile` rows nor less than an eighth of that: a bucket of some size is several tasks.
    """
    counts = dealt.groupBy("bucket", "pop").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("bucket").orderBy("pop")) - F.col("n")
    eighth = F.ceil(F.sum("n").over(Window.partitionBy("bucket")) / 8)
    counts = counts.select("bucket", "pop", "n", before.alias("before"), F.least(F.lit(tile), F.greatest(F.lit(-(-tile // 8)), eighth)).alias("tile"))
    placed = counts.select("bucket", "pop", "n", F.floor(F.col("before") / F.col("tile")).cast("int").alias("first"), F.floor((F.col("before") + F.col("n") - 1) / F.col("tile")).cast("int").alias("last"))
    return cut(placed.groupBy("bucket").agg(F.sum("n").alias("n"), F.max("last").alias("most"), F.collect_list(F.struct("pop", "first", "last")).alias("ranges")).where("n > 1").select("bucket", "ranges", (F.col("most") + 1).alias("tiles")))


def _tasks(tiled: DataFrame, radius: int, payload: list[str]) -> DataFrame:
    """(bucket, i, j, side, rep, payload) of rows with their bucket's ranges, each pair of tiles in one partition, in order."""
    mine = F.filter("ranges", lambda x: x["pop"] == F.col("pop"))[0]
    tiled = tiled.withColumn("own", mine["first"] + F.pmod(F.xxhash64("rep", "bucket"), mine["last"] - mine["first"] + 1).cast("int"))
    # the counts that a row's tile holds, and the tiles of all counts within the radius of those
    held = F.transform(F.filter("ranges", lambda x: (x["first"] <= F.col("own")) & (F.col("own") <= x["last"])), lambda x: x["pop"])
    tiled = tiled.withColumn("low", F.array_min(held) - radius).withColumn("high", F.array_max(held) + radius)
    close = F.filter("ranges", lambda x: (x["pop"] >= F.col("low")) & (x["pop"] <= F.col("high")))
    tiled = tiled.withColumn("from", F.array_min(F.transform(close, lambda x: x["first"]))).withColumn("to", F.array_max(F.transform(close, lambda x: x["last"])))
    pairs = tiled.select("bucket", "own", "rep", *payload, F.explode(F.sequence("from", "to")).alias("other"))
    tasks = pairs.select("bucket", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") > F.col("other")).cast("int").alias("side"), "rep", *payload)
    # rows are few bytes and much work, so bytes don't tell how many tasks there should be
    spark = tiled.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    return tasks.repartition(parts, "bucket", "i", "j").sortWithinPartitions("bucket", "i", "j")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, radius: int = RADIUS) -> DataFrame:
    """(id, fp, component_id): component_id is the least id reachable over links; equal fingerprints are linked.

    The id must be a whole number. A group whose ids are all null has a null component.
    """
    fps = cut(fingerprint_table(docs, id_col, text_col, width).withColumn("id", F.col("id").cast("long")))
    nodes = fps.groupBy("fp").agg(F.min("id").alias("rep"))
    found = components(links(nodes.where("rep is not null"), radius)).select(F.col("node").alias("rep"), "component")
    of_fp = nodes.join(found, "rep", "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return fps.join(of_fp, "fp").select(F.col("id").alias(id_col), "fp", "component_id")


# -- similarity of shingle sets -----------------------------------------------------------------------------

#: Words of 64 bits of a wide fingerprint, bands and minima a band of its bucket keys, and rows of a tile.
WIDE, BANDS, BAND, WIDE_TILE = 16, 12, 4, 2048
SIMILARITY, SHINGLE, SLACK = 0.8, 5, 1.0
MIX_A, MIX_B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def wide_radius(similarity: float = SIMILARITY, words: int = WIDE, slack: float = SLACK) -> int:
    """Bits by which sets of that Jaccard similarity differ at most: the mean and `slack` standard deviations.

    The cosine of two sets of one size with similarity j is 2 j / (1 + j); a bit differs with probability angle / pi.
    """
    p = np.arccos(2 * similarity / (1 + similarity)) / np.pi
    return int(64 * words * p + slack * np.sqrt(64 * words * p * (1 - p)))


def sketch(texts: list[str | None], width: int = SHINGLE, words: int = WIDE, bands: int = BANDS, band: int = BAND) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each text's set of shingles the size, the wide fingerprint, and the bucket keys.

    A bucket key stands for `band` minima of the hashes; a set has one minimum in each of bands * band equal ranges of
    hashes, an empty range that of the next one around.
    """
    flat, counts = flattened(texts, width)
    owner = np.repeat(np.arange(len(texts)), counts)
    order = np.lexsort((flat, owner))
    flat, owner = flat[order], owner[order]
    new = np.ones(len(flat), bool)
    new[1:] = (flat[1:] != flat[:-1]) | (owner[1:] != owner[:-1])
    flat, owner = flat[new], owner[new]
    sizes = np.bincount(owner, minlength=len(texts))
    wide, salts = np.zeros((len(texts), words), np.uint64), np.arange(1, words + 1, dtype=np.uint64) * MIX_B
    for k in range(words):
        mixed = (flat ^ salts[k]) * MIX_A
        mixed ^= mixed >> np.uint64(32)
        mixed *= MIX_B
        mixed ^= mixed >> np.uint64(29)
        wide[:, k] = majority(mixed, sizes)
    ranges = bands * band
    place = owner * ranges + (((flat >> np.uint64(32)) * np.uint64(ranges)) >> np.uint64(32)).astype(np.int64)
    first = np.ones(len(flat), bool)
    first[1:] = place[1:] != place[:-1]  # hashes are in order, so the first of a range is its least
    least, filled = np.zeros(len(texts) * ranges, np.uint64), np.zeros(len(texts) * ranges, bool)
    least[place[first]], filled[place[first]] = flat[first], True
    least, filled = least.reshape(-1, ranges), filled.reshape(-1, ranges)
    some = sizes > 0
    while not filled[some].all():
        take = ~filled & np.roll(filled, -1, axis=1)
        least = np.where(take, np.roll(least, -1, axis=1) * MIX_A + MIX_B, least)
        filled = filled | take
    keys = np.zeros((len(texts), bands), np.uint64)
    for k in range(band):
        keys = (keys ^ least[:, k::band][:, :bands]) * MIX_A
        keys ^= keys >> np.uint64(31)
    return sizes, wide, (keys + np.arange(bands, dtype=np.uint64) * MIX_B).view(np.int64)


def sketch_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE) -> DataFrame:
    """(id, size, pop, fp binary, buckets array<long>) of every row's set of shingles; pop counts the bits of fp."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            sizes, wide, keys = sketch(b.column("text").to_pylist(), width)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(sizes, pa.int64()), pa.array(population(wide), pa.int64()), pa.array([x.tobytes() for x in wide], pa.binary()), pa.array(list(keys), pa.list_(pa.int64()))], ["id", "size", "pop", "fp", "buckets"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "id long, size long, pop long, fp binary, buckets array<long>")


def similar(left: list[np.ndarray], right: list[np.ndarray] | None, radius: int, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs within the radius whose sets' sizes allow the similarity."""
    a, b = near(left[0], None if right is None else right[0], radius)
    x, y = left[1][a], (left if right is None else right)[1][b]
    fit = np.minimum(x, y) >= similarity * np.maximum(x, y)
    return a[fit], b[fit]


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE, similarity: float = SIMILARITY, tile: int = WIDE_TILE) -> DataFrame:
    """(id, component_id): the least id reachable over texts whose sets of shingles are that similar or more.

    Wide fingerprints tell the similarity; those that share a bucket are compared, tile by tile as above, and texts
    of equal sets are one node. Texts without a word have the empty set and are one group. `wide_radius` says how
    sharp the limit is, the buckets find pairs at the limit with a probability of 1 - (1 - similarity**BAND)**BANDS.
    """
    rows = cut(sketch_table(docs, id_col, text_col, width))
    nodes = cut(rows.groupBy("fp", "size").agg(F.min("id").alias("rep"), F.min("pop").alias("pop"), F.min("buckets").alias("buckets")))
    known, radius = nodes.where("rep is not null and size > 0"), wide_radius(similarity)
    light = known.select("rep", "size", "pop", F.explode(F.array_distinct("buckets")).alias("bucket"))
    shared = light.join(tiles_of(light, tile), "bucket")  # rows alone in a bucket go before fingerprints move
    tasks = _tasks(shared.join(known.select("rep", "fp"), "rep"), radius, ["fp", "size"])
    found = tasks.mapInArrow(_compare(WIDE, lambda a, b: similar(a, b, radius, similarity), 1), "a long, b long")
    parts = components(found).select(F.col("node").alias("rep"), "component")
    of_node = nodes.join(parts, "rep", "left").select("fp", "size", F.coalesce("component", "rep").alias("component_id"))
    return rows.select("id", "fp", "size").join(of_node, ["fp", "size"]).select(F.col("id").alias(id_col), "component_id")


def _least_of(docs: DataFrame, groups: DataFrame, id_col: str) -> DataFrame:
    gone = groups.where(F.col(id_col) != F.col("component_id")).select(F.col(id_col).cast("long").alias("of")).distinct().alias("gone")
    return docs.alias("docs").join(gone, F.col(f"docs.{id_col}").cast("long") == F.col("gone.of"), "left_anti")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, radius: int = RADIUS) -> DataFrame:
    """The rows of docs without those whose id is not the least of its group by fingerprints; rows without an id stay.

    Rows that repeat the id that stays all stay: they are the same document.
    """
    return _least_of(docs, near_duplicates(docs.select(id_col, text_col), id_col, text_col, width, radius), id_col)


def drop_similar(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """The same by similarity of shingle sets."""
    return _least_of(docs, similar_groups(docs.select(id_col, text_col), id_col, text_col, width, similarity), id_col)
