"""Packing of tokenised documents into sequences, by cutting stock over the histogram of their tails.

A document's ids end with one separator. Its full stretches of `capacity` ids are sequences of their own; the
rest, its tail, is an item whose size is rounded up to a class of `grain` ids. The histogram of classes, as many
numbers as there are classes, goes to the driver and through column generation; documents of a class are ranked
by bucket and id, and ranks are dealt to the slots of patterns by arithmetic. Offsets in a sequence are sums of
true lengths, so there is no gap; padding is what the rounding and the last bins leave at the end.

Added tokens (content to id) are found in the raw text first and are one id each, as the tokenizers library has
it; what lies between them goes to the ranks piece by piece. Without them their letters are ordinary text.

No document is cut but into its full stretches and its tail. Null and empty texts are their separator alone. Each
row is a document, also one that repeats another's id (pieces then have that id more than once).
"""

from __future__ import annotations

import base64
import json
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from boxsum.llm.cutting_stock import plan
from boxsum.llm.shared import blocks, cut

CAPACITY, GRAIN, SEPARATOR = 1024, 8, 0


def added_tokens(path: str) -> dict[str, int]:
    """Content and id of the added tokens of a tokenizer's JSON."""
    with open(path, encoding="utf-8") as f:
        tokens = json.load(f)["added_tokens"]
    if odd := [t["content"] for t in tokens if t["lstrip"] or t["rstrip"] or t["single_word"]]:
        raise ValueError(f"added tokens that take or need what stands beside them are not known here: {odd}")
    return {t["content"]: t["id"] for t in tokens}


@lru_cache(maxsize=4)
def tokenizer(path: str, pattern: str, added: tuple[tuple[str, int], ...] = ()) -> tiktoken.Encoding:
    with open(path, "rb") as f:
        ranks = {base64.b64decode(t): int(r) for t, r in map(bytes.split, filter(None, f.read().splitlines()))}
    return tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens=dict(added))


def tokenise(docs: DataFrame, ranks: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, separator: int = SEPARATOR, with_ids: bool = False, added: dict[str, int] | None = None) -> DataFrame:
    """(row, id, tokens, crcs[, ids]): of each row its token count with the separator, and a checksum of each stretch."""

    special = tuple(sorted((added or {}).items()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = tokenizer(ranks, pattern, special)
        end = np.array([separator], "<u4").tobytes()
        for b in blocks(batches, "text"):
            raw = [np.asarray(encoding.encode_to_numpy(t or "", allowed_special="all"), "<u4").tobytes() + end for t in b.column("text").to_pylist()]
            crcs = [[zlib.crc32(r[i : i + 4 * capacity]) for i in range(0, len(r), 4 * capacity)] for r in raw]
            cols = [b.column("row"), b.column("id"), pa.array([len(r) // 4 for r in raw], pa.int64()), pa.array(crcs, pa.list_(pa.int64()))]
            if with_ids:
                cols.append(pa.array([np.frombuffer(r, "<u4").astype(np.int32) for r in raw], pa.list_(pa.int32())))
            yield pa.RecordBatch.from_arrays(cols, ["row", "id", "tokens", "crcs", "ids"][: len(cols)])

    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, f"row long, id {dict(rows.dtypes)['id']}, tokens long, crcs array<long>" + (", ids array<int>" if with_ids else ""))


def pack(docs: DataFrame, ranks: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, grain: int = GRAIN, separator: int = SEPARATOR, with_ids: bool = False, added: dict[str, int] | None = None) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids]): a row for each piece."""
    spark = docs.sparkSession
    docs_ids = cut(tokenise(docs, ranks, pattern, id_col, text_col, capacity, separator, with_ids, added))
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    tail = F.pmod(F.col("tokens"), F.lit(capacity))
    rows = docs_ids.select("*", F.floor(F.col("tokens") / capacity).alias("full"), tail.alias("tail"), F.ceil(tail / grain).cast("int").alias("class"), F.pmod(F.xxhash64("row"), F.lit(buckets)).alias("bucket"))

    # ranks: rows before a row in its class, and full stretches before its own, bucket by bucket
    sums = rows.groupBy("class", "bucket").agg(F.count("*").alias("n"), F.sum("full").alias("f"))
    in_class = Window.partitionBy("class").orderBy("bucket")
    classes_before = F.sum("all").over(Window.orderBy("class")) - F.col("all")  # capacity / grain + 1 rows at most
    of_classes = sums.groupBy("class").agg(F.sum("f").alias("all")).select("class", classes_before.alias("f_classes"))
    sums = sums.select("class", "bucket", (F.sum("n").over(in_class) - F.col("n")).alias("n_before"), (F.sum("f").over(in_class) - F.col("f")).alias("f_here")).join(F.broadcast(of_classes), "class")
    sums = sums.select("class", "bucket", "n_before", (F.col("f_here") + F.col("f_classes")).alias("f_before"))
    in_bucket = Window.partitionBy("class", "bucket").orderBy("row")
    light = rows.select("row", "id", "tokens", "full", "tail", "class", "bucket")
    ranked = light.select("*", (F.row_number().over(in_bucket) - 1).alias("n_here"), (F.sum("full").over(in_bucket) - F.col("full")).alias("f_here")).join(sums, ["class", "bucket"])
    ranked = ranked.select("row", "tail", "class", (F.col("n_here") + F.col("n_before")).alias("rank"), (F.col("f_here") + F.col("f_before")).alias("first_full"))

    histogram = {r["class"]: r["n"] for r in rows.where("class > 0").groupBy("class").agg(F.count("*").alias("n")).collect()}
    classes = sorted(histogram)
    patterns = plan(np.array(classes), np.array([histogram[c] for c in classes]), capacity // grain)
    slots, taken, sequences = [], dict.fromkeys(classes, 0), 0
    for often, pattern_counts in patterns:
        for c, k in zip(classes, pattern_counts.tolist(), strict=True):
            if k and taken[c] < histogram[c]:
                slots.append((c, taken[c], taken[c] + often * k, k, sequences))
                taken[c] += often * k
        sequences += often
    # each class's slots as an array, one a pattern that holds the class; a row is compared with those of its class
    of_class: dict[int, list] = {}
    for c, low, high, k, first in slots:
        of_class.setdefault(c, []).append((low, high, k, first))
    plan_rows = spark.createDataFrame([(c, [tuple(map(int, s)) for s in of]) for c, of in of_class.items()], "class int, slots array<struct<low: long, high: long, k: long, first: long>>")
    hit = F.element_at(F.filter("slots", lambda s: (s["low"] <= F.col("rank")) & (F.col("rank") < s["high"])), 1)
    placed = ranked.join(F.broadcast(plan_rows), "class", "left").withColumn("hit", F.when(F.col("class") > 0, hit))
    placed = placed.select("row", "first_full", "tail", "rank", F.expr("hit.first + (rank - hit.low) div hit.k").alias("sequence"), F.col("class"))
    # offsets: true lengths of what stands before in the sequence, the larger classes first
    in_sequence = Window.partitionBy("sequence").orderBy(F.desc("class"), "rank")
    tails = placed.where("tail > 0").select("row", "sequence", (F.sum("tail").over(in_sequence) - F.col("tail")).alias("tail_offset"))
    at = placed.select("row", "first_full").join(tails, "row", "left")
    pieces = rows.join(at, "row").select("*", F.posexplode("crcs").alias("k", "ids_crc32"))
    whole = F.col("k") < F.col("full")
    return pieces.select(
        F.col("id").alias(id_col), (F.col("k").cast("long") * capacity).alias("start"), F.when(whole, F.lit(capacity)).otherwise(F.col("tail")).cast("long").alias("length"), "ids_crc32", F.col("tokens").alias("doc_tokens"),
        F.when(whole, F.lit(sequences) + F.col("first_full") + F.col("k")).otherwise(F.col("sequence")).cast("long").alias("sequence_id"), F.when(whole, F.lit(0)).otherwise(F.col("tail_offset")).cast("long").alias("offset"),
        *([F.slice("ids", F.col("k") * capacity + 1, capacity).alias("ids")] if with_ids else []),
    )
