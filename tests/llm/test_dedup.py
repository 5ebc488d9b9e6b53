import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F
from pyspark.sql import types as T

from boxsum.llm import embedding_dedup, simhash
from boxsum.llm import components as stars
from boxsum.llm.components import components


def least_reachable(ids, links):
    parent = {i: i for i in ids}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_components_of_a_long_chain_and_a_star(spark):
    links = [(i, i + 1) for i in range(1, 300)] + [(1000, i) for i in range(1001, 1100)] + [(5, 5), (None, 3)]
    got = dict(components(spark.createDataFrame(links, "a long, b long")).collect())
    want = least_reachable({i for x in links if None not in x for i in x}, [x for x in links if None not in x])
    assert got == want
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_no_task_gets_all_links_of_a_hub(spark):
    n = 100_000
    hub = spark.range(n).select((F.col("id") + 1).alias("a"), F.lit(0).cast("long").alias("b"))
    held = spark.conf.get("spark.sql.shuffle.partitions"), spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.shuffle.partitions", "16")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        both = hub.unionByName(hub.select(F.col("b").alias("a"), F.col("a").alias("b"))).repartition(16)
        with_least = stars._with_least(both, 2 * n // stars.HEAVY_NODES)
        tasks = [r["count"] for r in with_least.groupBy(F.spark_partition_id()).count().collect()]
        assert sum(tasks) == 2 * n and max(tasks) < 2 * n / 8
        assert "Broadcast" in with_least._jdf.queryExecution().executedPlan().toString()
        got = components(hub.unionByName(spark.createDataFrame([(n + 5, n + 7), (n, n + 1)], "a long, b long")))
        assert {r["component"]: r["count"] for r in got.groupBy("component").count().collect()} == {0: n + 2, n + 5: 2}
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held[0])
        spark.conf.set("spark.sql.adaptive.enabled", held[1])


def brute_fingerprint(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    hashes = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 3]), 42) for i in range(max(1, len(words) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_simhash(rows):
    fps = [(i, brute_fingerprint(t)) for i, t in rows]
    links = [(a, b) for a, x in fps for b, y in fps if a < b and (x ^ y).bit_count() <= 3]
    root = least_reachable([i for i, _ in fps], links)
    return {(i, f"{fp:016x}", root[i]) for i, fp in fps}


@pytest.mark.parametrize("tile", [4, 8192])
def test_simhash_against_brute_force(spark, tile, monkeypatch):
    r = random.Random(3)
    words = ["Ab", "cD", "e", "É", "漢", "g"]
    rows = [(0, None), (1, ""), (2, " \t\n"), (3, "ONE"), (4, "one"), (5, "a b"), (6, "x y z\x0bq r")]
    base = " ".join(r.choice(words) for _ in range(900))
    for i in range(7, 140):
        t = base.split()
        for _ in range(r.randint(0, 6) * (i % 2)):
            t[r.randrange(len(t))] = r.choice(words)
        rows.append((i, " ".join(t) if i % 3 else " ".join(r.choice(words) + str(r.randint(0, 9)) for _ in range(r.randint(1, 30)))))
    monkeypatch.setattr(simhash, "PIECE", 3)
    monkeypatch.setattr(simhash.links, "__defaults__", (3, tile))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {(x.doc_id, f"{x.fp & (1 << 64) - 1:016x}", x.component_id) for x in simhash.near_duplicates(docs).collect()}
    want = brute_simhash(rows)
    assert got == want and len({c for *_, c in want}) < len(rows) - 5
    kept = {x.doc_id for x in simhash.drop_near_duplicates(docs).collect()}
    assert kept == {i for i, _, c in want if i == c}


def test_fingerprints_of_more_hashes_than_a_lane_counts():
    text = " ".join(str(i % 7) for i in range(3000))
    assert int(simhash.fingerprints([text, None, "a"])[0]) == brute_fingerprint(text)


def test_near_finds_every_pair_within_the_radius():
    r = np.random.default_rng(0)
    fps = np.concatenate([x ^ np.uint64(m) for x in [r.integers(0, 1 << 63, 300, np.uint64)] for m in (0, 1, 6, 0x1111)])
    fps = np.unique(fps)
    fps = fps[np.argsort(np.bitwise_count(fps), kind="stable")]
    a, b = simhash.near(fps, None, 3)
    want = {(i, j) for i in range(len(fps)) for j in range(i + 1, len(fps)) if int(fps[i] ^ fps[j]).bit_count() <= 3}
    assert set(zip(a.tolist(), b.tolist(), strict=True)) == want


def test_simhash_of_empty_table_and_extra_columns(spark):
    schema = "doc_id long, text string, fp string, bucket int, component_id int"
    assert simhash.near_duplicates(spark.createDataFrame([], schema)).count() == 0
    rows = [(1, "a b c d", "x", 1, 1), (2, "a b c d", None, 1, 1), (None, "a b c d", None, 1, 1), (2, "a b c d", None, 1, 1)]
    docs = spark.createDataFrame(rows, schema)
    assert {x.component_id for x in simhash.near_duplicates(docs).collect()} == {1}
    assert sorted(x.doc_id or -1 for x in simhash.drop_near_duplicates(docs).collect()) == [-1, 1]


def test_tiles_far_apart_in_population_are_not_dealt(spark):
    # one bucket of 3,000 rows with population counts 0..59: tiles of 100 rows hold two counts each
    dealt = spark.range(3000).select(F.lit(1).cast("long").alias("bucket"), F.expr("int(id % 60)").alias("pop"), F.col("id").alias("rep"), F.col("id").alias("fp"))
    tiled = dealt.join(simhash.tiles_of(dealt, 100), "bucket")
    tasks = simhash._tasks(tiled, 3, ["fp"])
    held = {(r.i, r.j) for r in tasks.select("i", "j").distinct().collect()}
    assert {i for i, _ in held} == set(range(30)) and all(j - i <= 2 for i, j in held) and len(held) < 90 < 30 * 31 / 2
    rows = tasks.groupBy("i", "j").agg(F.count("*").alias("n")).collect()
    assert max(r.n for r in rows) <= 400


def shingle_sets(texts, width=5):
    out = []
    for t in texts:
        w = (t or "").lower().split()
        out.append({tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set())
    return out


def test_similar_texts_are_grouped_and_others_left_alone(spark):
    r = random.Random(11)
    words = [f"w{i}" for i in range(500)]
    texts = [None, "", "  ", "one", "ONE", "a b c d e", "a b c d e f"]
    for _ in range(60):
        base = [r.choice(words) for _ in range(r.randint(20, 400))]
        texts.append(" ".join(base))
        for share in (0.0, 0.01, 0.02, 0.1, 0.5):
            copy = [r.choice(words) if r.random() < share else w for w in base]
            texts.append(" ".join(copy))
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in enumerate(texts)], "doc_id long, text string, fp string, size int").repartition(4)
    got = {x.doc_id: x.component_id for x in simhash.similar_groups(docs, tile=16).collect()}
    sets = shingle_sets(texts)
    score = lambda i, j: len(sets[i] & sets[j]) / len(sets[i] | sets[j]) if sets[i] | sets[j] else 1.0
    pairs = [(i, j, score(i, j)) for i in range(len(texts)) for j in range(i)]
    close = [(i, j) for i, j, s in pairs if s >= 0.8]
    assert sum(got[i] == got[j] for i, j in close) >= 0.97 * len(close) and len(close) > 150
    assert all(got[i] == got[j] for i, j, s in pairs if s >= 0.9)
    # nothing is linked but over pairs that are nearly as similar
    root = least_reachable(range(len(texts)), [(i, j) for i, j, s in pairs if s >= 0.68])
    assert all(root[i] == root[got[i]] for i in got)
    assert got[0] == got[1] == got[2] == 0 and got[3] == got[4] == 3 and got[5] != got[6]
    assert {x.doc_id for x in simhash.drop_similar(docs).collect()} == {i for i, c in {x.doc_id: x.component_id for x in simhash.similar_groups(docs).collect()}.items() if i == c}
    assert simhash.drop_similar(docs.limit(0)).count() == 0
    odd = docs.where("doc_id < 3").withColumn("of", F.lit(1)).withColumn("component_id", F.lit(2)).withColumn("__gone", F.lit(3))
    assert simhash.drop_similar(odd).columns == odd.columns and simhash.drop_near_duplicates(odd).count() == 1


def brute_links(rows):
    def sound(x, label):
        return label is not None and x is not None and all(c is not None and np.isfinite(c) for c in x) and any(x)

    good = [(i, np.array(x, float), k) for i, x, k in rows if sound(x, k)]
    return [(a, b) for a, x, k in good for b, y, m in good if a < b and k == m and len(x) == len(y) and x @ y / np.linalg.norm(x) / np.linalg.norm(y) >= 0.93]


@pytest.mark.parametrize("tile", [7, 2048])
def test_embeddings_against_brute_force(spark, tile):
    r = np.random.default_rng(1)
    rows, near = [], r.standard_normal(16)
    for i in range(160):
        x = near + 0.15 * r.standard_normal(16) if i % 3 else r.standard_normal(16)
        rows.append((i, [float(np.float32(c)) for c in x * (1 + i % 4)], i % 2))
    rows += [(200, rows[1][1], 1), (201, rows[1][1], 1), (202, None, 1), (203, rows[1][1], None), (204, [0.0] * 16, 1), (205, [float("nan")] + [1.0] * 15, 1), (206, [None] + [1.0] * 15, 1), (207, [float("inf")] + [1.0] * 15, 1), (208, [1.0] * 8, 1), (209, [2.0] * 8, 1), (210, [], 1)]
    vectors = spark.createDataFrame([(*x, "extra") for x in rows], T.StructType.fromDDL("vec_id long, embedding array<float>, label int, rep string"))
    got = {x.vec_id: (x.n_links, x.component_id, x.kept) for x in embedding_dedup.near_duplicates(vectors, tile=tile).collect()}
    links = brute_links(rows)
    root = least_reachable([x[0] for x in rows], links)
    assert got == {i: (sum(i in x for x in links), root[i], root[i] == i) for i, _, _ in rows}
    assert len(links) > 1000


def test_embeddings_of_an_empty_table(spark):
    assert embedding_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def pairs_at(cosine, n, d, r):
    x, y = r.standard_normal((n, d)), r.standard_normal((n, d))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    y -= (x * y).sum(axis=1, keepdims=True) * x
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    return x, cosine[:, None] * x + np.sqrt(1 - cosine * cosine)[:, None] * y


def test_estimates_are_unbiased_and_their_bounds_hold():
    r = np.random.default_rng(2)
    for d in (16, 64, 100, 768):
        cosine = r.uniform(-0.9, 0.99, 4000)
        x, y = pairs_at(cosine, 4000, d, r)
        code, factor = embedding_dedup.quantise(x)
        estimate = embedding_dedup.estimates(code, factor, embedding_dedup.turn(y))
        assert abs((estimate - cosine).mean()) < 0.01
        x, y = pairs_at(np.full(4000, 0.93), 4000, d, r)
        code, factor = embedding_dedup.quantise(x)
        estimate = embedding_dedup.estimates(code, factor, embedding_dedup.turn(y))
        differ = np.bitwise_count(code ^ embedding_dedup.quantise(y)[0]).sum(axis=1)
        for epsilon in (2.0, 3.0):  # the share that falls out is at most what the confidence allows, and not nothing
            out = (estimate < embedding_dedup.least_estimates(factor, d, 0.93, epsilon)).mean()
            assert out <= np.exp(-epsilon**2 / 2) and (differ > embedding_dedup.most_bits(d, 0.93, epsilon)).mean() < np.exp(-epsilon**2 / 2)
        assert (estimate < embedding_dedup.least_estimates(factor, d, 0.93, 1.0)).mean() > 0.01


def test_recall_and_what_each_test_leaves():
    r = np.random.default_rng(4)
    x, y = pairs_at(np.full(20_000, 0.9301), 20_000, 64, r)
    code, factor = embedding_dedup.quantise(x)
    codes = embedding_dedup.quantise(y)[0]
    differ = np.bitwise_count(code ^ codes).sum(axis=1)
    estimate = embedding_dedup.estimates(code, factor, embedding_dedup.turn(y))
    assert (differ <= embedding_dedup.most_bits(64, 0.93, embedding_dedup.EPSILON)).all()  # recall 1 of 20,000
    assert (estimate >= embedding_dedup.least_estimates(factor, 64, 0.93, embedding_dedup.EPSILON)).all()
    x = r.standard_normal((1500, 64))
    x[::3] = x[:1] + 0.4 * x[::3]
    code, factor = embedding_dedup.quantise(x)
    for epsilon in (6.0, 4.0):
        a, b, left = embedding_dedup.linked(x, None, code, factor, None, 0.93, epsilon)
        unit = x / np.linalg.norm(x, axis=1, keepdims=True)
        i, j = np.nonzero(np.triu(unit @ unit.T >= 0.93, 1))
        assert set(zip(a.tolist(), b.tolist(), strict=True)) == set(zip(i.tolist(), j.tolist(), strict=True))
        # bits rule out most pairs, the confidence bound of the estimates most of the others
        assert left["pairs"] == 1500 * 1499 // 2 and left["bits"] < 0.2 * left["pairs"] and left["estimate"] < 0.9 * left["bits"] and left["exact"] == len(i)
