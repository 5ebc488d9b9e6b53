import zlib

import corpus_pipeline
from boxsum.llm import quality, secret_scan
from boxsum.llm.queries import QUERIES, held_out

SF = "/root/testdata/sf0.001"


def test_stages_keep_the_columns_and_take_effect(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    seen = []
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        stage(spark, docs, SF).write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        seen.append(name)
        if name != "packing":
            assert docs.columns == corpus_pipeline.COLUMNS
            ids = {r.doc_id for r in docs.collect()}
            old = {r.doc_id: r for r in before.collect()}
            assert ids <= set(old)
        if name == "quality":
            labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
            sure = [i for i in old if i in labels]
            assert sum((i in ids) == bool(labels[i]) for i in sure) / len(sure) > 0.95
        if name == "near_duplicates":
            sets = {}
            for i, r in old.items():
                w = (r.text or "").lower().split()
                sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
            pairs = [(i, j, len(sets[i] & sets[j]) / len(sets[i] | sets[j])) for i in sets for j in sets if i < j]
            # of each two at a similarity of 0.8 or more one goes, and none goes but for one that is nearly as similar
            assert not any(i in ids and j in ids for i, j, s in pairs if s >= 0.8)
            for i in set(old) - ids:
                assert any(s >= 0.68 and i in (a, b) for a, b, s in pairs)
        if name == "secrets":
            assert ids == set(old)
            scan = secret_scan.scanner(secret_scan.RULES)
            assert not any(scan.scan([r.text for r in docs.collect()]))
    assert seen == ["quality", "language", "near_duplicates", "secrets", "packing"]
    pieces = docs.collect()
    assert {p.doc_id for p in pieces} == ids
    assert sum(p.length for p in pieces) == sum({p.doc_id: p.doc_tokens for p in pieces}.values())
    got = corpus_pipeline.run(spark, SF)
    assert sorted((p.doc_id, p.start, p.length, p.ids_crc32) for p in got.collect()) == sorted((p.doc_id, p.start, p.length, p.ids_crc32) for p in pieces)


def test_stages_of_no_documents(spark):
    empty = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, SF).count() == 0


def test_language_stage_learns_from_all_texts(spark):
    rare = [i for i in range(12_000, 12_100) if zlib.crc32(str(i).encode()) % 4 != 2][:4]
    rows = [(i, "the common words of a usual text", "en", "web", 32) for i in range(12_000)] + [(i, "zebra quartz jumping vixen", "en", "web", 26) for i in rare]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r.doc_id for r in corpus_pipeline.by_language(spark, docs, SF).select("doc_id").collect()}
    assert set(rare) <= kept and len(kept) == len(rows)


def test_held_out_fourth(spark):
    got = {r.id: r.h for r in spark.range(200).select("id", held_out("id").alias("h")).collect()}
    assert got == {i: zlib.crc32(str(i).encode()) % 4 == 2 for i in range(200)}


def test_queries_have_a_row_for_each_input_row(spark):
    n = {t: spark.read.parquet(f"{SF}/{t}.parquet").count() for t in ("documents", "embeddings", "pages")}
    for name, query in QUERIES.items():
        if not name.startswith("op8"):
            table = "embeddings" if name.startswith("op2") else "pages" if name.startswith(("op3", "op4")) else "documents"
            assert query(spark, SF).count() == n[table], name
    assert quality.N_TEXT > 10
