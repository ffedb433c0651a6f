"""The pipeline and its stages on odd rows."""

import zlib

import corpus_pipeline
from gridmask.llm import language_id

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def words(seed, n=60):
    return " ".join(f"w{seed}x{i * i % 97}" for i in range(n))


def test_near_dedup_judges_rows_not_ids(spark):
    a, b, c, d, e = map(words, range(5))
    rows = [(1, a), (1, b), (2, a), (3, c), (3, c), (None, c), (None, d), (None, d.upper()), (None, e), (0, b), (7, None), (None, "")]
    docs = spark.createDataFrame([(i, t, None, f"s{k}" if i is None else None, None) for k, (i, t) in enumerate(rows)], SCHEMA).repartition(3)
    kept = corpus_pipeline.without_near_duplicates(spark, docs, "")
    assert kept.columns == docs.columns
    found = sorted(((r.doc_id, r.text) for r in kept.collect()), key=str)
    upper = d if (None, d) in found else d.upper()
    assert found == sorted([(1, a), (0, b), (3, c), (None, upper), (None, e), (7, None)], key=str)
    again = sorted(((r.doc_id, r.text) for r in corpus_pipeline.without_near_duplicates(spark, docs.repartition(5), "").collect()), key=str)
    assert again == found
    assert corpus_pipeline.without_near_duplicates(spark, docs.limit(0), "").count() == 0


def test_language_stage_without_taught_texts(spark):
    rows = [(0, "some words"), (1, "1234 !!"), (2, None), (3, "é")]
    docs = spark.createDataFrame([(i, t, None, None, None) for i, t in rows], SCHEMA)
    assert sorted(r.doc_id for r in corpus_pipeline.by_language(spark, docs, "").collect()) == [0, 3]
    model = language_id.LanguageModel([], None)
    assert sorted(r.doc_id for r in language_id.known_language(docs, model, floor=0.5).collect()) == [0, 3]


def test_language_stage_rejects_texts_in_no_learned_language(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("lang is not null")
    odd = ["Это обычный русский текст о погоде и городе. " * 4, "这是一个关于天气和城市的普通中文文本。" * 6, "これは天気についての文章です。" * 6, "xqzt vvrk jjpw qqxz " * 10, "a8f3e09c1d77 " * 15]
    more = spark.createDataFrame([(10**6 + i, t, None, "s", len(t)) for i, t in enumerate(odd)], SCHEMA)
    kept = {r.doc_id for r in corpus_pipeline.by_language(spark, docs.unionByName(more), "").select("doc_id").collect()}
    taught = {r.doc_id for r in docs.select("doc_id").collect()}
    assert not kept - taught and len(kept) >= 0.99 * len(taught)
    model = language_id.LanguageModel(["en"], None, language_id.letters_of(["Abc", "é 1"]))
    assert model.letters == set("abcé") and [model.taught_share(t) for t in ("CAB 12!", "éж", "жж 1")] == [1, 0.5, 0]


def write_tables(spark, folder, rows, labels=()):
    schema = "doc_id long, text string, lang string, source string, n_chars long, score string, sequence_id string"
    spark.createDataFrame([(i, t, None, "s", None, "clash", "clash") for i, t in rows], schema).write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(list(labels), "doc_id long, quality int, toxic int").write.mode("overwrite").parquet(f"{folder}/labels.parquet")


def test_run_on_odd_rows(spark, tmp_path):
    long = " ".join(f"word{i * 7919 % 10007}" for i in range(20_000))
    rows = [(1, words(1)), (1, words(1)), (2, None), (3, ""), (4, "1234 ½ ②"), (5, long), (6, long.upper()), (7, words(7)), (None, words(8))]
    write_tables(spark, tmp_path, rows)
    # nothing is taught: every score is even, and only texts without a letter have no language
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    by_doc = {}
    for r in out:
        by_doc.setdefault(r.doc_id, []).append(r)
    assert set(by_doc) == {1, 5, 7, None}
    for pieces in by_doc.values():
        pieces.sort(key=lambda r: r.start)
        assert [p.start for p in pieces] == [sum(q.length for q in pieces[:k]) for k in range(len(pieces))]
        assert sum(p.length for p in pieces) == pieces[0].doc_tokens
    write_tables(spark, tmp_path / "none", [])
    assert corpus_pipeline.run(spark, str(tmp_path / "none")).count() == 0


def test_stages_keep_columns(spark, tmp_path):
    write_tables(spark, tmp_path, [(1, words(1)), (2, words(2))])
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, str(tmp_path)).columns == docs.columns
    assert zlib.crc32(b"1") % 3 != 1  # one of the two teaches in the language stage, without a lang
