"""The network against plain loops, held-out accuracy, odd rows; and the pipeline against plain code."""

import zlib
from collections import defaultdict

import numpy as np
import pytest

from gridmask.llm import byte_conv, language_id, quality

ODD = [None, "", " \n", "1234 ½ ² ① !!", "é", "x" * 40_000, "word " * 20_000, "same", "same"]


def test_windows_cover_the_text():
    for n in (0, 1, 4, 15, 16, 17, 40, 1000):
        text = bytes(range(1, 256)) * 4
        text = text[:n]
        w = byte_conv.cut(text, 16, 4)
        joined = b"".join([w[0].tobytes(), *(x[4:].tobytes() for x in w[1:])])
        assert joined[:n] == text and not any(joined[n:]) and len(joined) - n < 16 + 1


def test_pooling_equals_plain_loops():
    net = byte_conv.ByteConv(3, window=20, filters=2, embed=3, hidden=4)
    w = byte_conv.cut(b"some text that is longer than one window", 20, net.overlap)
    got = net.pooled(w)
    for i, row in enumerate(w):
        want = [max(max(0.0, float(net.p["E"][row[k : k + 5]].ravel() @ net.p["W"][:, f] + net.p["b"][f])) for k in range(16)) for f in range(8)]
        assert np.allclose(got[i], want, atol=1e-5)


def test_gradients():
    net = byte_conv.ByteConv(2, window=24, filters=2, embed=3, hidden=4)
    for k in net.p:
        net.p[k] = net.p[k].astype(np.float64)
    w = np.concatenate([byte_conv.cut(t, 24, net.overlap) for t in (b"abc def ghi", b"zzz yyy xxx www vvv uuu ttt")])
    starts, y, weights = np.array([0, 1]), np.array([0, 1]), np.array([1.0, 2.0])
    _, g = net._gradients(w, starts, y, weights)
    for k, at in [("O", (0, 1)), ("o", (1,)), ("H", (1, 2)), ("h", (0,)), ("b", (3,)), ("W", (1, 0)), ("E", (ord("z"), 1))]:
        old, eps, values = net.p[k][at], 1e-5, []
        for d in (eps, -eps):
            net.p[k][at] = old + d
            values.append(net._gradients(w, starts, y, weights)[0])
        net.p[k][at] = old
        assert abs((values[0] - values[1]) / (2 * eps) - g[k][at]) < 1e-4


def plain_document(net, text):
    """Class probabilities by the definition: every window on its own, then the largest and the mean of all."""
    w = byte_conv.cut(text, net.window, net.overlap)
    feats = []
    for row in w:
        spans = [net.p["E"][row[k : k + net.span]].ravel() for k in range(net.window - net.span + 1)]
        pooled = np.maximum((np.stack(spans) @ net.p["W"]).max(axis=0) + net.p["b"], 0)
        feats.append(np.maximum(pooled @ net.p["H"] + net.p["h"], 0))
    z = np.concatenate([np.max(feats, axis=0), np.mean(feats, axis=0)]) @ net.p["O"] + net.p["o"]
    e = np.exp(z - z.max())
    return e / e.sum()


def test_document_scores_equal_plain_ones():
    rng = np.random.default_rng(4)
    net = byte_conv.ByteConv(3, window=32, filters=3, embed=4, hidden=6)
    texts = [bytes(rng.integers(1, 256, n, dtype=np.uint8)) for n in (0, 1, 31, 32, 33, 500, 3000, 70, 28 * 300)]
    want = np.stack([plain_document(net, t) for t in texts])
    for at_once in (4, 50, 2048):  # long texts go in blocks, short ones together
        assert np.allclose(net.predict(texts, at_once), want, atol=1e-5)


def test_registered_scores_equal_plain_ones(spark, sf_dir):
    """op2 and op7 as registered, against the trained networks applied text by text."""
    from gridmask.llm import queries

    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    texts = {r.doc_id: r.text for r in docs.collect()}
    net = quality.train(docs, labels.where(~quality.in_held_out_fold()))
    model = language_id.train(docs.where(~language_id.in_held_out_fold()))
    short = sorted(texts, key=lambda i: len(texts[i] or ""))[:40]
    by_quality = {r.doc_id: r for r in queries.op7_quality(spark, sf_dir).collect()}
    by_language = {r.doc_id: r for r in queries.op2_language_id(spark, sf_dir).collect()}
    assert set(by_quality) == set(by_language) == set(texts)
    for i in short:
        want = plain_document(net, (texts[i] or "").encode())[1]
        assert abs(by_quality[i].score - want) < 1e-4 and by_quality[i].predicted == int(by_quality[i].score >= 0.3)
        if language_id.has_letter(texts[i]):
            p = plain_document(model.net, texts[i].lower().encode())
            assert by_language[i].lang_pred == model.languages[p.argmax()] and abs(by_language[i].score - p.max()) < 1e-4


def test_clashing_columns(spark):
    docs = spark.createDataFrame([(1, "some words", "en", "a", "b", "c", "d"), (2, None, None, "a", "b", "c", "d")], "doc_id long, text string, lang string, lang_pred string, score string, held_out string, predicted string")
    assert language_id.identify(docs).columns == ["doc_id", "held_out", "lang_pred", "score"]
    labels = spark.createDataFrame([(1, 1, "x"), (2, 0, "y")], "doc_id long, quality int, score string")
    assert quality.classify(docs, labels).columns == ["doc_id", "held_out", "score", "predicted"]
    assert {r.lang_pred for r in language_id.identify(docs.withColumn("doc_id", docs.doc_id + 0)).collect()} <= {"en", "und"}


def odd(spark, extra="lang string, source string"):
    return spark.createDataFrame([(i, t, None, "score") for i, t in enumerate(ODD)], f"doc_id long, text string, {extra}").coalesce(1)


@pytest.fixture(scope="module")
def larger():
    return "/root/testdata/sf0.01"


def test_language(spark, larger):
    docs = spark.read.parquet(f"{larger}/documents.parquet")
    rows = {r.doc_id: r for r in language_id.identify(docs).collect()}
    truth = {r.doc_id: r.lang for r in docs.collect()}
    assert len(rows) == len(truth)
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 3 == 1) and 0 <= r.score <= 1 for i, r in rows.items())
    held = [i for i, r in rows.items() if r.held_out]
    assert np.mean([rows[i].lang_pred == truth[i] for i in held]) > 0.93
    model = language_id.train(docs, per_language=50, epochs=1)
    got = {r.doc_id: r for r in language_id.predict(odd(spark), model).collect()}
    assert [got[i].lang_pred == "und" for i in range(len(ODD))] == [True, True, True, True, False, False, False, False, False]
    kept = language_id.known_language(odd(spark), model, floor=0.0)
    assert kept.columns == odd(spark).columns and sorted(r.doc_id for r in kept.collect()) == list(range(4, 9))
    none = language_id.identify(odd(spark)).collect()
    assert {r.lang_pred for r in none} == {"und"}
    assert language_id.identify(docs.limit(0)).count() == 0


def test_quality(spark, larger):
    docs, labels = (spark.read.parquet(f"{larger}/{t}.parquet") for t in ("documents", "labels"))
    rows = {r.doc_id: r for r in quality.classify(docs, labels).collect()}
    truth = {r.doc_id: r.quality for r in labels.collect()}
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for i, r in rows.items())
    held = [i for i, r in rows.items() if r.held_out and i in truth]
    good, bad = ([rows[i].score for i in held if truth[i] == q] for q in (1, 0))
    assert np.mean([g > b for g in good for b in bad]) > 0.95
    net = quality.train(docs, labels, per_class=40, epochs=1)
    assert sorted(r.doc_id for r in quality.score(odd(spark), net).collect()) == list(range(9))
    assert quality.good_quality(odd(spark), net, threshold=0.0).count() == 9
    assert {r.score for r in quality.classify(odd(spark), labels.limit(0)).collect()} == {0.5}
    assert quality.classify(docs.limit(0), labels).count() == 0


def test_pipeline(spark, larger):
    import corpus_pipeline

    from test_simhash import plain_components, plain_fingerprint
    from tokenizers import Tokenizer

    from gridmask.llm.tokens import tokenizer_path

    docs = spark.read.parquet(f"{larger}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "language_id", "simhash_near_dedup", "packing"]
    rows = corpus_pipeline.run(spark, larger).collect()
    labels = spark.read.parquet(f"{larger}/labels.parquet")
    net = quality.train(docs, labels.where(~quality.in_held_out_fold()))
    kept = [r for r in docs.collect() if quality.score_texts(net, [r.text])[0] >= 0.3]
    model = language_id.train(spark.createDataFrame(kept, docs.schema).where(~language_id.in_held_out_fold()))
    told = [model.predict([r.text]) for r in kept]
    kept = [r for r, (names, scores) in zip(kept, told) if names[0] != "und" and scores[0] >= 1.25 / len(model.languages)]
    comp = plain_components([r.doc_id for r in kept], [plain_fingerprint(r.text) for r in kept])
    kept = [r for r in kept if comp[r.doc_id] == r.doc_id]
    library, by_doc = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json")), defaultdict(list)
    for r in rows:
        by_doc[r.doc_id].append(r)
    assert set(by_doc) == {r.doc_id for r in kept}
    for r in kept:
        pieces = sorted(by_doc[r.doc_id], key=lambda p: p.start)
        ids, at = np.array([*library.encode(r.text, add_special_tokens=False).ids, 2], "<u4"), 0
        for p in pieces:
            assert p.start == at and p.ids_crc32 == zlib.crc32(ids[at : at + p.length])
            at += p.length
        assert at == len(ids)
