"""The max-plus scan against one sequential pass, word-wise BPE against the library."""

import random
import zlib

import numpy as np
from sentencepiece import SentencePieceProcessor

from gridmask.llm import sentence_pieces as sp
from gridmask.llm.tokens import tokenizer_path

PATH = tokenizer_path("piece_bpe_32k.model")
ODD = [None, "", " ", "a", "  two  blanks ", "a\nb", "a \n b", "\n", "tab\tx", "▁mark", "日本 語", "é ñ", "x" * 3000, "word " * 4000, "</s> <s>", "ﬁ ligature", "a  b", "İ", "​ zero", "don't", "a\r\nb", "same", "same"]


def random_lattice(rng, letters="abc", longest=4):
    pieces = {"".join(rng.choice(letters) for _ in range(rng.randint(1, longest))): -rng.random() * 5 for _ in range(12)}
    return sp.Lattice(pieces, -9.0)


def plain_best(lattice, text):
    best = [0.0] + [-1e18] * len(text)
    for j in range(1, len(text) + 1):
        for i in range(max(0, j - lattice.longest), j):
            s = lattice.scores.get(text[i:j], lattice.unknown if j - i == 1 else None)
            if s is not None:
                best[j] = max(best[j], best[i] + s)
    return best[-1]


def score(lattice, pieces):
    return sum(lattice.scores.get(p, lattice.unknown) for p in pieces)


def test_scan_equals_one_pass():
    rng = random.Random(2)
    for _ in range(60):
        lattice = random_lattice(rng)
        text = "".join(rng.choice("abcd") for _ in range(rng.randint(0, 40)))
        best = plain_best(lattice, text)
        for chunk in (None, 1, 2, 3, 7, 20):
            pieces = sp.segment(lattice, text, chunk)
            assert "".join(pieces) == text and abs(score(lattice, pieces) - best) < 1e-9


def test_products_are_associative():
    rng = random.Random(3)
    lattice = random_lattice(rng)
    text = "".join(rng.choice("abcd") for _ in range(60))
    m = [lattice.transfer(text, i, i + 20) for i in (0, 20, 40)]
    left, right = sp.max_plus(sp.max_plus(m[0], m[1]), m[2]), sp.max_plus(m[0], sp.max_plus(m[1], m[2]))
    assert np.allclose(left[0, 0], right[0, 0]) and np.allclose(left[0, 0], plain_best(lattice, text))


def test_giants_over_tasks(spark):
    rng = random.Random(4)
    lattice = random_lattice(rng)
    texts = ["".join(rng.choice("abcd") for _ in range(n)) for n in (0, 1, 5, 200, 333)] + [None]
    df = spark.createDataFrame([(i, t, "no") for i, t in enumerate(texts)], "doc_id long, text string, part string")
    for options in ({"chunk": 37}, {"chunk": 9, "fan": 3}):  # several levels of products
        got = {r.doc_id: r.pieces for r in sp.segment_giants(df, lattice, **options).collect()}
        for i, t in enumerate(texts):
            assert "".join(got[i]) == (t or "") and abs(score(lattice, got[i]) - plain_best(lattice, t or "")) < 1e-9
    odd = spark.createDataFrame([(None, texts[3]), (1, texts[3]), (1, texts[4]), (1, texts[4])], "doc_id long, text string")
    got = sorted(((r.doc_id or 0, "".join(r.pieces)) for r in sp.segment_giants(odd, lattice, chunk=50, fan=2).collect()))
    assert got == sorted([(0, texts[3]), (1, texts[3]), (1, texts[4]), (1, texts[4])])


def test_bpe_equals_library(spark, sf_dir):
    library = SentencePieceProcessor(model_file=PATH)
    texts = ODD + [r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, ids string")
    got = {r.doc_id: r.ids for r in sp.encode(df, PATH).collect()}
    assert [got[i] for i in range(len(texts))] == [library.encode(t or "") for t in texts]
    back = {r.doc_id: r.text for r in sp.decode(sp.encode(df, PATH), PATH).collect()}
    assert [back[i] for i in range(len(texts))] == [library.decode(library.encode(t or "")) for t in texts]
    for r in sp.encode_and_check(df, PATH).collect():
        ids = library.encode(texts[r.doc_id] or "")
        assert (r.n_pieces, r.ids_crc32, r.decoded_crc32) == (len(ids), zlib.crc32(np.array(ids, "<u4")), zlib.crc32(library.decode(ids).encode()))
    assert sp.encode(df.limit(0), PATH).count() == 0
