"""Packing, counts and token files against the tokenizer library itself."""

import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
from tokenizers import Tokenizer

from gridmask.llm import packing, token_counts, token_files
from gridmask.llm.shared import new_path
from gridmask.llm.tokens import CachedEncoder, tokenizer_path

ODD = ["", None, " ", "a", "  a  b ", "a\n\n b", "a \n b", "a\n b \n", "x <|endoftext|> y", "<|endoftext|>", "é ñ  z", "a  b   c", "tab\tx\t y", "don't I'LL we've", "\x1cfoo\x1d bar", "日本語 テキスト", "é x ́y", "ΣΑΣ ΟΔΟΣ", "a\r\nb \r\n c", " ", "x" * 5000, "word. " * 9000, "same", "same", "İstanbul क़ा", "<|x", "a   b"]
SCHEMA = "doc_id long, text string, length string, start string"


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "other", "column") for i, t in enumerate(texts)], SCHEMA).coalesce(2)


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_cached_encoder_equals_library(spark, sf_dir, name):
    enc = CachedEncoder(tokenizer_path(name), max_pieces=3000)
    texts = [t or "" for t in ODD] + [r.text or "" for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    want = [e.ids for e in enc.library.encode_batch(texts, add_special_tokens=False)]
    for lo in range(0, len(texts), 37):  # the cache is emptied on the way
        ids, sizes = enc.encode_many(texts[lo : lo + 37])
        assert [x.tolist() for x in np.split(ids, np.cumsum(sizes)[:-1])] == want[lo : lo + 37]
        assert enc.count_many(texts[lo : lo + 37]).tolist() == [len(x) for x in want[lo : lo + 37]]


def test_counts(spark):
    library = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    got = {r.doc_id: r for r in token_counts.count_tokens(frame(spark, ODD), tokenizer_path("byte_bpe_50k.json")).collect()}
    for i, t in enumerate(ODD):
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert (got[i].n_bytes, got[i].n_tokens, got[i].over_limit) == (len((t or "").encode()), n, n > 512)
    assert token_counts.count_tokens(frame(spark, []), tokenizer_path("byte_bpe_50k.json")).count() == 0


def test_segment_random_access():
    rng = np.random.default_rng(1)
    ids = np.concatenate([rng.integers(0, 50000, 4000), rng.integers(0, 200, 1000), [0, 255, 256, 65535, 65536, 1 << 24]]).astype(np.uint32)
    first = np.array([0, 0, 10, 4000, 4000, len(ids)])
    seg = token_files.Segment(token_files.encode_segment(ids, first))
    assert [seg.token(i) for i in range(len(ids))] == ids.tolist()
    for a, b in [(0, len(ids)), (63, 64), (64, 700), (5, 5), (1000, 1001), (4990, len(ids))]:
        assert seg.slice(a, b).tolist() == ids[a:b].tolist()
    assert seg.document(2).tolist() == ids[10:4000].tolist()
    empty = token_files.Segment(token_files.encode_segment(ids[:0], np.array([0, 0])))
    assert empty.document(0).tolist() == []


def test_token_files(spark):
    library = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    to = new_path(spark, "t")
    token_files.write_token_files(frame(spark, ODD).sample(False, 1.0), tokenizer_path("byte_bpe_50k.json"), to, segment_tokens=3000)
    got = sorted(token_files.read_token_files(spark, to).collect())
    start = 0
    for i, (r, t) in enumerate(zip(got, ODD, strict=True)):
        ids = np.array([*library.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (i, start, len(ids), zlib.crc32(ids))
        start += len(ids)
    to = new_path(spark, "t")
    token_files.write_token_files(frame(spark, []), tokenizer_path("byte_bpe_50k.json"), to)
    assert token_files.read_token_files(spark, to).count() == 0


def brute_cuts(positions, penalties, size, exact):
    at, best = [0, *positions], [(0.0, [])]
    for j in range(1, len(at)):
        options = []
        for i in range(j):
            n = at[j] - at[i]
            if n <= size:
                pad = 0 if exact and n & (n - 1) == 0 else size - n
                options.append((best[i][0] + pad + penalties[j - 1], [*best[i][1], at[j]]))
        best.append(min(options))
    return best[-1][0]


@pytest.mark.parametrize("exact", [False, True])
def test_cuts_are_optimal(exact):
    rng = random.Random(5)
    for _ in range(60):
        size = rng.choice([7, 12, 16])
        positions = np.cumsum([rng.randint(1, 5) for _ in range(rng.randint(1, 25))])
        penalties = np.array([float(rng.choice([0, 1, 9])) for _ in positions])
        ends = packing.choose_cuts(positions, penalties, size, exact)
        cost, begin = 0.0, 0
        for e in ends:
            n = e - begin
            assert 0 < n <= size
            cost += (0 if exact and n & (n - 1) == 0 else size - n) + penalties[positions.tolist().index(e)]
            begin = e
        assert begin == positions[-1] and cost == pytest.approx(brute_cuts(positions.tolist(), penalties.tolist(), size, exact))


@pytest.mark.parametrize("horizon", [600_000, 9000])
def test_pack(spark, sf_dir, horizon):
    path, library = tokenizer_path("word_bpe_49k.json"), Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    texts = ODD + [r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    rows = packing.pack(frame(spark, texts), path, horizon=horizon).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append(r)
    for i, t in enumerate(texts):
        ids = np.array([*library.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) and r.length > 0
            assert r.ids_crc32 == zlib.crc32(ids[at : at + r.length])
            at += r.length
        assert at == len(ids)
    padding = total = 0
    for pieces in by_seq.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 4096
        padding += 0 if at & (at - 1) == 0 else 4096 - at
        total += at
    assert padding / total < 0.02
    assert packing.pack(frame(spark, []), path).count() == 0
