"""Fingerprints, allocation, the join and components against brute force."""

import random
import re

import numpy as np
import xxhash

from gridmask.llm import components, simhash


def plain_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    grams = [" ".join(words[i : i + 4]) for i in range(len(words) - 3)] if len(words) >= 4 else [" ".join(words)] if words else []
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_components(ids, fps, radius=4):
    parent = {i: i for i in ids}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, f in zip(ids, fps):
        for j, g in zip(ids, fps):
            if j < i and (f ^ g).bit_count() <= radius:
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    return {i: root(i) for i in ids}


def test_fingerprint():
    for t in [None, "", "  \t\n", "One", "ÄÖ Ü a\x0bb", "a b c d", "the Cat sat ON the mat " * 9, "x\x1cy z w q r s", "dup dup dup dup dup"]:
        assert simhash.fingerprint(t) == plain_fingerprint(t)


def test_allocation_is_least_and_complete():
    rng = np.random.default_rng(3)
    costs = rng.integers(0, 50, (40, 4, 4)).astype(float)
    got = simhash.allocate(costs, 5)
    assert (got.sum(axis=1) == 1).all() and got.min() >= -1
    for row, t in zip(costs, got):
        best = min(sum(row[i, s[i]] for i in range(4)) for s in np.ndindex(4, 4, 4, 4) if sum(s) == 5)
        assert sum(row[i, t[i] + 1] for i in range(4)) == best


def test_join_on_planted_fingerprints(spark):
    rng = random.Random(7)
    fps = [0, (1 << 64) - 1]
    for _ in range(40):
        f = rng.getrandbits(64)
        fps += [f] + [f ^ sum(1 << b for b in rng.sample(range(64), rng.choice([1, 3, 4, 5, 8]))) for _ in range(6)]
    hub = rng.getrandbits(64)
    fps += [hub ^ sum(1 << b for b in rng.sample(range(64), 3)) for _ in range(150)]
    fps = sorted(set(fps), key=lambda f: (f * 2654435761) % 1009)
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame(list(zip(signed, range(len(fps)))), "fp long, rep long")
    for options in ({}, {"bucket_rows": 8, "most": 1}):
        comp = {r.node: r.component for r in components.connected_components(simhash.links_forest(df, 4, **options)).collect()}
        assert {i: comp.get(i, i) for i in range(len(fps))} == plain_components(range(len(fps)), fps)


def test_documents(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    odd = spark.createDataFrame([(10_000 + i, t, "fp") for i, t in enumerate([None, "", " ", "One", "one", "a b c d e", "A b c d e"])], docs.schema)
    rows = simhash.near_duplicates(docs.union(odd).withColumnRenamed("lang", "fp").union(odd)).collect()
    assert len(rows) == docs.count() + 14
    text = {r.doc_id: r.text for r in docs.union(odd).collect()}
    ids = sorted(text)
    want = plain_components(ids, [plain_fingerprint(text[i]) for i in ids])
    for r in rows:
        assert r.fp % 2**64 == plain_fingerprint(text[r.doc_id]) and r.component_id == want[r.doc_id]
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_components_of_chains(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 - i) for i in range(1, 50)] + [(5000, 5000), (7, 3)]
    random.Random(1).shuffle(edges)
    got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(edges, "x long, y long").repartition(4)).collect()}
    assert got == {**{i: 0 for i in range(1, 201)}, **{i: 951 for i in range(952, 1001)}}


def test_registered_query(spark, sf_dir):
    """op4 as registered: hex digits and components against plain code."""
    from gridmask.llm import queries

    rows = spark.read.parquet(f"{sf_dir}/documents.parquet").collect()
    fps = [plain_fingerprint(r.text) for r in rows]
    comp = plain_components([r.doc_id for r in rows], fps)
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op4_simhash(spark, sf_dir).collect()}
    assert got == {r.doc_id: (format(f, "016x"), comp[r.doc_id]) for r, f in zip(rows, fps)}


def test_hot_buckets_are_cut(spark):
    """Buckets of more than bucket_rows: every index row in one block, and no link lost."""
    rng = np.random.default_rng(9)
    base = rng.integers(0, 1 << 63, dtype=np.uint64)
    fps = {int(base)}
    while len(fps) < 300:  # near one value, so all partitions are hot
        x = int(base)
        for b in rng.choice(64, rng.integers(1, 6), replace=False):
            x ^= 1 << int(b)
        fps.add(x)
    fps = sorted(fps)
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    distinct = spark.createDataFrame([(f, i) for i, f in enumerate(signed)], "fp long, rep long")
    want = plain_components(list(range(len(fps))), fps)
    for size in (8192, 16):
        links = [(r.a, r.b) for r in simhash.links_forest(distinct, 4, bucket_rows=size).collect()]
        root = {i: i for i in range(len(fps))}

        def find(i):
            while root[i] != i:  # noqa: B023
                i = root[i]  # noqa: B023
            return i

        for a, b in links:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
        assert {i: find(i) for i in range(len(fps))} == {i: want[i] for i in range(len(fps))}


def plain_wide(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    k = min(5, len(words))
    h = [xxhash.xxh3_128_intdigest(g, 42) for g in {b" ".join(words[i : i + k]) for i in range(len(words) - k + 1)}] if words else []
    own = xxhash.xxh3_128_intdigest(b" ".join(words), 43)
    bits = 0
    for b in range(128 if words else 0):
        twice = 2 * sum(x >> b & 1 for x in h)
        bits |= (own >> b & 1 if twice == len(h) else twice > len(h)) << b
    return bits


def as_int(digest_words):
    """The digest's bytes, most significant first, as the library's integer counts them."""
    return int.from_bytes(np.asarray(digest_words, "<u8").tobytes(), "little")


def swap(x):
    """Bytes of a 128-bit integer turned round: the fingerprint reads the digest's bytes in their order."""
    return int.from_bytes(x.to_bytes(16, "big"), "little")


def test_wide_fingerprint():
    for t in [None, "", " \n", "One", "a b c d e", "a b c d e f", "the Cat sat ON the mat " * 9, "x y z w q r s t u v", "ÄÖ Ü a b c d e f g"]:
        assert as_int(simhash.wide_fingerprint(t)) == swap(plain_wide(t)), t
    # an even number of shingles, half of them shared: tied bits do not make texts of few shingles alike
    a, b = (simhash.wide_fingerprint(t) for t in ("one two three four five six", "one two three four five seven"))
    assert int(np.bitwise_count(a ^ b).sum()) > 22


def test_join_of_two_words(spark):
    """All pairs within the radius link, none beyond the reach; pairs between them mostly do."""
    rng = random.Random(11)
    fps = [0]
    for _ in range(60):
        f = rng.getrandbits(128)
        fps += [f] + [f ^ sum(1 << b for b in rng.sample(range(128), d)) for d in (1, 9, 15, 16, 19, 22, 23, 30)]
    rows = [tuple(np.array([f & (2**64 - 1), f >> 64], np.uint64).view(np.int64).tolist()) + (i,) for i, f in enumerate(fps)]
    df = spark.createDataFrame(rows, "w0 long, w1 long, rep long")
    for options in ({}, {"bucket_rows": 8}):
        comp = {r.node: r.component for r in components.connected_components(simhash.links_forest(df, 15, 22, **options)).collect()}
        at_least, at_most = plain_components(range(len(fps)), fps, 15), plain_components(range(len(fps)), fps, 22)
        got = [comp.get(i, i) for i in range(len(fps))]
        assert all(got[i] == got[at_least[i]] for i in range(len(fps)))
        assert all(at_most[i] == at_most[g] for i, g in enumerate(got))
        assert sum(g != i for i, g in enumerate(got)) > 0.95 * sum(at_most[i] != i for i in range(len(fps)))


def test_first_of_groups_by_similarity(spark):
    """Near copies of a similarity of 0.9 and more go, unrelated texts and texts that share one passage stay."""
    rng = random.Random(5)
    vocabulary = [f"word{i}" for i in range(3000)]
    passage = rng.choices(vocabulary, k=55)
    rows, copies = [], set()
    for i in range(150):
        words = rng.choices(vocabulary, k=rng.choice([130, 300, 900]))
        rows.append((10 * i, " ".join(words + (passage if i % 3 == 0 else []))))
        near = list(rows[-1][1].split())
        for at in rng.sample(range(len(near)), max(1, len(near) // 130)):
            near[at] = "changed"
        rows.append((10 * i + 1, " ".join(near)))
        copies.add(10 * i + 1)
    rows += [(5000 + i, t) for i, t in enumerate(["a b c d e f", "a b c d e g", "z b c d e f", "x", "y"])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "xxhash64(doc_id, text) AS _row")
    kept = {r.doc_id for r in simhash.first_of_groups(docs).collect()}
    assert {i for i, _ in rows} - copies <= kept
    assert len(copies & kept) <= 3
