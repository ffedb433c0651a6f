"""Nearest neighbours against exact search."""

import numpy as np
from pyspark.sql import functions as F

from gridmask.llm import ann


def exact(ids, x, queries, k=10):
    out = {}
    for q in queries:
        i = ids.index(q)
        d = np.sqrt(((x - x[i]) ** 2).sum(axis=1))
        order = [j for j in np.lexsort((ids, d)) if j != i][:k]
        out[q] = [(ids[j], d[j]) for j in order]
    return out


def test_recall_on_table(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    rows = df.collect()
    want = exact([r.vec_id for r in rows], np.array([r.embedding for r in rows], float), [r.vec_id for r in rows if r.vec_id % 20 == 0])
    got = {}
    for r in ann.search(df, F.col("vec_id") % 20 == 0).collect():
        got.setdefault(r.query_id, []).append(r)
    hits = 0
    for q, w in want.items():
        mine = sorted(got[q], key=lambda r: r["rank"])
        assert [r["rank"] for r in mine] == list(range(1, 11)) and [(r.score, r.vec_id) for r in mine] == sorted((r.score, r.vec_id) for r in mine)
        hits += len({r.vec_id for r in mine} & {i for i, _ in w})
        true = dict(w)
        assert all(abs(r.score - true[r.vec_id]) < 1e-9 for r in mine if r.vec_id in true)
    assert hits / (10 * len(want)) >= 0.9


def test_odd_rows(spark):
    rng = np.random.default_rng(0)
    vectors = [[float(np.float32(x)) for x in rng.standard_normal(8)] for _ in range(30)]
    rows = [(i, v, 1) for i, v in enumerate(vectors)] + [(40, vectors[0], 1), (41, vectors[0], 1), (42, vectors[0], 1)]
    bad = [(100, None, 1), (101, [0.0] * 8, 1), (102, [float("nan")] * 8, 1), (103, [None] * 8, 1), (104, [1.0], 1)]
    df = spark.createDataFrame(rows + bad, "vec_id long, embedding array<float>, rank int")
    ids, x = [r[0] for r in rows], np.array([r[1] for r in rows])
    want = exact(ids, x, ids)
    for size in (50_000, 5):  # large lists are salted
        got = {}
        for r in ann.search(df, F.lit(True), n_lists=3, target=1.0, list_rows=size, eps=9.0).collect():
            got.setdefault(r.query_id, []).append((r["rank"], r.vec_id))
        assert {q: [i for _, i in sorted(v)] for q, v in got.items()} == {q: [i for i, _ in w] for q, w in want.items()}
    assert ann.search(df.limit(0), F.lit(True)).count() == 0
    few = ann.search(df.where("vec_id < 4"), F.lit(True)).groupBy("query_id").count().collect()
    assert {r["count"] for r in few} == {3}


def test_repeated_rows_and_doubles(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((40, 6))  # not exact in 32 bits
    rows = [(i, x[i].tolist()) for i in range(40)] + [(7, x[7].tolist()), (7, x[8].tolist()), (None, x[9].tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    all_x = np.array([r[1] for r in rows])
    got = {}
    for r in ann.search(df, F.col("vec_id") == 7, target=1.0, eps=9.0).collect():
        got.setdefault(r["rank"], []).append((r.vec_id, r.score))
    assert sorted(got) == list(range(1, 11)) and all(len(v) == 3 for v in got.values())  # three rows ask, each has ten
    want = {k: [] for k in got}
    for q in (7, 40, 41):
        d = np.sqrt(((all_x - all_x[q]) ** 2).sum(axis=1))
        ids = [1 << 62 if r[0] is None else r[0] for r in rows]
        order = [j for j in np.lexsort((range(43), ids, d)) if j != q][:10]
        for k, j in enumerate(order, 1):
            want[k].append((rows[j][0], d[j]))
    for k in want:
        a, b = sorted(got[k], key=str), sorted(want[k], key=str)
        assert [i for i, _ in a] == [i for i, _ in b] and np.allclose([s for _, s in a], [s for _, s in b], rtol=1e-14, atol=0)


def test_adaptive_scan_keeps_the_nearest():
    rng = np.random.default_rng(4)
    x = rng.standard_normal((2000, 64)).astype(np.float32)
    q = rng.standard_normal(64).astype(np.float32)
    d = ((x - q) ** 2).sum(axis=1)
    worst = np.sort(d)[9]
    alive = ann.adaptive_scan(q, [np.ascontiguousarray(x.T)[c : c + 16] for c in range(0, 64, 16)], float(worst), 2.5)
    assert set(np.argsort(d)[:10]) <= set(alive) and len(alive) < 40
