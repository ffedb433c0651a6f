"""The array engine: masks, edges, codecs, encodings, trees, appends, baselines; against brute force and DuckDB."""

import itertools
import random
import time

import numpy as np
import pytest

from gridmask.functions import edges as E
from gridmask.functions.codec import CODECS
from gridmask.model import ArrayQuery, ArraySpec, Constraint, Dim, complete_query, fit_spec, to_ranges
from gridmask.operators import append as A
from gridmask.operators import baselines as B
from gridmask.operators import encoding, linear
from gridmask.operators import query as Q
from gridmask.operators.tree import IndexConfig, build_index, choose_fanout, fit_fanout, leaf_row, leaf_rows, merge_ranges, node_row, read_index, vacuum, versions

C = Constraint


def test_constraints():
    assert [(c.lo, c.hi) for c in to_ranges(C.isin([5, 1, 2, 3, 9]), True)] == [(1, 3), (5, 5), (9, 9)]
    spec = ArraySpec((Dim("x", 0, 10), Dim("y", 5, 9)), "value", (4, 4))
    r = complete_query(ArrayQuery({"x": C(2, 7, False, True)}), spec)
    assert r.dims == (((3, 8),), ((5, 9),)) and complete_query(ArrayQuery({"y": C.between(20, 30)}), spec).empty
    with pytest.raises(ValueError):
        complete_query(ArrayQuery({"z": C()}), spec)
    assert [choose_fanout(n) for n in (1, 2, 3, 4, 5)] == [(64,), (8, 8), (4, 4, 4), (4,) * 4, (3,) * 5]
    with pytest.raises(ValueError):
        IndexConfig(bins=1)


@pytest.mark.parametrize("name", list(CODECS))
def test_codecs(name):
    codec, rng = CODECS[name], np.random.default_rng(1)
    cases = [rng.random(n) < p for n in (1, 31, 32, 62, 63, 64, 65, 1000, 32_768) for p in (0.0, 0.01, 0.5, 1.0)]
    cases.append(np.repeat(rng.random(50) < 0.5, 700))
    for n in (1, 31, 64, 1000):
        same = [c for c in cases if len(c) == n]
        assert codec.encode_many([*same, np.zeros(n, bool), np.ones(n, bool)]) == [codec.encode(c) for c in (*same, np.zeros(n, bool), np.ones(n, bool))]
    assert codec.encode_many([]) == [] and codec.encode_many(cases) == [codec.encode(c) for c in cases]
    for a in cases:
        assert (codec.decode(codec.encode(a)) == a).all() and codec.count(codec.encode(a)) == a.sum()
        b = np.roll(a, 7)
        x, y = codec.encode(a), codec.encode(b)
        for got, want in ((codec.and_(x, y), a & b), (codec.or_(x, y), a | b), (codec.xor(x, y), a ^ b), (codec.andnot(x, y), a & ~b), (codec.not_(x), ~a)):
            assert got == codec.encode(want)


def test_five_by_five_column_does_not_shrink():
    bits = np.zeros((5, 5), bool)
    bits[:, 1] = True
    assert len(CODECS["wah"].encode(bits.ravel())) == 8 + 4  # one literal word after the length
    wide = np.zeros((4096, 64), bool)
    wide[:, 1] = True  # rows stretched to words: a run of equal words
    assert len(CODECS["wordrun"].encode(wide.ravel())) < 24 < len(CODECS["wah"].encode(wide.ravel()))


@pytest.mark.parametrize("bins", [1, 2, 3, 4, 7, 8, 16, 17])
def test_encodings(bins):
    rng = np.random.default_rng(bins)
    bin_of = np.where(rng.random(300) < 0.2, -1, rng.integers(0, bins, 300))
    present = bin_of >= 0
    for enc in encoding.ENCODINGS:
        maps = encoding.stored(bin_of, bins, enc)
        assert len(maps) == encoding.bitmap_count(bins, enc)
        for i, j in itertools.combinations_with_replacement(range(bins), 2):
            got, reads = encoding.bin_range(lambda k: maps[k], present, bins, enc, i, j)
            assert (got == (present & (bin_of >= i) & (bin_of <= j))).all()
            most = {"equality": max(1, bins // 2), "two_level": 2 * encoding.GROUP + bins // encoding.GROUP, "bit_sliced": max(1, (bins - 1).bit_length()), "components": 8}
            assert reads <= most.get(enc, 2)


def test_slices_and_components():
    rng = np.random.default_rng(0)
    ranks, present = rng.integers(0, 60, 500), rng.random(500) < 0.9
    slices = encoding.bit_slices(ranks, present)
    parts = [[present & (d <= i) for i in range(b - 1)] for d, b in zip(encoding.digits(ranks, (4, 5, 3)), (4, 5, 3))]
    for bound in range(66):
        want = present & (ranks < bound)
        assert (encoding.sliced_below(slices, present, bound) == want).all()
        assert (encoding.components_below(parts, present, (4, 5, 3), bound) == want).all()


def test_edge_reduction():
    rng = np.random.default_rng(2)
    for _ in range(60):
        edges = np.unique(rng.integers(0, 200, rng.integers(3, 30))).astype(float)
        mass, bins = rng.exponential(1, len(edges) - 1) ** 2, int(rng.integers(2, 8))
        error = lambda kept: E.wsse(E.merged_mass(edges, mass, kept), bins)  # noqa: B023, E731
        width, depth, best = E.reduce_equi_width(edges, bins), E.reduce_equi_depth(edges, mass, bins), E.reduce_optimal(edges, mass, bins)
        for kept in (width, depth, best):
            assert set(kept) <= set(edges) and kept[0] == edges[0] and kept[-1] == edges[-1] and len(kept) <= bins + 1
            assert E.merged_mass(edges, mass, kept).sum() == pytest.approx(mass.sum())
        assert error(best) <= error(depth) + 1e-9 and len(depth) == min(bins + 1, len(edges))
    edges, mass = np.arange(17.0), 2.0 ** -np.arange(16)
    a, b, c = (E.wsse(E.merged_mass(edges, mass, f(edges, mass, 4)), 4) for f in (E.REDUCE["equi_width"], E.reduce_equi_depth, E.reduce_optimal))
    assert a > b >= c


def test_exchange_begins_with_all_bins_and_ends_no_worse():
    rng = np.random.default_rng(21)
    for _ in range(40):
        edges = np.unique(rng.exponential(50, rng.integers(1, 40)))
        mass, bins = rng.exponential(1, max(1, len(edges) - 1)) ** 2, int(rng.integers(2, 9))
        begin, depth = E.begin_equi_depth(edges, mass, bins), E.reduce_equi_depth(edges, mass, bins)
        assert set(begin) <= set(edges) and begin[0] == edges[0] and begin[-1] == edges[-1] and len(begin) == min(bins + 1, len(edges))
        a, b = (E.wsse(E.merged_mass(edges, mass, kept), bins) for kept in (begin, depth))
        assert b <= a + 1e-9 * (1 + a)


def test_v_optimal_is_optimal():
    rng = np.random.default_rng(3)
    for _ in range(20):
        values, freq = np.arange(8.0), rng.integers(1, 30, 8).astype(float)
        edges, cost = E.v_optimal(values, freq, 3)
        every = min(sum(freq[a:b].var() * (b - a) for a, b in zip((0, i, j), (i, j, 8))) for i in range(1, 7) for j in range(i + 1, 8))
        assert cost == pytest.approx(every) and edges[0] == 0 and edges[-1] == 7


def test_v_optimal_by_blocks():
    """Many values at once: the plain recursion's cost and edges, in a fraction of its time."""

    def plain(values, freq, bins):
        k, s, q = len(values), np.concatenate([[0], np.cumsum(freq)]), np.concatenate([[0], np.cumsum(freq**2)])
        best, back = np.array([0.0] + [q[j] - s[j] ** 2 / j for j in range(1, k + 1)]), np.zeros((bins + 1, k + 1), int)
        for b in range(2, bins + 1):
            nxt = np.full(k + 1, np.inf)
            for j in range(b, k + 1):
                i = np.arange(b - 1, j)
                cost = best[i] + q[j] - q[i] - (s[j] - s[i]) ** 2 / (j - i)
                nxt[j], back[b, j] = cost.min(), i[np.argmin(cost)]
            best = nxt
        cuts, j = [], k
        for b in range(bins, 1, -1):
            j = back[b, j]
            cuts.append(j)
        return np.unique([values[0], *values[cuts], values[-1]]), best[k]

    rng, times = np.random.default_rng(4), {}
    for k, bins in ((1, 1), (2, 2), (64, 3), (65, 4), (66, 66), (600, 4)):
        values, freq = np.sort(rng.random(k)), rng.random(k)
        for f in (E.v_optimal, plain):
            start = time.perf_counter()
            out = f(values, freq, bins)
            times[f] = time.perf_counter() - start, out
        assert times[plain][1][1] == pytest.approx(times[E.v_optimal][1][1]) and list(times[plain][1][0]) == list(times[E.v_optimal][1][0])
    assert times[E.v_optimal][0] < times[plain][0] / 1.5


def masks_of(spark, node, constraints, n_words):
    from gridmask.operators.tree import NODE

    row = spark.createDataFrame([node], NODE)
    cols = []
    for c in constraints:
        cols += Q.attr_partial(c, *Q._literal_bounds(c), n_words) + Q.attr_complete(c, *Q._literal_bounds(c), n_words)
    return list(row.select(*[x.alias(f"c{i}") for i, x in enumerate(cols)]).first())


def slots(words, n):
    return {s for s in range(n) if words[s // 64] >> (s % 64) & 1}


@pytest.mark.parametrize(("fanout", "bins"), [((8, 8), 200), ((8, 8), 3), ((3, 3, 3, 3, 3), 16), ((4, 4, 4, 4), 4)])
def test_attribute_masks(spark, fanout, bins):
    rng, n = random.Random(7), int(np.prod(fanout))
    for _ in range(2):
        ids = sorted(rng.sample(range(n), min(n, 40)))
        lows = [float(rng.randint(0, 30)) for _ in ids]
        highs = [a + rng.choice([0, 0, 1, 5, 20]) for a in lows]
        children = {"slot": ids, "vmin": lows, "vmax": highs, "n_cells": [10] * len(ids), "edges": [[a, b] if a < b else [a] for a, b in zip(lows, highs)], "weights": [[10.0]] * len(ids)}
        node = node_row(0, [0] * len(fanout), children, fanout, IndexConfig(bins=bins, fanout=fanout))
        cs = [C(rng.choice([None, *range(-2, 55)]), rng.choice([None, *range(-2, 55)]), rng.random() < 0.5, rng.random() < 0.5) for _ in range(25)]
        cs = [c for c in cs if not c.empty] + [C(None, None), C(5, 5, True, True)]
        w = -(-n // 64)
        got = masks_of(spark, node, cs, w)
        for k, c in enumerate(cs):
            partial, complete = slots(got[2 * k * w : (2 * k + 1) * w], n), slots(got[(2 * k + 1) * w : (2 * k + 2) * w], n)
            inside = lambda v, c=c: (c.lo is None or (v >= c.lo if c.lo_incl else v > c.lo)) and (c.hi is None or (v <= c.hi if c.hi_incl else v < c.hi))
            truly = {s for s, a, b in zip(ids, lows, highs) if inside(a) and inside(b)}
            meets = {s for s, a, b in zip(ids, lows, highs) if (c.lo is None or b > c.lo or (b == c.lo and c.lo_incl)) and (c.hi is None or a < c.hi or (a == c.hi and c.hi_incl))}
            assert complete <= truly and truly | complete <= set(ids) and meets - partial - complete == set()
            if bins == 200:
                assert complete == truly


def test_containing_child_is_not_complete(spark):
    children = {"slot": [0, 1, 2], "vmin": [0.0, 45.0, 70.0], "vmax": [100.0, 50.0, 80.0], "n_cells": [1] * 3, "edges": [[0.0, 100.0], [45.0, 50.0], [70.0, 80.0]], "weights": [[1.0]] * 3}
    node = node_row(0, [0, 0], children, (8, 8), IndexConfig(fanout=(8, 8)))
    partial, complete = masks_of(spark, node, [C.between(40.0, 60.0)], 1)
    assert slots([complete], 64) == {1} and slots([partial], 64) - {1} == {0}


def test_linearisation():
    for fan, levels in (((8, 8), 3), ((3,) * 5, 2), ((4, 4, 4), 3)):
        zs, n = linear.slot_z(fan), len(fan)
        step = n * linear.digit_bits(fan)
        rng = random.Random(0)
        for _ in range(50):
            path = [rng.randrange(len(zs)) for _ in range(levels)]
            z = 0
            for s in path:
                z = z << step | zs[s]
            want = [0] * n
            for s in path:
                want = [w * f + d for w, f, d in zip(want, fan, linear.slot_digits(fan)[s])]
            assert linear.decode_z(z, fan, levels) == want
    points = np.array(list(itertools.product(range(16), repeat=2)))
    h = linear.hilbert_index(points, 4)
    order = points[np.argsort(h)]
    assert sorted(h) == list(range(256)) and (np.abs(np.diff(order, axis=0)).sum(axis=1) == 1).all()


@pytest.fixture(scope="module")
def line16(spark):
    """16 places, chunks of 4 with value ranges [0,10], [12,15], [20,30], [14,40]."""
    values = [0, 4, 7, 10, 12, 13, 14, 15, 20, 24, 27, 30, 14, 22, 33, 40]
    cells = spark.createDataFrame([(i, float(v)) for i, v in enumerate(values)], "x long, value double")
    return build_index(cells, ArraySpec((Dim("x", 0, 16),), "value", (4,)), IndexConfig(fanout=(4,), list_below=0))


def test_worked_descent(line16):
    q = ArrayQuery({"x": C.between(2, 12)}, C.between(13.0, 31.0))
    ((level, kids),) = Q.descend(line16, complete_query(q, line16.spec))
    assert level == 0 and {(r.z, r.complete) for r in kids.collect()} == {(2, True), (1, False)}
    node = line16.level(1).first()
    assert node.plus == [12.0, 14.0, 20.0] and node.minus == [10.0, 15.0, 30.0, 40.0]  # where a child begins or ends
    t = Q.trace(line16, q).first()
    assert (t.children, t.complete, t.partial, t.pruned, t.lookups) == (4, 1, 1, 2, 8)
    assert sorted(r.x for r in Q.range_query(line16, q).collect()) == [5, 6, 7, 8, 9, 10, 11]
    for levels in (1,):
        e = Q.estimate_count(line16, q, levels).first()
        assert e.lower_bound <= 7 <= e.upper_bound


def random_cells(spark, shape, share, seed=0, values=50):
    rng = np.random.default_rng(seed)
    at = np.argwhere(rng.random(shape) < share)
    v = rng.integers(0, values, len(at)).astype(float)
    names = [f"d{i}" for i in range(len(shape))]
    rows = [(*map(int, p), float(x)) for p, x in zip(at, v)]
    return spark.createDataFrame(rows, ", ".join(f"{n} long" for n in names) + ", value double"), names, rows


def plain(rows, names, q):
    def ok(c, v):
        if c.values is not None:
            return v in c.values
        return (c.lo is None or (v >= c.lo if c.lo_incl else v > c.lo)) and (c.hi is None or (v <= c.hi if c.hi_incl else v < c.hi))

    return sorted(r for r in rows if ok(q.attr, r[-1]) and all(ok(q.dims.get(n, C()), x) for n, x in zip(names, r)))


@pytest.mark.parametrize("enc", encoding.ENCODINGS)
def test_random_arrays(spark, enc):
    cells, names, rows = random_cells(spark, (40, 30), 0.6)
    spec = fit_spec(cells, names, (4, 4))
    index = build_index(cells, spec, IndexConfig(bins=4, fanout=(3, 2), leaf_encoding=enc, list_below=6))
    rng = random.Random(1)
    tables = enc in ("range", "interval")  # the descent by tables does not depend on the encoding
    for _ in range(2):
        a, b = sorted(rng.sample(range(41), 2))
        v, w = sorted(rng.sample(range(51), 2))
        q = ArrayQuery({"d0": C.between(a, b)}, C(v, w, rng.random() < 0.5, rng.random() < 0.5))
        for exact, dense in ((True, 4096), (False, 4096), *(((True, 0), (False, 4)) if tables else ())):
            index.dense_rows = dense
            assert sorted(map(tuple, Q.range_query(index, q, exact, "bitmaps").collect())) == plain(rows, names, q)
        assert sorted(map(tuple, Q.range_query(index, q).collect())) == plain(rows, names, q) and Q.count_query(index, q).first().hits == len(plain(rows, names, q))
    q = ArrayQuery({"d1": C.isin([0, 1, 5, 29])}, C.isin([3.0, 4.0, 40.0]))
    traces = []
    for index.dense_rows in (0, 4096) if tables else (4096, 4096):
        assert sorted(map(tuple, Q.range_query(index, q, leaves="bitmaps").collect())) == plain(rows, names, q)
        traces.append(sorted(map(tuple, Q.trace(index, q).collect())))
    assert traces[0] == traces[1]


def files_of(index, table):
    """Data files of an index's table, by folder."""
    from pathlib import Path

    return {str(f) for f in Path(index.path.removeprefix("file://"), table).rglob("*.parquet")}


def scanned(df, path):
    """(files, rows) that a finished query read from tables under path."""
    df.collect()
    files = rows = 0
    todo = [df._jdf.queryExecution().executedPlan()]
    while todo:
        plan = todo.pop()
        name = plan.nodeName()
        if name.startswith("AdaptiveSparkPlan"):
            todo.append(plan.executedPlan())
            continue
        if "QueryStage" in name:
            todo.append(plan.plan())
            continue
        if name.startswith("Scan parquet") and path.removeprefix("file:").strip("/") in plan.relation().location().rootPaths().mkString(","):
            files += plan.metrics().apply("numFiles").value()
            rows += plan.metrics().apply("numOutputRows").value()
        kids = plan.children()
        todo += [kids.apply(i) for i in range(kids.size())]
    return files, rows


def test_ranges_merge():
    assert merge_ranges([(5, 7), (0, 2), (2, 3), (6, 9)]) == [(0, 3), (5, 9)]
    assert merge_ranges([(0, 1), (10, 11), (12, 13), (50, 51)], 2) == [(0, 13), (50, 51)]


def test_query_reads_few_parts(spark):
    """A selective query reads a small share of the files and rows of cells and leaves, each part once."""
    n = 128
    cells = spark.range(n * n).selectExpr(f"id div {n} as x", f"id % {n} as y", "cast(id % 977 as double) as value")
    index = build_index(cells, fit_spec(cells, ["x", "y"], (8, 8)), IndexConfig(fanout=(4, 4), part_cells=1024))
    assert len(index.parts) == 16
    q = ArrayQuery({"x": C.between(40, 50), "y": C.between(100, 109)}, C.between(0.0, 900.0))  # about 0.5 %
    all_files = len(files_of(index, "cells")) + len(files_of(index, "level=0"))
    for index.dense_rows in (4096, 0):
        files, rows = scanned(Q.range_query(index, q), index.path)
        assert files <= all_files * 0.2 and rows <= n * n * 0.1, (index.dense_rows, files, rows)
    blocks = [(r.block, r.reads) for r in Q.blocks_read(index, q).collect()]
    assert len(set(blocks)) == len(blocks) <= 2 and {k for _, k in blocks} == {1}
    want = cells.where("x >= 40 and x < 50 and y >= 100 and y < 109 and value < 900").count()
    for index.dense_rows in (4096, 0, 3):
        assert Q.range_query(index, q).count() == want


def test_batch_reads_few_parts(spark):
    """Queries of a batch read the cells of the parts that they reach."""
    n = 128
    cells = spark.range(n * n).selectExpr(f"id div {n} as x", f"id % {n} as y", "cast(id % 977 as double) as value")
    index = build_index(cells, fit_spec(cells, ["x", "y"], (8, 8)), IndexConfig(fanout=(4, 4), part_cells=1024))
    boxes = spark.createDataFrame([(0, 40, 50, 100, 109, 0.0, 900.0), (1, 41, 44, 90, 97, 100.0, 300.0), (2, 500, 600, 0, 9, 0.0, 1.0)], "q int, lo_x long, hi_x long, lo_y long, hi_y long, lo_value double, hi_value double")
    files, rows = scanned(Q.batch_query(index, boxes), f"{index.path}/cells")
    assert 0 < rows <= n * n * 0.2 and files <= len(files_of(index, "cells")) * 0.2
    want = cells.crossJoin(boxes).where("x >= lo_x and x < hi_x and y >= lo_y and y < hi_y and value >= lo_value and value < hi_value").select("q", "x", "y", "value")
    assert sorted(map(tuple, Q.batch_query(index, boxes).collect())) == sorted(map(tuple, want.collect()))
    assert Q.batch_query(index, boxes.where("q = 2")).count() == 0


def test_append_and_modify(spark):
    cells, names, rows = random_cells(spark, (30, 60), 0.5, seed=4)
    first = cells.where("d1 < 20")
    q = ArrayQuery({"d0": C.below(25)}, C.between(10.0, 41.0))
    for rebalance, part in ((False, 1 << 20), (True, 200)):
        index = build_index(first, fit_spec(first, names, (4, 4)), IndexConfig(bins=4, fanout=(2, 2), part_cells=part))
        height = index.height
        index = A.append(index, cells.where("d1 >= 20 and d1 < 30"), rebalance)
        index = A.append(index, cells.where("d1 >= 30"), rebalance)
        assert index.height > height and sorted(map(tuple, Q.range_query(index, q).collect())) == plain(rows, names, q)
        again = read_index(spark, index.path)
        for again.dense_rows in (0, 4096):
            assert sorted(map(tuple, Q.range_query(again, q).collect())) == plain(rows, names, q)
        if rebalance:  # then every table is as a rebuild makes it, but for where the bins of leaves' parents lie
            fresh = build_index(cells, fit_spec(cells, names, (4, 4)), index.config)
            for k in range(index.height + 1):
                own, new = ({r.z: r for r in i.level(k).collect()} for i in (index, fresh))
                assert own == new
    changed = {r[:2]: float(99 - r[2]) for r in rows if r[0] < 5}
    new = spark.createDataFrame([(*k, v) for k, v in changed.items()], cells.schema)
    want = [(*r[:2], changed.get(r[:2], r[2])) for r in rows]
    assert sorted(map(tuple, Q.range_query(A.modify(index, new), q).collect())) == plain(want, names, q)


def test_append_below_the_origin(spark):
    cells, names, rows = random_cells(spark, (30, 30), 0.5, seed=6)
    shifted = [(a - 9, b - 30, v) for a, b, v in rows]
    index = build_index(cells, fit_spec(cells, names, (4, 4)), IndexConfig(bins=4, fanout=(2, 2), part_cells=50))
    index = A.append(index, spark.createDataFrame([r for r in shifted if r[0] < 0], cells.schema))
    want = rows + [r for r in shifted if r[0] < 0]
    assert sorted(map(tuple, Q.range_query(read_index(spark, index.path), ArrayQuery({}, C.at_least(5.0))).collect())) == plain(want, names, ArrayQuery({}, C.at_least(5.0)))


def test_append_writes_touched_parts_only(spark):
    cells, names, rows = random_cells(spark, (64, 64), 0.5, seed=8)
    index = build_index(cells, fit_spec(cells, names, (4, 4)), IndexConfig(bins=4, fanout=(2, 2), part_cells=100))
    tables = ["cells", *(f"level={k}" for k in range(index.part_level))]
    before = {t: files_of(index, t) for t in tables}
    old = {t: {f: __import__("os").stat(f).st_mtime_ns for f in before[t]} for t in tables}
    assert len(index.parts) >= 8
    changed = A.modify(index, spark.createDataFrame([(5, 5, 77.0), (6, 5, 78.0)], cells.schema))
    for t in tables:
        fresh = files_of(changed, t) - before[t]
        assert len({f.split("part=")[1].split("/")[0] for f in fresh}) == 1 and all("gen=2" in f for f in fresh)
        assert {f: __import__("os").stat(f).st_mtime_ns for f in before[t]} == old[t]
    want = [r for r in rows if r[:2] not in ((5, 5), (6, 5))] + [(5, 5, 77.0), (6, 5, 78.0)]
    everything = ArrayQuery({}, C.at_least(0.0))
    assert sorted(map(tuple, Q.range_query(changed, everything).collect())) == sorted(want)
    # the version before is still whole, until it is cleared away
    assert sorted(map(tuple, Q.range_query(read_index(spark, index.path, 1), everything).collect())) == sorted(rows)
    assert vacuum(changed) > 0 and versions(spark, changed.path) == [2]
    assert sorted(map(tuple, Q.range_query(read_index(spark, changed.path), everything).collect())) == sorted(want)


def test_batches_are_taken_once(spark):
    one = spark.createDataFrame([(3, 4, 7.0)], "d0 long, d1 long, value double")
    index = build_index(one, fit_spec(one, ["d0", "d1"], (4, 4)))
    path = A.append(index, one, on_collision="sum", batch=("s", 0)).path
    for _ in range(2):  # a restarted writer knows only what is on disk
        index = A.append(read_index(spark, path), one, on_collision="sum", batch=("s", 0))
    assert index.cells.first().value == 14.0 and index.state["batches"] == {"s": 0}
    assert A.append(index, one, on_collision="sum", batch=("s", 1)).cells.first().value == 21.0
    with pytest.raises(RuntimeError):  # two writers cannot publish the same version
        A.append(index, one, on_collision="sum", batch=("t", 0))


def test_members_and_estimates(spark):
    cells, names, rows = random_cells(spark, (40, 40), 0.6, seed=9, values=9)
    index = build_index(cells, fit_spec(cells, names, (4, 4)), IndexConfig(fanout=(4, 4), list_below=0))
    root = index.level(index.height).first()
    assert root.edges == [float(v) for v in range(9)] and len(root.weights) == 9  # bins are single values
    for q in (ArrayQuery({}, C.eq(3.0)), ArrayQuery({"d0": C.isin([1, 2, 17]), "d1": C.isin([0, 39])}, C.isin([0.0, 4.0, 8.0])), ArrayQuery({}, C.eq(3.5)), ArrayQuery({"d0": C.at_most(20)}, C(2, 5, False, True))):
        want = plain(rows, names, q)
        for index.dense_rows in (4096, 0):
            assert sorted(map(tuple, Q.range_query(index, q, leaves="bitmaps").collect())) == want
        if q.dims == {}:
            for levels in (1, index.height):
                assert Q.estimate_agg(index, q, levels).first().est_count == pytest.approx(len(want))
            assert Q.estimate_from_histograms(index, q).first().est_sum == pytest.approx(sum(r[2] for r in want))
    few = index.node_rows(1, [r.z for r in index.level(1).collect()])
    assert any(bin(e).count("1") < bin(r["present"]).count("1") for r in few.values() for e in r["equal"])


@pytest.mark.parametrize("order", ["row", "hilbert"])
def test_file_orders(spark, order):
    cells, names, rows = random_cells(spark, (40, 30), 0.6)
    index = build_index(cells, fit_spec(cells, names, (4, 4)), IndexConfig(bins=4, fanout=(4, 4), node_order=order, part_cells=300))
    q = ArrayQuery({"d0": C.between(7, 30)}, C.between(10.0, 30.0))
    assert sorted(map(tuple, Q.range_query(index, q).collect())) == plain(rows, names, q)


def test_written_index_and_source(spark, tmp_path):
    from gridmask.sources.index_source import register

    cells, names, rows = random_cells(spark, (40, 30), 0.6)
    path = f"file://{tmp_path}/index"
    index = build_index(cells, fit_spec(cells, names, (4, 4)), IndexConfig(bins=4, fanout=(3, 2), part_cells=200), path)
    q = ArrayQuery({"d0": C.between(7, 30)}, C.between(10.0, 30.0))
    assert sorted(map(tuple, Q.range_query(read_index(spark, path), q).collect())) == plain(rows, names, q)
    A.modify(index, spark.createDataFrame([(8, 8, 11.5)], cells.schema))
    rows = [r for r in rows if r[:2] != (8, 8)] + [(8, 8, 11.5)]
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    register(spark)
    df = spark.read.format("gridmask").option("index", path).load().where("d0 >= 7 and d0 < 30 and value >= 10 and value < 30")
    assert sorted(map(tuple, df.collect())) == plain(rows, names, q)


def test_baselines_agree(spark):
    cells, names, rows = random_cells(spark, (12, 10, 8), 0.5, seed=5)
    spec = fit_spec(cells, names, (4, 4, 4))
    index = build_index(cells, spec, IndexConfig(bins=4, fanout=(2, 2, 2)))
    lines = B.build_linear(cells, spec, ["value"], 8, "interval")
    columns = [B.build_linear(cells, spec, [*names, "value"], 12, enc) for enc in ("range", "equality", "bit_sliced", "components", "two_level")]
    for q in (ArrayQuery({"d0": C.between(2, 9), "d2": C.at_least(3)}, C.between(5.0, 33.0)), ArrayQuery({}, C.at_least(48.0)), ArrayQuery({"d1": C.between(50, 60)}), ArrayQuery({"d0": C.isin([1, 2, 7]), "d2": C.isin([0, 5])}, C.isin([4.0, 9.0, 10.0]))):
        want = plain(rows, names, q)
        for f in (B.zone_map, B.synopsis_tree, B.grid_filter, Q.range_query):
            assert sorted(map(tuple, f(index, q).collect())) == want
        assert sorted(map(tuple, B.rect_clip(lines, q).collect())) == want
        for own in columns:
            assert sorted(map(tuple, B.dim_columns(own, q).collect())) == want
    boxes = B.clipped_boxes(lines, ArrayQuery({"d0": C.between(2, 9)}, C.between(5.0, 33.0)))
    few = B.count_bounds(columns[0], {"d0": [C.between(2, 9)], "value": [C.between(5.0, 33.0)]}).first()
    assert few.lower_bound <= len(plain(rows, names, ArrayQuery({"d0": C.between(2, 9)}, C.between(5.0, 33.0)))) <= few.upper_bound
    flat = B.box_cells(boxes, spec)
    assert flat.count() == flat.distinct().count()


def test_empty_and_single(spark):
    cells, names, _ = random_cells(spark, (5, 5), 0.5)
    none = cells.where("d0 > 100")
    index = build_index(none, fit_spec(none, names, (4, 4)))
    assert Q.range_query(index, ArrayQuery()).count() == 0
    one = spark.createDataFrame([(3, 4, 7.0)], cells.schema)
    index = build_index(one, fit_spec(one, names, (4, 4)))
    assert Q.range_query(index, ArrayQuery({}, C.eq(7.0))).count() == 1 and Q.range_query(index, ArrayQuery({}, C.eq(8.0))).count() == 0


def test_sweep_equals_plain_clip():
    rng = np.random.default_rng(1)
    runs = (((2, 4), (7, 9)), ((0, 3), (5, 6), (8, 10)), ((1, 9),))
    lo = rng.integers(0, 10, (60, 3))
    boxes = np.stack([lo, lo + rng.integers(1, 5, (60, 3))], axis=2)
    want = []
    for box in boxes:
        for cut in itertools.product(*runs):
            got = [(max(a, c), min(b, d)) for (a, b), (c, d) in zip(box, cut)]
            if all(a < b for a, b in got):
                want.append(tuple(int(x) for p in got for x in p))
    assert sorted(map(tuple, B.sweep(boxes, runs).reshape(-1, 6).tolist())) == sorted(want)


def test_five_dimensions_fit_the_code(spark):
    """A grid of unequal sides, for which five digits of equal width a level take more than 62 bits."""
    spec = ArraySpec((Dim("a", 0, 120_000), Dim("b", 0, 6_000), Dim("c", 0, 84), Dim("d", 0, 7), Dim("e", 0, 50)), "value", (64, 32, 16, 4, 16))
    fan = fit_fanout(spec)
    zs, step = linear.slot_z(fan), linear.step_bits(fan)
    assert len(set(zs)) == len(zs) == int(np.prod(fan)) and max(zs) < 1 << step
    rng = random.Random(4)
    want = {tuple(rng.randrange(d.hi) for d in spec.dims): float(i) for i in range(300)}
    cells = spark.createDataFrame([(*at, v) for at, v in want.items()], "a long, b long, c long, d long, e long, value double")
    index = build_index(cells, spec)
    for q in (ArrayQuery({"a": C.below(70_000), "d": C.at_least(2)}, C.between(20.0, 250.0)), ArrayQuery({"b": C.between(100, 4_000), "e": C.below(40)})):
        hits = {at for at, v in want.items() if (at[0] < 70_000 and at[3] >= 2 and 20 <= v < 250 if "a" in q.dims else 100 <= at[1] < 4_000 and at[4] < 40)}
        for leaves in ("values", "bitmaps"):
            assert {tuple(r)[:5] for r in Q.range_query(index, q, leaves=leaves).collect()} == hits


def test_codes_leave_out_digits_of_dimensions_at_their_end(spark):
    """Two children along each of five dimensions of unequal sides: 15 levels of five bits would not fit a code."""
    from pyspark.sql import functions as F

    from gridmask.sources.index_source import register

    spec, fan = ArraySpec((Dim("a", 0, 1_200_000), Dim("b", 0, 60_000), Dim("c", 0, 84), Dim("d", 0, 7), Dim("e", 0, 50)), "value", (64, 32, 16, 4, 16)), (2,) * 5
    layout = linear.code_layout(spec.grid, fan, 15)
    assert [sum(own) for own in layout] == [5, 4, 3, *[2] * 8, *[1] * 4]
    assert linear.code_layout(spec.grid, (8, 8, 2, 2, 2), 5) == [[3, 3, 1, 1, 1]] * 5
    rng = random.Random(8)
    want = {tuple(rng.randrange(d.hi) for d in spec.dims): float(i) for i in range(240)} | {tuple(d.hi - 1 for d in spec.dims): 500.0}

    def frame(cells):
        return spark.createDataFrame([(*at, v) for at, v in cells.items()], "a long, b long, c long, d long, e long, value double")

    cells = frame(want)
    coded = cells.select(*spec.names, linear.z_code(linear.chunk_coords(spec), fan, 15, layout).alias("z")).toPandas()
    for d, k, at in zip(spec.names, spec.chunk, linear.decode_z(coded["z"].to_numpy(), fan, 15, layout)):
        assert (at == coded[d].to_numpy() // k).all()
    box, top = ArrayQuery({"a": C.between(90_000, 900_000), "d": C.at_least(2)}, C.between(20.0, 250.0)), ArrayQuery({"c": C.at_least(64)}, C.at_least(100.0))

    def check(index, queries):
        for q in queries:
            hits = {at for at, v in want.items() if (90_000 <= at[0] < 900_000 and at[3] >= 2 and 20 <= v < 250 if q is box else at[2] >= 64 and v >= 100)}
            assert {tuple(r)[:5] for r in Q.range_query(index, q).collect()} == hits

    index = build_index(cells, spec, IndexConfig(fanout=fan, part_cells=16))
    assert max(index.parts) < 1 << index.bits(index.height, index.part_level)
    check(index, (box, top))
    index.dense_rows = 0
    check(index, (box,))
    index.dense_rows = 4096
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    register(spark)
    read = spark.read.format("gridmask").option("index", index.path.removeprefix("file://")).load()
    assert {tuple(r)[:5] for r in read.where("a >= 90000 and c < 40").collect()} == {at for at in want if at[0] >= 90_000 and at[2] < 40}
    # beyond the digits that a dimension has: all codes are others
    want[7, 7, 300, 6, 7] = 302.0
    check(A.append(index, frame({(7, 7, 300, 6, 7): 302.0})), (top,))


@pytest.mark.parametrize("below", [None, 0, 12, 10**6])
@pytest.mark.parametrize("rule", ["equi_depth", "equi_width"])
def test_leaves_at_once_equal_leaves_one_by_one(rule, below):
    rng, spec = np.random.default_rng(3), ArraySpec((Dim("x", 3, 500), Dim("y", 7, 300)), "value", (16, 8))
    for bins in (2, 4, 16):
        cfg = IndexConfig(bins=bins, fanout=(4, 4), list_below=below, leaf_binning=rule)
        zs, want, parts = np.sort(rng.choice(4**6, 40, replace=False)), {}, []
        for z in zs.tolist():
            no = np.sort(rng.choice(128, rng.integers(1, 128), replace=False)).astype(np.int32)
            v = rng.integers(0, rng.choice([2, 20, 1000]), len(no)) / 2.0
            at = linear.decode_z(z, (4, 4), 6)
            want[z] = leaf_row(z, [d.lo + a * c for d, a, c in zip(spec.dims, at, spec.chunk)], no, v, spec, cfg)
            parts.append((np.full(len(no), z), no, v))
        got = [tuple(r.values()) for b in leaf_rows(*map(np.concatenate, zip(*parts)), spec, cfg, 6) for r in b.to_pylist()]
        assert {r[0]: r for r in got} == want and len(got) == len(want)


@pytest.mark.parametrize("encoding", ["range", "interval", "equality"])
def test_bitmap_leaves_at_once_equal_leaves_one_by_one(encoding):
    rng, spec = np.random.default_rng(5), ArraySpec((Dim("x", 3, 500), Dim("y", 7, 300)), "value", (16, 8))
    for bins, below, codec in ((2, 0, "wah"), (5, 40, "wah"), (16, 0, "wah"), (16, 30, "raw")):
        cfg = IndexConfig(bins=bins, fanout=(4, 4), list_below=below, leaf_encoding=encoding, codec=codec)
        want, parts = {}, []
        for z in range(60):
            no = rng.choice(128, 128 if z % 9 == 0 else rng.integers(1, 128), replace=False).astype(np.int32)
            v = rng.integers(0, rng.choice([1, 4, 20, 1000]), len(no)) / 2.0
            at = linear.decode_z(z, (4, 4), 6)
            want[z] = leaf_row(z, [d.lo + a * c for d, a, c in zip(spec.dims, at, spec.chunk)], no, v, spec, cfg)
            parts.append((np.full(len(no), z), no, v))
        got = [tuple(r.values()) for b in leaf_rows(*map(np.concatenate, zip(*parts)), spec, cfg, 6) for r in b.to_pylist()]
        assert {r[0]: r for r in got} == want and len(got) == len(want)


@pytest.mark.parametrize("codec", sorted(CODECS))
def test_bitmaps_from_ones_equal_bitmaps_from_bits(codec):
    rng = np.random.default_rng(6)
    for n in (1, 31, 62, 100, 124, 32768):
        maps = [rng.random(n) < p for p in (0, 0.001, 0.05, 0.5, 0.97, 1, 0)] + [np.arange(n) // 31 % 3 > 0]
        row, place = np.nonzero(np.stack(maps))
        mixed = rng.permutation(len(row))
        ends, data = CODECS[codec].encode_ones(n, len(maps), row[mixed], place[mixed])
        assert [data[a:b] for a, b in zip([0, *ends], ends)] == [CODECS[codec].encode(m) for m in maps]


def test_linear_index_lists_blocks_of_few_cells(spark):
    """A wide array of few cells a block keeps three rows a block instead of some dozens; answers are as before."""
    rng = random.Random(9)
    want = {(rng.randrange(2_000), rng.randrange(3_000)): float(i % 97) for i in range(400)} | {(5, y): float(y % 50) for y in range(1_000)}
    cells = spark.createDataFrame([(*at, v) for at, v in want.items()], "x long, y long, value double")
    spec = fit_spec(cells, ["x", "y"], (32, 32))
    q = ArrayQuery({"x": C.between(3, 1_500), "y": C.at_least(40)}, C.between(10.0, 60.0))
    hits = {(*at, v) for at, v in want.items() if 3 <= at[0] < 1_500 and at[1] >= 40 and 10 <= v < 60}
    for enc in ("range", "interval", "components"):
        lines, columns = B.build_linear(cells, spec, ["value"], 8, enc), B.build_linear(cells, spec, ["x", "y", "value"], 8, enc)
        rows = {r[0]: r[1] for r in columns.bitmaps.groupBy("block").count().collect()}
        assert sorted(rows.values())[-2] == 4 and max(rows.values()) > 4  # x = 5 fills its block, all others are listed
        assert {tuple(r) for r in B.dim_columns(columns, q).collect()} == hits == {tuple(r) for r in B.rect_clip(lines, q).collect()}
        bounds = B.count_bounds(columns, B.wanted_columns(spec, complete_query(q, spec))).first()
        assert bounds.lower_bound <= len(hits) <= bounds.upper_bound


@pytest.fixture
def four_tasks(spark):
    """Four tasks after a shuffle, however few rows there are."""
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    yield
    spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_leaves_are_made_from_dealt_cells(spark, tmp_path, four_tasks):
    """Cells are dealt once, by code: a part's leaves come from few tasks, so they lie in few files."""
    cells = spark.range(64 * 64).selectExpr("id div 64 AS x", "id % 64 AS y", "cast(id * 7 % 101 AS double) AS value")
    index = build_index(cells, fit_spec(cells, ["x", "y"], (4, 4)), IndexConfig(fanout=(2, 2), part_cells=256), f"file://{tmp_path}/i")
    assert index.leaves.count() == 256 and len(index.parts) == 16
    assert len(list((tmp_path / "i" / "level=0").rglob("*.parquet"))) <= len(index.parts) + 4


def test_z_code_of_many_levels_is_compiled(spark):
    """The JVM leaves methods of 8,000 bytes of code and more uncompiled; tables of several levels' digits keep below."""
    from pyspark.sql import functions as F

    for fan, levels in (((2,) * 5, 11), ((4, 4, 4), 8), ((3,) * 5, 6)):
        names = [f"c{i}" for i in range(len(fan))]
        cells = spark.range(2000).select(*[(F.col("id") * (7 * i + 3) % min(f**levels, 3000)).alias(c) for i, (c, f) in enumerate(zip(names, fan))])
        rows = cells.withColumn("z", linear.z_code([F.col(c) for c in names], fan, levels))
        code = rows._jdf.queryExecution().debug().codegenToSeq()
        assert max(code.apply(i)._3().maxMethodCodeSize() for i in range(code.size())) < 8000
        got = rows.toPandas()
        for c, at in zip(names, linear.decode_z(got["z"].to_numpy(), fan, levels)):
            assert (got[c].to_numpy() == at).all()


@pytest.mark.parametrize("fan, cfg", [((2, 2, 2), IndexConfig(bins=4)), ((2, 2, 2), IndexConfig(bins=4, node_values=False)), ((16, 8), IndexConfig(bins=8))])
def test_plain_nodes_at_once_as_one_by_one(fan, cfg):
    import math

    import pyarrow as pa

    from gridmask.operators import tree as T

    rng, n, n_slots = np.random.default_rng(3), 60, math.prod(fan)
    nodes = []
    for g in range(n):
        kids = []
        for s in sorted(rng.choice(n_slots, rng.integers(1, 7), replace=False)):
            e = np.unique(rng.integers(0, 6 + 3 * (g % 4), rng.integers(1, 4))).astype(float)
            spread = g % 10 == 9 and len(e) > 1
            kids.append((s, e[0], e[-1], int(rng.integers(1, 9)), e, rng.integers(1, 5, len(e) - spread).astype(float)))
        nodes.append(kids)
    flat = [k for kids in nodes for k in kids]
    slot, low, high, cells = (np.array([k[i] for k in flat]) for i in range(4))
    owner = np.repeat(np.arange(n), [len(kids) for kids in nodes])
    every = T.Children(owner, slot, low, high, cells, *(np.array([len(k[i]) for k in flat]) for i in (4, 5)), *(np.concatenate([k[i] for k in flat]) for i in (4, 5)))
    plain = T.plain_nodes(every, n, cfg)
    words, numbers = pa.list_(pa.int64()), pa.list_(pa.float64())
    kinds = {"z": pa.int64(), "lo": words, "n_cells": pa.int64(), "vmin": pa.float64(), "vmax": pa.float64(), "edges": numbers, "weights": numbers, "plus": numbers, "started": pa.list_(words), "minus": numbers, "ended": pa.list_(words), "equal": pa.list_(words), "present": words}
    z = np.arange(n)
    got = T.plain_node_rows(z[plain], np.stack([z, z], axis=1)[plain], every.of(plain), n_slots, cfg, pa.schema(list(kinds.items()))).to_pylist()
    assert 10 < plain.sum() < n and len(got) == plain.sum()
    for row in got:
        kids = dict(zip(("slot", "vmin", "vmax", "n_cells", "edges", "weights"), zip(*nodes[row["z"]])))
        assert tuple(row.values()) == node_row(row["z"], row["lo"], kids, fan, cfg)


@pytest.mark.parametrize("fan, cfg", [((4, 4, 4), IndexConfig(bins=4)), ((8, 8), IndexConfig(bins=16)), ((16, 8), IndexConfig(bins=8, node_values=False))])
def test_wide_nodes_at_once_as_one_by_one(fan, cfg):
    import math

    import pyarrow as pa

    from gridmask.operators import tree as T

    rng, n, n_slots = np.random.default_rng(4), 50, math.prod(fan)
    nodes = []
    for g in range(n):
        kids = []
        for s in sorted(rng.choice(n_slots, rng.integers(2, n_slots), replace=False)):
            e = np.unique(rng.integers(0, 20 + 100 * (g % 5), rng.integers(1, 18))).astype(float)
            spread = g % 3 > 0 and len(e) > 1 and rng.random() < 0.7
            kids.append((s, e[0], e[-1], int(rng.integers(1, 9)), e, rng.integers(0, 5, len(e) - spread).astype(float)))
        nodes.append(kids)
    flat = [k for kids in nodes for k in kids]
    slot, low, high, cells = (np.array([k[i] for k in flat]) for i in range(4))
    owner = np.repeat(np.arange(n), [len(kids) for kids in nodes])
    every = T.Children(owner, slot, low, high, cells, *(np.array([len(k[i]) for k in flat]) for i in (4, 5)), *(np.concatenate([k[i] for k in flat]) for i in (4, 5)))
    wide = ~T.plain_nodes(every, n, cfg) & (T.bounds_of(every, n) > 1)
    words, numbers = pa.list_(pa.int64()), pa.list_(pa.float64())
    kinds = {"z": pa.int64(), "lo": words, "n_cells": pa.int64(), "vmin": pa.float64(), "vmax": pa.float64(), "edges": numbers, "weights": numbers, "plus": numbers, "started": pa.list_(words), "minus": numbers, "ended": pa.list_(words), "equal": pa.list_(words), "present": words}
    z = np.arange(n)
    got = T.wide_node_rows(z[wide], np.stack([z] * len(fan), axis=1)[wide], every.of(wide), n_slots, cfg, pa.schema(list(kinds.items()))).to_pylist()
    assert wide.sum() > 30 and len(got) == wide.sum()
    for row in got:
        kids = dict(zip(("slot", "vmin", "vmax", "n_cells", "edges", "weights"), zip(*nodes[row["z"]])))
        assert tuple(row.values()) == node_row(row["z"], row["lo"], kids, fan, cfg)


def test_edges_of_many_nodes_reduced_as_one_by_one():
    from gridmask.functions import edges as E

    rng = np.random.default_rng(6)
    for bins in (2, 3, 8, 16):
        rows = [np.unique(rng.integers(0, 400, rng.integers(bins + 3, 120))).astype(float) for _ in range(60)]
        rows = [e for e in rows if len(e) > bins + 1]
        masses = [rng.integers(0, 9, len(e) - 1).astype(float) ** rng.integers(1, 3) for e in rows]
        n, most = np.array([len(e) for e in rows]), max(map(len, rows))
        edges, mass = np.full((len(rows), most), np.inf), np.zeros((len(rows), most - 1))
        for i, (e, m) in enumerate(zip(rows, masses)):
            edges[i, : len(e)], mass[i, : len(m)] = e, m
        kept = E.reduce_equi_depth_many(edges, n, mass, bins)
        for e, m, k in zip(rows, masses, kept):
            assert e[k].tolist() == E.reduce_equi_depth(e, m, bins).tolist()


def test_raw_rows_collapse_as_they_are_dealt(spark):
    import pandas as pd
    from pyspark.sql import functions as F

    rng = np.random.default_rng(7)
    rows = spark.createDataFrame(pd.DataFrame({"x": rng.integers(0, 160, 3000), "y": rng.integers(3, 123, 3000), "value": rng.random(3000)}))
    cells = rows.groupBy("x", "y").agg(F.max("value").alias("value"))
    cfg = IndexConfig(bins=4, fanout=(2, 2), part_cells=30)
    index = build_index(rows, fit_spec(rows, ["x", "y"], (4, 4)), cfg, raw=True)
    plain = build_index(cells, fit_spec(cells, ["x", "y"], (4, 4)), cfg)
    assert index.spec == plain.spec and index.spec.n_cells == cells.count() < 3000 and index.state["parts"] == plain.state["parts"]
    for name in ("cells", *(f"level={k}" for k in range(index.height + 1))):
        assert sorted(map(str, index.read(name).collect())) == sorted(map(str, plain.read(name).collect()))
    # parts are many: what is made of a part's children is one file
    assert index.part_level > 1 and len(index.parts) >= 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    files = index.level(1).select(F.input_file_name().alias("f")).distinct().count()
    assert files == len(index.parts)


def test_raw_rows_collapse_in_a_linear_index_and_few_answers_are_broadcast(spark):
    import pandas as pd
    from pyspark.sql import functions as F

    rng = np.random.default_rng(8)
    rows = spark.createDataFrame(pd.DataFrame({"x": rng.integers(0, 20_000, 2000), "y": rng.integers(5, 20_000, 2000), "value": rng.random(2000)}))
    rows = rows.unionByName(rows.withColumn("value", F.col("value") / 2)).repartition(3)
    cells = rows.groupBy("x", "y").agg(F.max("value").alias("value"))
    index = B.build_linear(rows, fit_spec(rows, ["x", "y"], (32, 32)), ["x", "y", "value"], 8, raw=True)
    plain = B.build_linear(cells, fit_spec(cells, ["x", "y"], (32, 32)), ["x", "y", "value"], 8)
    assert index.spec.n_cells == cells.count() < rows.count()
    for name in ("cells", "bitmaps"):
        assert sorted(map(str, getattr(index, name).collect())) == sorted(map(str, getattr(plain, name).collect()))
    q = ArrayQuery({"x": C.between(100, 9000), "y": C.between(50, 7000)}, C.between(0.2, 0.9))
    found = B.dim_columns(index, q)
    assert index.blocks * B.block_cells(index.spec) // 4 > Q.MOST_BROADCAST
    assert "BroadcastHashJoin" in found._jdf.queryExecution().sparkPlan().toString()
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, B.scan(cells, index.spec, q).collect()))
    none = B.dim_columns(index, ArrayQuery({"x": C.between(100, 9000)}, C.between(5.0, 6.0)))
    assert none.count() == 0


def test_edges_of_many_values_are_equally_deep(spark):
    from pyspark.sql import functions as F

    cells = spark.range(300_000).select((F.col("id") * 7919 % 300_000).alias("k"), F.expr("CASE WHEN id % 2 = 0 THEN 3.0D ELSE sqrt(id) END").alias("value"))
    edges = B.global_edges(cells, ["k", "value"], 16)
    assert len(edges["k"]) == 17 and (edges["k"][0], edges["k"][-1]) == (0, 299_999)
    assert np.abs(np.diff(edges["k"]) - 300_000 / 16).max() < 200
    assert 3.0 in edges["value"] and len(edges["value"]) < 17  # half of all values are one


def test_middle_of_a_bin_as_by_all_inner_edges():
    rng = np.random.default_rng(5)
    for _ in range(300):
        total = np.concatenate([[0], np.cumsum(rng.integers(0, 4, 20))]).astype(float)
        a, b = sorted(rng.choice(21, 2, replace=False))
        if b - a > 1:
            inner = np.arange(a + 1, b)
            assert E._middle(total.tolist(), int(a), int(b)) == inner[np.argmin(np.abs(total[inner] - (total[a] + total[b]) / 2))]


def test_listed_leaves_answer_by_their_cells_numbers(spark):
    """A chunk of 8,192 cells that lists three of them answers with their numbers, not with words over the whole chunk."""
    rng = np.random.default_rng(11)
    rows = {(int(x), int(y)): float(v) for x, y, v in zip(rng.integers(0, 300, 60), rng.integers(0, 300, 60), rng.integers(0, 50, 60))}
    cells = spark.createDataFrame([(x, y, v) for (x, y), v in rows.items()], "x long, y long, value double")
    index = build_index(cells, fit_spec(cells, ["x", "y"], (128, 64)))
    q = ArrayQuery({"x": Constraint.isin([*range(20, 90), *range(100, 250)]), "y": Constraint.below(200)}, Constraint.between(5.0, 30.0))
    want = {(x, y) for (x, y), v in rows.items() if (20 <= x < 90 or 100 <= x < 250) and y < 200 and 5.0 <= v < 30.0}
    region = complete_query(q, index.spec)
    answers = Q.leaf_answers(index, region, Q.descend(index, region)).collect()
    assert answers and all(r.listed and r.hit == r.sure and 0 < len(r.hit) < 60 for r in answers)
    assert sum(len(r.hit) for r in answers) <= len(want)
    assert Q.count_query(index, q).first().hits == len(want) > 0
    assert {(r.x, r.y) for r in Q.range_query(index, q, leaves="bitmaps").collect()} == want
