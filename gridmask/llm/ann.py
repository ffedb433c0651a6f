"""Approximate nearest neighbours by an adaptive scan of dimensions within probed lists.

Vectors are rotated by a random orthogonal matrix and dealt to the nearest of about sqrt(rows) centroids, fitted on a
bounded sample of `sample_rows` rows. How many lists a query probes is measured on that sample: the fewest whose share
of the true neighbours reaches `target`; neighbours in the whole table lie closer than in the sample, so the share can
only rise. A query probes more lists where those hold fewer than k rows. Within a list, rotated vectors lie in blocks
of columns; after each block a candidate's distance so far, scaled to all dimensions, is tested against the query's
k-th best: by the concentration of random projections, distance_so_far > (1 + eps / sqrt(d))**2 * d / D * best rejects
it at a small error rate. Each query starts with the k-th best among the sampled vectors of its nearest lists, so tests
reject from the first list on. Survivors are measured exactly, in double precision, on the original vectors.

Lists beyond `list_rows` rows are salted into parts, so no task holds more; each part gives every probing query its k
best, and the k best of those are the answer.

Null, zero and ragged vectors (not of the commonest length), and those with null or non-finite components, take no
part. Rows are told apart by a number of their own: a query's candidates are all rows but itself, rows of the same
vec_id among them, and rows that repeat a query are queries too, with ranks of their own under the same query_id. A
null vec_id is a candidate, last among ties. Ties go to the smaller vec_id. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .embedding_dedup import usable, usual_length
from .shared import exchange_size, materialize


def rotation(dims: int, seed: int = 5) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dims, dims)))
    return q * np.sign(np.diag(r))


def kmeans(x: np.ndarray, k: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """Lloyd's centroids; an empty one is put on a random point."""
    rng = np.random.default_rng(seed)
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)]
    for _ in range(rounds):
        near = nearest(x, centres, 1)[:, 0]
        sums = np.zeros_like(centres)
        np.add.at(sums, near, x)
        counts = np.bincount(near, minlength=len(centres))
        centres = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], x[rng.integers(0, len(x), len(centres))])
    return centres


def nearest(x: np.ndarray, centres: np.ndarray, k: int) -> np.ndarray:
    """(rows, k): the k nearest centroids of each row, nearest first."""
    d = (centres * centres).sum(axis=1) - 2 * x @ centres.T
    k = min(k, d.shape[1])
    top = np.argpartition(d, k - 1, axis=1)[:, :k]
    return np.take_along_axis(top, np.argsort(np.take_along_axis(d, top, axis=1), axis=1), axis=1)


def needed_probes(sample: np.ndarray, centres: np.ndarray, k: int, target: float, queries: int = 256) -> int:
    """The fewest probes that find the share `target` of the true k nearest of `queries` sampled vectors in the sample."""
    k = min(k, len(sample) - 1)
    if k < 1:
        return len(centres)
    asked = np.linspace(0, len(sample) - 1, min(queries, len(sample))).astype(int)
    home = nearest(sample, centres, 1)[:, 0]
    square = (sample * sample).sum(axis=1)
    at = []
    for i in asked:
        d = square - 2 * sample @ sample[i]
        d[i] = np.inf
        true = np.argpartition(d, k - 1)[:k]
        order = nearest(sample[i : i + 1], centres, len(centres))[0]
        place = np.empty(len(centres), np.int64)
        place[order] = np.arange(len(centres))
        at.append(place[home[true]])
    ranks = np.sort(np.concatenate(at))
    return int(ranks[min(len(ranks) - 1, int(np.ceil(target * len(ranks))) - 1)]) + 1


def adaptive_scan(query: np.ndarray, blocks: list[np.ndarray], worst: float, eps: float) -> np.ndarray:
    """Rows of a list that survive all tests against the squared distance `worst`; blocks hold the list's columns."""
    dims = sum(b.shape[0] for b in blocks)
    alive = np.arange(blocks[0].shape[1])
    so_far, seen = np.zeros(len(alive), np.float32), 0
    for b in blocks:
        part = b[:, alive] if len(alive) < b.shape[1] else b
        diff = part - query[seen : seen + b.shape[0], None]
        so_far = so_far + np.einsum("ij,ij->j", diff, diff)
        seen += b.shape[0]
        limit = worst * (seen / dims) * (1 + eps / np.sqrt(seen)) ** 2 if seen < dims else worst * (1 + 1e-4)
        keep = so_far <= limit
        if not keep.all():
            alive, so_far = alive[keep], so_far[keep]
        if not len(alive):
            break
    return alive


def scan_list(ids: np.ndarray, rows: np.ndarray, vectors: np.ndarray, turned: np.ndarray, query_row: int, query: np.ndarray, query_turned: np.ndarray, bound: float, k: int, block: int, eps: float, chunk: int = 4_096) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k nearest rows of one list part not farther than bound: ids, row numbers, exact distances. The query's own
    row is left out."""
    best_ids, best_rows, best, worst = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), bound
    for at in range(0, len(ids), chunk):
        part = slice(at, at + chunk)
        blocks = [turned[c : c + block, part] for c in range(0, turned.shape[0], block)]
        alive = at + (adaptive_scan(query_turned, blocks, worst * worst, eps) if np.isfinite(worst) else np.arange(blocks[0].shape[1]))
        alive = alive[rows[alive] != query_row]
        if len(alive):
            diff = vectors[alive].astype(np.float64) - query
            dist = np.sqrt((diff * diff).sum(axis=1))
            all_ids, all_rows, all_dist = np.concatenate([best_ids, ids[alive]]), np.concatenate([best_rows, rows[alive]]), np.concatenate([best, dist])
            order = np.lexsort((all_rows, all_ids, all_dist))[:k]
            best_ids, best_rows, best = all_ids[order], all_rows[order], all_dist[order]
            if len(best) == k:
                worst = min(worst, float(best[-1]))
    return best_ids, best_rows, best


def search(vectors: DataFrame, is_query: Column, k: int = 10, n_lists: int | None = None, target: float = 0.96, sample_rows: int = 20_000, list_rows: int = 50_000, block: int = 16, eps: float = 3.0) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest of every row that is_query holds for, among all other rows.

    n_lists None: sqrt(rows), at most an eighth of the sample. target: the share of true neighbours that probes are
    chosen for.
    """
    spark = vectors.sparkSession
    result = "query_id long, rank int, vec_id long, score double"
    base = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding", F.coalesce(is_query, F.lit(False)).alias("asks"))
    dims, n_rows = usual_length(base)
    if not dims:
        return spark.createDataFrame([], result)
    double = dict(base.dtypes)["embedding"] == "array<double>"
    kind, kind_sql = (pa.float64(), "array<double>") if double else (pa.float32(), "array<float>")
    good = base.where(usable() & (F.size("embedding") == dims)).withColumn("embedding", F.col("embedding").cast(kind_sql))
    sample = good.select("embedding").orderBy(F.xxhash64("vec_id", "embedding"), "vec_id").limit(sample_rows).collect()
    turn = rotation(dims)
    turned_sample = np.array([r[0] for r in sample], np.float64) @ turn
    centres = kmeans(turned_sample, n_lists or max(1, min(round(n_rows**0.5), len(sample) // 8)))
    probes = needed_probes(turned_sample, centres, k, target)
    home = nearest(turned_sample, centres, 1)[:, 0]
    members = [turned_sample[home == i] for i in range(len(centres))]

    def matrix(b: pa.RecordBatch, name: str) -> np.ndarray:
        return b.column(name).flatten().to_numpy(zero_copy_only=False).reshape(-1, dims)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 4_000):
                b = big.slice(at, 4_000)
                lists = nearest(matrix(b, "embedding").astype(np.float64) @ turn, centres, 1)[:, 0]
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("row", "vec_id", "asks", "embedding")), pa.array(lists.astype(np.int32))], names=["row", "vec_id", "asks", "embedding", "l"])

    # row numbers are written down with the rows, so that they stay the same
    numbered = good.withColumn("row", F.monotonically_increasing_id())
    dealt = materialize(numbered.mapInArrow(deal, f"row long, vec_id long, asks boolean, embedding {kind_sql}, l int"), "dealt")
    # as many rows as lists, whatever the corpus
    sizes = np.zeros(len(centres), np.int64)
    for r in dealt.groupBy("l").count().collect():
        sizes[r["l"]] = r["count"]
    parts = np.maximum(1, -(-sizes // list_rows))

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A query's row for every part of every list that it probes, with the bound it starts from."""
        for big in batches:
            for at in range(0, big.num_rows, 250):
                b = big.slice(at, 250)
                x = matrix(b, "embedding").astype(np.float64) @ turn
                order = nearest(x, centres, len(centres))
                # the own row counts among those of a list, hence more than k
                deep = np.maximum(probes, 1 + (np.cumsum(sizes[order], axis=1) <= k).sum(axis=1))
                take, lists, salts, bounds = [], [], [], []
                for i in range(len(x)):
                    near = np.concatenate([members[l] for l in order[i, :4]])
                    gaps = np.sort(((near - x[i]) ** 2).sum(axis=1))
                    # one of the sampled may be the query itself, so one more is counted
                    bound = float(np.sqrt(gaps[k])) * (1 + 1e-6) if len(gaps) > k else np.inf
                    for l in order[i, : deep[i]].tolist():
                        if sizes[l]:
                            take += [i] * int(parts[l])
                            lists += [l] * int(parts[l])
                            salts += range(int(parts[l]))
                            bounds += [bound] * int(parts[l])
                rows = pa.array(take, pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(lists, pa.int32()), pa.array(salts, pa.int32()), pa.array(np.ones(len(take), np.int8)), *(b.column(c).take(rows) for c in ("row", "vec_id", "embedding")), pa.array(bounds, pa.float64())], names=["l", "p", "asking", "row", "vec_id", "embedding", "bound"])

    shape = f"l int, p int, asking byte, row long, vec_id long, embedding {kind_sql}, bound double"
    asked = dealt.where("asks").select("row", "vec_id", "embedding").mapInArrow(ask, shape)
    cut = F.broadcast(spark.createDataFrame([(i, int(n)) for i, n in enumerate(parts)], "l int, n int"))
    stored = dealt.join(cut, "l").select("l", F.pmod(F.xxhash64("row"), F.col("n")).cast("int").alias("p"), F.lit(0).cast("byte").alias("asking"), "row", "vec_id", "embedding", F.lit(None).cast("double").alias("bound"))
    dealt_out = stored.unionByName(asked).repartition(max(exchange_size(spark), len(centres) // 8), "l", "p").sortWithinPartitions("l", "p", "asking", "row")

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by list part, stored ones before queries; one part's stored rows are held at a time."""
        key: tuple[int, int] | None = None
        held: list[tuple[np.ndarray, ...]] = []
        ready: tuple[np.ndarray, ...] = ()
        for b in batches:
            l, p, asking, row = (b.column(c).to_numpy(zero_copy_only=False) for c in ("l", "p", "asking", "row"))
            # a null id comes last among ties
            ids = b.column("vec_id").fill_null(np.iinfo(np.int64).max).to_numpy(zero_copy_only=False)
            x = matrix(b, "embedding")
            bound = b.column("bound").to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero((l[1:] != l[:-1]) | (p[1:] != p[:-1]) | (asking[1:] != asking[:-1])) + 1).tolist(), len(l)]
            out: list[tuple[np.ndarray, ...]] = []
            for s, e in zip(cuts, cuts[1:]):
                if s == e:
                    continue
                if key != (l[s], p[s]):
                    key, held, ready = (l[s], p[s]), [], ()
                if not asking[s]:
                    held.append((ids[s:e], row[s:e], x[s:e]))
                    continue
                if not held:
                    continue
                if not ready:
                    all_ids, all_rows, all_x = (np.concatenate(c) for c in zip(*held))
                    ready = all_ids, all_rows, all_x, np.ascontiguousarray((all_x.astype(np.float64) @ turn).astype(np.float32).T)
                for i in range(s, e):
                    q = x[i].astype(np.float64)
                    found, found_rows, dist = scan_list(*ready, row[i], q, (q @ turn).astype(np.float32), bound[i], k, block, eps)
                    out.append((np.full(len(found), row[i]), np.full(len(found), ids[i]), found, found_rows, dist))
            if out:
                cols = [np.concatenate(c) for c in zip(*out)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["query_row", "query_id", "vec_id", "row", "score"])

    found = dealt_out.mapInArrow(scan, "query_row long, query_id long, vec_id long, row long, score double")
    w = Window.partitionBy("query_row").orderBy("score", "vec_id", "row")
    real = lambda c: F.when(F.col(c) < F.lit(np.iinfo(np.int64).max), F.col(c)).alias(c)
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select(real("query_id"), "rank", real("vec_id"), "score")
