"""Embedding near-duplicates: random-hyperplane sign hashing in several tables, exact cosine, components.

Vectors are compared within equal labels only. Equal vectors of a label become one class first. Each class is hashed
into `tables` buckets by the signs of its products with `bits` random hyperplanes. What travels to the buckets is a
class number and the signs of all hyperplanes in use, at most 64 bytes. Two classes of a bucket that agree in so few
signs that their angle can hardly be the threshold's are passed over; only classes with a partner left have their
vector fetched, and those pairs are verified by exact cosine in double precision. A pair that shares several buckets
is counted in the first alone, which both sides' signs tell, so numbers of links add up without the pairs ever being
written. Components come from spanning forests of the verified pairs.

bits grow with the logarithm of the largest label's rows, so that buckets stay small, and tables with them: a pair at
the threshold's angle shares a table with probability (1 - angle / pi) ** bits, and there are as many tables as keep
the share of missed pairs at the threshold at or below `miss`. Closer pairs are missed less. The test on signs passes
over another 1 in 3 million at most (5 standard deviations).

Null, zero and ragged vectors (not of the commonest length), and those with null or non-finite components, or a
null label, link with nothing: 0 links, their own component, kept. Repeated rows count as vectors of their own, rows
that share a vec_id too. A row without a vec_id takes part; it is kept if its whole component has none. An empty
table gives an empty result; other columns are passed by.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components, forest
from .shared import exchange_size, materialize

RESULT = "vec_id long, n_links long, component_id long, kept boolean"
#: Hyperplanes in use, at most: their signs are what a row carries to its buckets.
MOST_SIGNS = 512


def usable(vec: str = "embedding") -> F.Column:
    """Not null, no null or non-finite component, not all zero."""
    finite = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(F.col(vec).isNotNull() & finite & F.exists(vec, lambda x: x != 0), F.lit(False))


def usual_length(df: DataFrame, vec: str = "embedding") -> tuple[int, int]:
    """The commonest length of usable vectors, ties to the larger, and how many have it; zeros if there is none."""
    top = df.where(usable(vec)).groupBy(F.size(vec).alias("n")).count().orderBy(F.desc("count"), F.desc("n")).first()
    return (top["n"], top["count"]) if top else (0, 0)


def hashing(rows: int, threshold: float, miss: float, bucket: int = 32) -> tuple[int, int]:
    """(bits, tables) for labels of at most `rows` rows: buckets of about `bucket` unrelated rows."""
    bits = min(24, max(8, math.ceil(math.log2(max(1, rows) / bucket))))
    shared = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, min(255, math.ceil(math.log(miss) / math.log(1 - shared)))


def near_duplicates(vectors: DataFrame, threshold: float = 0.93, bits: int | None = None, tables: int | None = None, miss: float = 1e-4, seed: int = 17, block_rows: int = 4_096) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of vectors(vec_id, embedding, label)."""
    spark = vectors.sparkSession
    base = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding", "label")
    dims, _ = usual_length(base)
    fit = usable() & (F.size("embedding") == dims) & F.col("label").isNotNull()
    alone = base.where(~fit).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    if not dims:
        return alone
    # -0.0 and 0.0 are one value; two hashes with different beginnings stand for a vector
    zero = F.lit(0.0).cast(dict(base.dtypes)["embedding"].removeprefix("array<").removesuffix(">"))
    good = base.where(fit).withColumn("v", F.transform("embedding", lambda x: F.when(x == 0, zero).otherwise(x)))
    good = good.select("vec_id", "label", F.xxhash64("v").alias("h1"), F.xxhash64(F.lit(7), "v").alias("h2"), "v")
    merged = good.groupBy("label", "h1", "h2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.first("v").alias("v"))
    # class numbers are written down with the classes, so that they stay the same
    classes = materialize(merged.withColumn("cid", F.monotonically_increasing_id()), "vector-classes")
    largest = classes.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    own_bits, own_tables = hashing(largest, threshold, miss)
    bits, tables = bits or own_bits, tables or own_tables
    rng = np.random.default_rng(seed)
    pool = min(-(-tables * bits // 8) * 8, MOST_SIGNS)
    planes = rng.standard_normal((dims, pool))
    own = np.stack([rng.permutation(pool)[:bits] for _ in range(tables)]) if tables * bits > pool else np.arange(tables * bits).reshape(tables, bits)
    weights = 1 << np.arange(bits, dtype=np.int64)
    turned = math.acos(threshold) / math.pi
    most = int(pool * turned + 5 * math.sqrt(pool * turned * (1 - turned))) + 1
    label_type = dict(classes.dtypes)["label"]

    def signs_of(raw: np.ndarray) -> np.ndarray:
        return np.unpackbits(raw.view(np.uint8).reshape(len(raw), -1), axis=1, bitorder="little")

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 2_000):
                b = big.slice(at, 2_000)
                n = b.num_rows
                x = b.column("v").flatten().to_numpy(zero_copy_only=False).reshape(-1, dims).astype(np.float64)
                signs = x @ planes > 0
                codes = (signs[:, own] * weights).sum(axis=2)
                raw = np.packbits(signs, axis=1, bitorder="little")
                take = pa.array(np.repeat(np.arange(n), tables))
                packed = pa.array([r.tobytes() for r in raw], pa.binary())
                cols = [b.column("label").take(take), pa.array(np.tile(np.arange(tables, dtype=np.int32), n)), pa.array(codes.ravel().astype(np.int32)), b.column("cid").take(take), packed.take(take)]
                yield pa.RecordBatch.from_arrays(cols, names=["label", "tab", "code", "cid", "signs"])

    placed = classes.select("label", "v", "cid").mapInArrow(hashed, f"label {label_type}, tab int, code int, cid long, signs binary")
    # a bucket's name is a hash; its last byte is the table, so rows of two tables never meet
    rows = placed.select(F.shiftleft(F.xxhash64("label", "tab", "code"), 8).bitwiseOR(F.col("tab").cast("long")).alias("k"), "cid", "signs")
    # a bucket of more than block_rows is cut into blocks by the class; every two blocks meet in one group
    sizes = rows.groupBy("k").count().where(F.col("count") > block_rows)
    large = materialize(sizes.select("k", F.ceil(F.col("count") / block_rows).cast("int").alias("blocks")), "large-buckets")
    blocks = F.coalesce("blocks", F.lit(1))
    cut = rows.join(large, "k", "left").withColumn("block", F.pmod(F.xxhash64("cid"), blocks).cast("int"))
    meets = cut.withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    grouped = meets.select("k", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "cid", "signs")
    key = ["k", "lo", "hi"]

    def by_group(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
        """Tables of whole groups from rows sorted by key; a group has 2 * block_rows rows or so."""
        held: list[pa.RecordBatch] = []
        for b in batches:
            marks = [b.column(c).to_numpy(zero_copy_only=False) for c in key]
            change = np.flatnonzero(np.any([m[1:] != m[:-1] for m in marks], axis=0)) + 1
            first = tuple(m[0] for m in marks)
            if held and tuple(held[-1].column(c)[held[-1].num_rows - 1].as_py() for c in key) != first:
                yield pa.Table.from_batches(held)
                held = []
            if len(change):
                last = int(change[-1])
                yield pa.Table.from_batches([*held, b.slice(0, last)])
                held = [b.slice(last)]
            elif b.num_rows:
                held.append(b)
        if held:
            yield pa.Table.from_batches(held)

    def groups(table: pa.Table) -> Iterator[tuple[int, int, int, int, int]]:
        marks = [table.column(c).to_numpy() for c in key]
        change = np.flatnonzero(np.any([m[1:] != m[:-1] for m in marks], axis=0)) + 1
        for s, e in zip([0, *change.tolist()], [*change.tolist(), table.num_rows]):
            if e - s > 1:
                yield s, e, int(marks[0][s]) & 255, int(marks[1][s]), int(marks[2][s])

    def pairs(signs: np.ndarray, block: np.ndarray, tab: int, across: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(i, j), i < j: pairs of a group whose signs allow the threshold and whose first common bucket is this one."""
        bits_of = signs_of(signs)
        near = bits_of.astype(np.float32) * 2 - 1
        codes = (bits_of[:, own] * weights).sum(axis=2)
        n = len(near)
        for at in range(0, n, 512):
            i, j = np.nonzero(near[at : at + 512] @ near[at:].T >= pool - 2 * most)
            ok = i < j
            i, j = at + i[ok], at + j[ok]
            same = codes[i, tab] == codes[j, tab]  # unless two buckets' names collide
            same &= ~(codes[i, :tab] == codes[j, :tab]).any(axis=1)
            if across:
                same &= block[i] != block[j]
            yield i[same], j[same]

    width = pool // 8

    def raw_signs(t: pa.Table, s: int, e: int) -> np.ndarray:
        return np.frombuffer(b"".join(t.column("signs").slice(s, e - s).to_pylist()), np.uint8).reshape(e - s, width)

    def candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows of a group that have a partner left."""
        for t in by_group(batches):
            keep = np.zeros(t.num_rows, bool)
            block = t.column("block").to_numpy()
            for s, e, tab, lo, hi in groups(t):
                for i, j in pairs(raw_signs(t, s, e), block[s:e], tab, lo != hi):
                    keep[s + i] = keep[s + j] = True
            if keep.any():
                yield from t.filter(pa.array(keep)).combine_chunks().to_batches()

    dealt = grouped.repartition(exchange_size(spark), *key).sortWithinPartitions(*key)
    left = materialize(dealt.mapInArrow(candidates, grouped.schema), "candidates")
    fetched = left.join(classes.select("cid", "label", "copies", "v"), "cid").repartition(exchange_size(spark), *key).sortWithinPartitions(*key)

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(a, b, links): forest links have links 0, numbers of links have a = b."""
        for t in by_group(batches):
            out: list[tuple[np.ndarray, ...]] = []
            cid, copies, block = (t.column(c).to_numpy() for c in ("cid", "copies", "block"))
            for s, e, tab, lo, hi in groups(t):
                x = t.column("v").slice(s, e - s).combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, dims).astype(np.float64)
                label = np.array(t.column("label").slice(s, e - s).to_pylist(), object)
                x = x / np.sqrt((x * x).sum(axis=1))[:, None]
                counts, edges = np.zeros(e - s, np.int64), []
                for i, j in pairs(raw_signs(t, s, e), block[s:e], tab, lo != hi):
                    ok = np.zeros(len(i), bool)
                    for at in range(0, len(i), 100_000):
                        part = slice(at, at + 100_000)
                        ok[part] = (x[i[part]] * x[j[part]]).sum(axis=1) >= threshold
                    ok &= label[i] == label[j]
                    i, j = i[ok], j[ok]
                    np.add.at(counts, i, copies[s + j])
                    np.add.at(counts, j, copies[s + i])
                    if len(i):
                        edges.append(forest(cid[s + i], cid[s + j]))
                if edges:
                    a, b = forest(*(np.concatenate(c) for c in zip(*edges)))
                    has = np.flatnonzero(counts)
                    out.append((np.concatenate([a, cid[s + has]]), np.concatenate([b, cid[s + has]]), np.concatenate([np.zeros(len(a), np.int64), counts[has]])))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], names=["a", "b", "links"])

    verified = materialize(fetched.mapInArrow(verify, "a long, b long, links long"), "verified")
    links = verified.where("a = b").groupBy(F.col("a").alias("cid")).agg(F.sum("links").alias("others"))
    comp = connected_components(verified.where("a <> b").select("a", "b")).select(F.col("node").alias("cid"), "component")
    slim = classes.select("cid", "label", "h1", "h2", "rep", "copies").join(comp, "cid", "left").withColumn("component", F.coalesce("component", "cid"))
    # most components are one class: their name needs no shuffle beyond the two joins
    firsts = slim.groupBy("component").agg(F.min("rep").alias("component_id"))
    labelled = slim.join(links, "cid", "left").join(firsts, "component").select("label", "h1", "h2", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "component_id")
    linked = good.select("vec_id", "label", "h1", "h2").join(labelled, ["label", "h1", "h2"])
    return linked.select("vec_id", "n_links", "component_id", F.col("vec_id").eqNullSafe(F.col("component_id")).alias("kept")).unionByName(alone)
