"""SimHash near-duplicates by the generalised pigeonhole principle.

A fingerprint has one or more 64-bit words; two documents link when at most `radius` bits differ. With a larger
`reach`, candidates link at up to that many bits: complete up to `radius`, by chance beyond it. The bits are grouped
into partitions, correlated ones together. Thresholds t_i >= -1 with sum radius - (number of partitions) + 1 never miss a
linked pair: some partition differs in at most t_i bits. Every fingerprint gets the thresholds of its own that make
the fewest candidates, by dynamic programming over exact counts of all fingerprints; -1 leaves a partition out.
Probes enumerate the values within t_i of a fingerprint's value, meet the index rows of that value, and are verified.

Work is on distinct fingerprints, so copies cost nothing. A task yields a spanning forest of the pairs that it
verified, not the pairs. A bucket of more than `bucket_rows` index rows is cut into blocks by a hash: each index row
lies in one block, and a probe of the bucket goes to each of them. Memory: one block's index rows (8 bytes a word and 8
for the id) and a block of candidates.

Null text counts as empty: no word, fingerprint 0, linked like any other. Repeated rows are kept. An empty table
gives an empty result. Other columns are passed by.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components, forest
from .shared import exchange_size, materialize, ranges

WORD = 64
#: Words of the fingerprints that estimate similarity.
WIDE = ("w0", "w1")
#: A column that tells rows apart, where doc_id does not.
ROW = "_row"
#: An odd multiplier that spreads fingerprints over blocks.
MIX = np.uint64(0x9E3779B97F4A7C15)


def fingerprint(text: str | None, words_per_shingle: int = 4, seed: int = 42) -> int:
    """Unsigned fingerprint of a whole text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    starts, k = ends - sizes, min(words_per_shingle, len(words))
    digest = xxhash.xxh64_intdigest
    n = len(words) - k + 1
    h = np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts[:n].tolist(), ends[k - 1 :].tolist())), np.uint64, n)
    return int(np.packbits(2 * count_ones(h) > n, bitorder="little").view("<u8")[0])


def count_ones(h: np.ndarray) -> np.ndarray:
    """How many of the hashes, one a row, have each bit set."""
    raw = h.view(np.uint8).reshape(len(h), -1)
    ones = np.zeros(raw.shape[1] * 8, np.int64)
    for at in range(0, len(raw), 4096):
        ones += np.unpackbits(raw[at : at + 4096], axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return ones


def wide_fingerprint(text: str | None, words_per_shingle: int = 5, seed: int = 42) -> np.ndarray:
    """Two words over the set of shingles. A tied bit is the whole text's, so that texts of few shingles keep apart."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(2, np.uint64)
    k, digest = min(words_per_shingle, len(words)), xxhash.xxh3_128_digest
    seen = {digest(b" ".join(words[i : i + k]), seed) for i in range(len(words) - k + 1)}
    twice = 2 * count_ones(np.frombuffer(b"".join(seen), np.uint8).reshape(-1, 16))
    own = np.unpackbits(np.frombuffer(digest(b" ".join(words), seed + 1), np.uint8), bitorder="little")
    bits = np.where(twice == len(seen), own, twice > len(seen)).astype(np.uint8)
    return np.packbits(bits, bitorder="little").view("<u8")


def _by_row(docs: DataFrame, of_text: Callable[[str | None], np.ndarray], names: tuple[str, ...], also: tuple[str, ...]) -> DataFrame:
    """doc_id, the words of each row's fingerprint as signed longs, and the long columns in `also`."""
    out = ["doc_id", *names, *also]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                fps = np.array([of_text(t) for t in b.column("text").to_pylist()], np.uint64).reshape(-1, len(names)).view(np.int64)
                words = [pa.array(np.ascontiguousarray(fps[:, w])) for w in range(len(names))]
                yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), *words, *(b.column(c) for c in also)], names=out)

    return docs.select("doc_id", "text", *also).mapInArrow(run, ", ".join(f"{n} long" for n in out))


def fingerprints(docs: DataFrame, words_per_shingle: int = 4, also: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long), and the long columns in `also`."""
    return _by_row(docs, lambda t: fingerprint(t, words_per_shingle), ("fp",), also)


def wide_fingerprints(docs: DataFrame, words_per_shingle: int = 5, also: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the columns WIDE, and the long columns in `also`."""
    return _by_row(docs, lambda t: wide_fingerprint(t, words_per_shingle), WIDE, also)


def group_bits(sample: np.ndarray, parts: int) -> list[list[int]]:
    """Equal groups of bits: each grows by the bit most correlated with those it has, on a sample (n, words) of fingerprints."""
    size = sample.shape[1] * WORD
    bits = np.unpackbits(sample.astype("<u8").view(np.uint8).reshape(-1, size // 8), axis=1, bitorder="little").astype(float)
    centred = bits - bits.mean(axis=0) if len(bits) else bits
    spread = np.sqrt((centred**2).sum(axis=0)) + 1e-9
    tie = np.abs(centred.T @ centred) / np.outer(spread, spread)
    free, groups = set(range(size)), []
    for _ in range(parts):
        first = max(free, key=lambda i: (sum(tie[i, j] for j in free), -i))
        group = [first]
        free.remove(first)
        while len(group) < size // parts:
            nxt = max(free, key=lambda i: (sum(tie[i, j] for j in group), -i))
            group.append(nxt)
            free.remove(nxt)
        groups.append(sorted(group))
    return groups


def part_values(fps: np.ndarray, groups: list[list[int]]) -> np.ndarray:
    """(n, parts): the value in each group of bits of each fingerprint (n, words)."""
    u = fps.view(np.uint64)
    out = np.zeros((len(u), len(groups)), np.int64)
    for i, group in enumerate(groups):
        for k, bit in enumerate(group):
            out[:, i] |= ((u[:, bit // WORD] >> np.uint64(bit % WORD)) & np.uint64(1)).astype(np.int64) << k
    return out


def balls(histogram: np.ndarray, most: int) -> np.ndarray:
    """(most + 1, values): rows in the index whose value lies within e bits of v, for e = 0..most."""
    width = len(histogram).bit_length() - 1
    v = np.arange(len(histogram))
    out, shells = [histogram.astype(np.float64)], histogram.astype(np.float64)
    for e in range(1, most + 1):
        shells = sum(histogram[v ^ sum(1 << b for b in bits)] for bits in combinations(range(width), e)).astype(np.float64)
        out.append(out[-1] + shells)
    return np.stack(out)


def allocate(costs: np.ndarray, total: int) -> np.ndarray:
    """costs (n, parts, steps): cost of threshold step - 1. Steps that add up to total, at least cost, by row."""
    n, parts, steps = costs.shape
    best = np.full((n, total + 1), np.inf)
    best[:, 0] = 0
    choice = np.zeros((parts, n, total + 1), np.int8)
    for i in range(parts):
        nxt = np.full_like(best, np.inf)
        for s in range(steps):
            for t in range(s, total + 1):
                c = best[:, t - s] + costs[:, i, s]
                better = c < nxt[:, t]
                nxt[better, t] = c[better]
                choice[i, better, t] = s
        best = nxt
    out, left = np.zeros((n, parts), np.int64), np.full(n, total)
    for i in reversed(range(parts)):
        out[:, i] = choice[i, np.arange(n), left]
        left -= out[:, i]
    return out - 1


def _words(b: pa.RecordBatch, first: int, names: list[str]) -> np.ndarray:
    return np.stack([b.column(first + i).to_numpy(zero_copy_only=False) for i in range(len(names))], axis=1)


def _before(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether a's row comes before b's, by the first word that differs."""
    out = a[:, -1] < b[:, -1]
    for w in reversed(range(a.shape[1] - 1)):
        out = (a[:, w] < b[:, w]) | ((a[:, w] == b[:, w]) & out)
    return out


def links_forest(distinct: DataFrame, radius: int, reach: int | None = None, parts: int | None = None, sample_rows: int = 20_000, most: int = 2, bucket_rows: int = 8_192, probe_cost: float = 3.0) -> DataFrame:
    """distinct(words..., rep) -> (a, b): links between reps that span the components of all pairs within radius bits.

    Four parts a word, unless said otherwise. Beyond radius, pairs within reach bits link if they become candidates.
    """
    spark = distinct.sparkSession
    sc = spark.sparkContext
    names = [c for c in distinct.columns if c != "rep"]
    parts = parts or 4 * len(names)
    limit = radius if reach is None else reach
    width = len(names) * WORD // parts
    sample = np.array(distinct.select(*names).orderBy(F.xxhash64(*names)).limit(sample_rows).collect(), np.int64).reshape(-1, len(names))
    groups = group_bits(sample.view(np.uint64), parts)

    def part_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = part_values(_words(b, 0, names), groups)
            keys = v + (np.arange(parts) << width)
            k, n = np.unique(keys, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(n.astype(np.int64))], names=["k", "n"])

    # exact counts of all fingerprints; at most parts * 2^width rows, whatever the corpus
    counts = np.zeros(parts << width, np.int64)
    for k, n in distinct.select(*names).mapInArrow(part_rows, "k long, n long").groupBy("k").agg(F.sum("n")).collect():
        counts[k] = n
    counts = counts.reshape(parts, -1)
    tables = sc.broadcast(counts)
    flips = [[sum(1 << x for x in bits) for bits in combinations(range(width), e)] for e in range(most + 1)]

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near = [balls(h, most) for h in tables.value]
        sizes = np.cumsum([len(x) for x in flips])
        for big in batches:
            for at in range(0, big.num_rows, 2_000):
                b = big.slice(at, 2_000)
                fps, reps = _words(b, 0, names), b.column(len(names)).to_numpy(zero_copy_only=False)
                mixed = np.zeros(len(fps), np.uint64)
                for w in range(len(names)):
                    mixed = (mixed ^ fps[:, w].view(np.uint64)) * MIX
                v = part_values(fps, groups)
                costs = np.zeros((len(fps), parts, most + 2))
                for i in range(parts):
                    costs[:, i, 1:] = near[i][:, v[:, i]].T + probe_cost * sizes
                thresholds = allocate(costs, radius - parts + 1 + parts)
                rows: list[tuple[np.ndarray, ...]] = []
                for i in range(parts):
                    salts = 1 + tables.value[i] // bucket_rows
                    # each index row in one block of its bucket
                    who = np.arange(len(fps))
                    block = (mixed >> np.uint64(33)).astype(np.int64) % salts[v[:, i]]
                    rows.append((np.full(len(who), i), v[:, i], block, np.zeros(len(who), np.int64), who))
                    for e in range(most + 1):
                        who = np.flatnonzero(thresholds[:, i] >= e)
                        for flip in flips[e]:
                            values = v[who, i] ^ flip
                            hit = tables.value[i][values] > 0
                            # probes in every block of the bucket
                            own = salts[values[hit]]
                            mine, values = np.repeat(who[hit], own), np.repeat(values[hit], own)
                            rows.append((np.full(len(mine), i), values, ranges(np.zeros(len(own), np.int64), own), np.ones(len(mine), np.int64), mine))
                part, value, salt, role, who = (np.concatenate(x).astype(np.int64) for x in zip(*rows))
                key = ((part << width | value) << 20) | salt
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(role.astype(np.int8)), *(pa.array(fps[who, w]) for w in range(len(names))), pa.array(reps[who])], names=["k", "role", *names, "rep"])

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by key, index rows before probes. Only the last bucket's index rows are carried on."""
        carried: tuple[np.ndarray, ...] = (np.zeros(0, np.int64), np.zeros((0, len(names)), np.int64), np.zeros(0, np.int64))
        for b in batches:
            k, role, reps = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1, 2 + len(names)))
            fps = _words(b, 2, names)
            is_index = role == 0
            ik, ifp, irep = (np.concatenate([c, x[is_index]]) for c, x in zip(carried, (k, fps, reps)))
            pk, pfp, prep = (x[~is_index] for x in (k, fps, reps))
            low, high = np.searchsorted(ik, pk, "left"), np.searchsorted(ik, pk, "right")
            todo = high - low
            at, sums = 0, np.cumsum(todo)
            found: list[tuple[np.ndarray, np.ndarray]] = []
            while at < len(pk):
                stop = max(at + 1, int(np.searchsorted(sums, (sums[at - 1] if at else 0) + 2_000_000, "right")))
                mine = ranges(low[at:stop], todo[at:stop])
                whose = np.repeat(np.arange(at, stop), todo[at:stop])
                differ = np.zeros(len(mine), np.uint8)
                for w in range(len(names)):
                    differ += np.bitwise_count((ifp[mine, w] ^ pfp[whose, w]).view(np.uint64))
                near = np.flatnonzero(differ <= limit)
                close = near[_before(ifp[mine[near]], pfp[whose[near]])]
                if len(close):
                    found.append(forest(irep[mine[close]], prep[whose[close]]))
                at = stop
            if found:
                a, c = forest(*(np.concatenate(x) for x in zip(*found)))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(c)], names=["a", "b"])
            last = ik == k[-1]
            carried = ik[last], ifp[last], irep[last]

    rows = distinct.select(*names, "rep").mapInArrow(emit, f"k long, role byte, {', '.join(f'{n} long' for n in names)}, rep long")
    dealt = rows.repartition(exchange_size(spark), "k").sortWithinPartitions("k", "role")
    return dealt.mapInArrow(verify, "a long, b long")


def near_duplicates(docs: DataFrame, radius: int = 4, words_per_shingle: int = 4) -> DataFrame:
    """doc_id, fp, component_id (the smallest doc_id that links lead to, itself included), one row per row of docs."""
    fps = materialize(fingerprints(docs, words_per_shingle), "fingerprints")
    distinct = materialize(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")), "distinct-fingerprints")
    comp = connected_components(links_forest(distinct, radius))
    labels = distinct.join(comp, distinct.rep == comp.node, "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return fps.join(labels, "fp", "left").select("doc_id", "fp", "component_id")


def first_of_groups(docs: DataFrame, radius: int = 15, reach: int = 22, words_per_shingle: int = 5) -> DataFrame:
    """doc_id, ROW, rows: of each group of linked texts the first key (doc_id, nulls last, then fingerprint and ROW) and its rows.

    docs has the column ROW beside doc_id and text. Fingerprints are the nodes, so repeated and null ids join no groups.
    Sets of shingles with a Jaccard similarity s differ in a share acos(2s / (1 + s)) / pi of the 128 bits if they are
    of one size: 19.4 bits at 0.8, with a deviation of 4; unrelated texts differ in 64 with a deviation of 5.7.
    """
    fps = materialize(wide_fingerprints(docs, words_per_shingle, (ROW,)), "fingerprints")
    keys = fps.groupBy("doc_id", *WIDE, ROW).agg(F.count("*").alias("rows"))
    distinct = materialize(fps.select(*WIDE).distinct().withColumn("rep", F.monotonically_increasing_id()), "distinct-fingerprints")
    comp = connected_components(links_forest(distinct, radius, reach))
    groups = distinct.join(comp, distinct.rep == comp.node, "left").select(*WIDE, F.coalesce("component", "rep").alias("group"))
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", *WIDE, ROW, "rows")
    first = keys.join(groups, list(WIDE)).groupBy("group").agg(F.min(order).alias("first"))
    return first.select("first.doc_id", f"first.{ROW}", "first.rows")
