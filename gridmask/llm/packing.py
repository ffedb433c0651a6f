"""Order-preserving packing: a dynamic programme chooses where token windows are cut.

Documents of a partition, in the order read, form one stream of ids. A window of at most `size` ids may end at
the end of a document, at the end of a sentence, or, dearer, inside a sentence. Cost of a window: its padding
plus the penalty of the cut that ends it. With cut positions p and penalties c, the least cost D of a prefix is

    D[j] = c[j] + size - p[j] + min over i with p[j] - p[i] <= size of (D[i] + p[i])

so the minimum slides over a window of candidates and a monotone queue keeps it, in time linear in the cuts.
A window whose length is a power of two needs no padding; that matters for a stream's tail, where every
position is a candidate and those lengths are tried as well.

Null and empty texts become a document of the end id alone. Repeated rows are packed each. Ties go to the
earlier cut. An empty table gives no pieces. No id is dropped or repeated.
"""

from __future__ import annotations

import re
import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .tokens import CachedEncoder, encoder

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
SENTENCE_COST, INSIDE_COST = 0.5, 4.0
#: Sentence ends nearer than this to the one before are no candidates; inside longer sentences, one candidate each.
SPACING, FALLBACK = 16, 24


def choose_cuts(positions: np.ndarray, penalties: np.ndarray, size: int, exact: bool = False, open_end: bool = False) -> list[int]:
    """Ends of the windows of least cost over the stream [0, positions[-1]); positions ascend, gaps at most size.

    exact: lengths that are powers of two cost no padding (for short streams; 12 more transitions a cut).
    open_end: the last window costs nothing, as what follows decides about it.
    """
    p, c = positions.tolist(), penalties.tolist()
    cost, back = [0.0], [-1]
    at = [0, *p]
    keys: deque[tuple[float, int]] = deque([(0.0, 0)])
    place = {x: i for i, x in enumerate(at)} if exact else {}
    powers = [1 << k for k in range(size.bit_length()) if 1 << k <= size] if exact else []
    for j, (pos, pen) in enumerate(zip(p, c), 1):
        low = pos - size
        while at[keys[0][1]] < low:
            keys.popleft()
        best, i = keys[0]
        best += pen + size - pos
        if open_end and j == len(p):
            best, i = min((cost[k], k) for k in range(j) if at[k] >= low)
        for w in powers:
            k = place.get(pos - w)
            if k is not None and cost[k] + pen < best:
                best, i = cost[k] + pen, k
        cost.append(best)
        back.append(i)
        key = best + pos
        while keys and keys[-1][0] > key:
            keys.pop()
        keys.append((key, j))
    ends, j = [], len(p)
    while j > 0:
        ends.append(at[j])
        j = back[j]
    return ends[::-1]


def candidates(doc_ends: np.ndarray, sentence_ends: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Cut positions over n ids and their penalties."""
    thin = sentence_ends[np.flatnonzero(np.diff(sentence_ends // SPACING, append=-1))] if len(sentence_ends) else sentence_ends
    known = np.union1d(thin, doc_ends)
    gaps = np.diff(known, prepend=0)
    long = np.flatnonzero(gaps > 2 * FALLBACK)
    inside = [np.arange(known[k] - gaps[k] + FALLBACK, known[k], FALLBACK) for k in long]
    if n - (known[-1] if len(known) else 0) > 2 * FALLBACK:
        inside.append(np.arange((known[-1] if len(known) else 0) + FALLBACK, n, FALLBACK))
    positions = np.unique(np.concatenate([known, *inside, [n]])).astype(np.int64)
    penalties = np.full(len(positions), INSIDE_COST)
    penalties[np.isin(positions, thin, assume_unique=True)] = SENTENCE_COST
    penalties[np.isin(positions, doc_ends)] = 0.0
    return positions, penalties


class Packer:
    """Feeds on encoded documents, gives windows as pieces. Holds at most `horizon` ids and one document."""

    def __init__(self, size: int, ends_sentence: np.ndarray, horizon: int) -> None:
        self.size, self.ends_sentence, self.horizon = size, ends_sentence, horizon
        self.ids = np.zeros(0, np.int32)
        self.parts: list[np.ndarray] = []
        self.docs: list[tuple[int | None, int, int, int]] = []  # id, ids of it that are gone, ids here, all its ids
        self.held = 0
        self.sequence = 0

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.parts.append(ids)
        self.docs.append((doc_id, 0, len(ids), len(ids)))
        self.held += len(ids)

    def windows(self, last: bool) -> Iterator[tuple]:
        if self.held < self.horizon and not last or not self.held:
            return
        ids = np.concatenate([self.ids, *self.parts])
        doc_ends = np.cumsum([d[2] for d in self.docs])
        sentence_ends = np.flatnonzero(self.ends_sentence[ids]) + 1
        n = len(ids)
        tail = n if n > self.size else 0 if last else n
        positions, penalties = candidates(doc_ends[doc_ends <= tail], sentence_ends[sentence_ends <= tail], tail) if tail else (np.zeros(0, np.int64), np.zeros(0))
        ends = choose_cuts(positions, penalties, self.size, open_end=True) if tail else []
        if last:
            # what the open last window holds is cut anew: every position in it may be a cut
            ends = ends[:-1]
            start = ends[-1] if ends else 0
            rest = np.arange(start + 1, n + 1)
            cost = np.full(len(rest), INSIDE_COST)
            cost[np.isin(rest, sentence_ends)] = SENTENCE_COST
            cost[np.isin(rest, doc_ends)] = 0.0
            ends += [start + e for e in choose_cuts(rest - start, cost, self.size, exact=True)]
        else:
            ends = ends[:-3]  # the last ones would be chosen without what follows
        yield from self._emit(ids, ends)
        done = ends[-1] if ends else 0
        self.ids, self.parts, self.held = ids[done:], [], n - done

    def _emit(self, ids: np.ndarray, ends: list[int]) -> Iterator[tuple]:
        docs, k, begin = self.docs, 0, 0
        gone, here = docs[0][1], docs[0][2]
        for end in ends:
            offset = 0
            while begin < end:
                while here == 0:
                    k += 1
                    gone, here = docs[k][1], docs[k][2]
                n = min(here, end - begin)
                yield docs[k][0], gone, n, zlib.crc32(ids[begin : begin + n]), docs[k][3], self.sequence, offset
                begin, offset, gone, here = begin + n, offset + n, gone + n, here - n
            self.sequence += 1
        self.docs = [(docs[k][0], gone, here, docs[k][3]), *docs[k + 1 :]] if here or k + 1 < len(docs) else []


def sentence_end_ids(enc: CachedEncoder) -> np.ndarray:
    """By id: does the token close a sentence?"""
    names = [enc.library.id_to_token(i) or "" for i in range(enc.library.get_vocab_size())]
    return np.array([bool(re.fullmatch(r"[^\w\s]*[.!?][^\w\s]*(</w>)?", n.strip("ĠĊ"))) and not n.startswith("<|") for n in names])


def pack(docs: DataFrame, path: str, size: int = 4096, end_id: int | None = 2, horizon: int = 600_000, cached_pieces: int = 400_000) -> DataFrame:
    """Pieces of documents in sequences of at most `size` ids; sequence_id is unique over all partitions.

    No shuffle: each input partition is a stream of its own, and the same split gives the same windows again.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, cached_pieces)
        if not hasattr(enc, "sentence_ends"):
            enc.sentence_ends = sentence_end_ids(enc)
        packer, base = Packer(size, enc.sentence_ends, horizon), TaskContext.get().partitionId() << 40

        def batch(rows: list[tuple]) -> pa.RecordBatch:
            cols = list(zip(*rows))
            cols[5] = [base + s for s in cols[5]]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=[x.split()[0] for x in SCHEMA.split(", ")])

        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                ids, sizes = enc.encode_many([t or "" for t in b.column("text").to_pylist()])
                if end_id is not None:
                    ids, sizes = np.insert(ids, np.cumsum(sizes), end_id), sizes + 1
                for doc_id, one in zip(b.column("doc_id").cast(pa.int64()).to_pylist(), np.split(ids, np.cumsum(sizes)[:-1])):
                    packer.add(doc_id, one)
                if rows := list(packer.windows(False)):
                    yield batch(rows)
        if rows := list(packer.windows(True)):
            yield batch(rows)

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)
