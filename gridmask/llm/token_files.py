"""Token ids on disk as directly addressable codes.

A segment holds the ids of consecutive documents. An id is cut into 8-bit chunks, lowest first; level k keeps
the k-th chunks of the ids that have one, and a bitmap of level k tells which of them go on at level k + 1.
A rank directory (ones before each 512-bit block) turns a position at one level into the position at the next,
so any token is found from its number alone, without decoding its neighbours.

Layout of a segment, little-endian: magic "DAC1", uint32 levels, uint64 documents, uint64 tokens, then the
documents' first positions (uint64 each, and the end); for every level uint64 entries, the chunks (uint8), and,
but for the last level, the bitmap (uint64 words) and the directory (uint32 by block). Parts start at multiples
of 8 bytes.

The segments of a corpus are rows of a Parquet table in ascending (part, segment) order, so that any store that
Spark writes to can hold them and a lost task leaves no partial file behind.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import exchange_size
from .tokens import encoder

BLOCK_WORDS = 8
MAGIC = b"DAC1"


def _padded(b: bytes) -> bytes:
    return b + b"\0" * (-len(b) % 8)


def encode_segment(ids: np.ndarray, first: np.ndarray) -> bytes:
    """ids: all tokens; first: position of each document's first token, and the end."""
    out = [first.astype("<u8").tobytes()]
    rest, levels = ids.astype(np.uint32), 0
    while True:
        on = rest > 0xFF
        last = not on.any()
        out += [struct.pack("<Q", len(rest)), _padded((rest & 0xFF).astype(np.uint8).tobytes())]
        levels += 1
        if last:
            break
        bits = np.packbits(on, bitorder="little")
        words = np.frombuffer(_padded(bits.tobytes()), "<u8")
        ones = np.concatenate([[0], np.cumsum(np.bitwise_count(words), dtype=np.int64)])
        out += [words.tobytes(), _padded(ones[: len(words) : BLOCK_WORDS].astype("<u4").tobytes())]
        rest = rest[on] >> 8
    return MAGIC + struct.pack("<IQQ", levels, len(first) - 1, len(ids)) + b"".join(out)


class Segment:
    """Reads a segment; nothing is decoded before it is asked for."""

    def __init__(self, data: bytes) -> None:
        if data[:4] != MAGIC:
            raise ValueError("not a token segment")
        levels, self.n_docs, self.n_tokens = struct.unpack_from("<IQQ", data, 4)
        at = 24
        self.first = np.frombuffer(data, "<u8", self.n_docs + 1, at).astype(np.int64)
        at += 8 * (self.n_docs + 1)
        self.levels: list[tuple[np.ndarray, np.ndarray | None, np.ndarray | None]] = []
        for k in range(levels):
            (n,) = struct.unpack_from("<Q", data, at)
            chunks = np.frombuffer(data, np.uint8, n, at + 8)
            at += 8 + n + -n % 8
            words = ranks = None
            if k < levels - 1:
                n_words = -(-n // 64)
                words = np.frombuffer(data, "<u8", n_words, at)
                at += 8 * n_words
                n_blocks = -(-n_words // BLOCK_WORDS)
                ranks = np.frombuffer(data, "<u4", n_blocks, at)
                at += 4 * n_blocks + -(4 * n_blocks) % 8
            self.levels.append((chunks, words, ranks))

    @staticmethod
    def _rank(words: np.ndarray, ranks: np.ndarray, i: int) -> int:
        """Ones before bit i."""
        w = i >> 6
        block = w // BLOCK_WORDS
        n = int(ranks[block]) + int(np.bitwise_count(words[block * BLOCK_WORDS : w]).sum())
        return n + (int(words[w]) & ((1 << (i & 63)) - 1)).bit_count()

    def token(self, i: int) -> int:
        """The i-th token."""
        value = shift = 0
        for chunks, words, ranks in self.levels:
            value |= int(chunks[i]) << shift
            shift += 8
            if words is None or not int(words[i >> 6]) >> (i & 63) & 1:
                break
            i = self._rank(words, ranks, i)
        return value

    def slice(self, start: int, stop: int) -> np.ndarray:
        """Tokens start..stop, level by level."""
        out = np.zeros(stop - start, np.uint32)
        if start >= stop:
            return out
        where, shift = np.arange(stop - start), 0
        for chunks, words, ranks in self.levels:
            out[where] |= chunks[start:stop].astype(np.uint32) << shift
            shift += 8
            if words is None:
                break
            w = start >> 6
            bits = np.unpackbits(words[w : ((stop - 1) >> 6) + 1].view(np.uint8), bitorder="little")[start - 64 * w :][: stop - start]
            on = bits.astype(bool)
            if not on.any():
                break
            where, start = where[on], self._rank(words, ranks, start)
            stop = start + len(where)
        return out

    def document(self, k: int) -> np.ndarray:
        return self.slice(int(self.first[k]), int(self.first[k + 1]))


SEGMENT_SCHEMA = "part int, segment int, before long, n_tokens long, doc_ids array<long>, payload binary"


def write_token_files(docs: DataFrame, path: str, to: str, end_id: int | None = 2, segment_tokens: int = 1_000_000) -> None:
    """Encode docs(doc_id, text) in ascending doc_id order (nulls first, ties by text) into segments under `to`.

    Null text counts as empty; each document's ids are followed by end_id. Memory is bounded by segment_tokens
    and the longest text. Documents are dealt to parts by ranges of doc_id.
    """
    n = exchange_size(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, segment, before = encoder(path), TaskContext.get().partitionId(), 0, 0
        held: list[tuple[np.ndarray, np.ndarray]] = []
        doc_ids: list[int | None] = []

        def flush() -> pa.RecordBatch:
            nonlocal segment, before, held, doc_ids
            ids, sizes = (np.concatenate(x) for x in zip(*held))
            first = np.concatenate([[0], np.cumsum(sizes)])
            row = [[part], [segment], [before], [len(ids)], [doc_ids], [encode_segment(ids, first)]]
            segment, before, held, doc_ids = segment + 1, before + len(ids), [], []
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary()))], names=["part", "segment", "before", "n_tokens", "doc_ids", "payload"])

        total = 0
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                ids, sizes = enc.encode_many([t or "" for t in b.column("text").to_pylist()])
                if end_id is not None:
                    ids = np.insert(ids, np.cumsum(sizes), end_id)
                    sizes = sizes + 1
                held.append((ids, sizes))
                doc_ids += b.column("doc_id").cast(pa.int64()).to_pylist()
                total += len(ids)
                if total >= segment_tokens:
                    yield flush()
                    total = 0
        if held:
            yield flush()

    ordered = docs.select("doc_id", "text").repartitionByRange(n, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    ordered.mapInArrow(run, SEGMENT_SCHEMA).write.parquet(to)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start (tokens of all documents before it), n_tokens, ids_crc32, one row per document, from the files."""
    rows = spark.read.schema(SEGMENT_SCHEMA).parquet(path)
    # one total for each part: as many rows as the write had tasks
    totals = sorted((r["part"], r["n"]) for r in rows.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect())
    bases = dict(zip((p for p, _ in totals), np.concatenate([[0], np.cumsum([n for _, n in totals])]).tolist()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part, before, doc_ids, payload in zip(*(b.column(c).to_pylist() for c in ("part", "before", "doc_ids", "payload"))):
                seg = Segment(payload)
                sizes, flat = np.diff(seg.first), seg.slice(0, seg.n_tokens).astype("<u4")
                sums = [zlib.crc32(flat[i:j]) for i, j in zip(seg.first[:-1].tolist(), seg.first[1:].tolist())]
                start = bases[part] + before + seg.first[:-1]
                yield pa.RecordBatch.from_arrays([pa.array(doc_ids, pa.int64()), pa.array(start, pa.int64()), pa.array(sizes, pa.int64()), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return rows.select("part", "before", "doc_ids", "payload").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")
