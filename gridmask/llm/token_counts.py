"""Token counts of whole texts: a broadcast table of frequent pieces first, a worker's cache for the rest.

Tier 1 is a table piece -> number of tokens, bounded by ``table_size`` entries of at most ``MOST_CHARS`` characters and
broadcast as one string of pieces and one byte a length. Its pieces are the commonest of about ``sample_docs`` texts
drawn at random over the whole table, counted in the tasks that read them. Tier 2 is the worker's cache, filled by the
tokenizer library. Neither shuffles pre-tokens of the corpus, and neither changes a result: what the table lacks is
encoded. Null and empty texts have 0 bytes and 0 tokens; repeated rows are kept; other columns are passed by. An empty
table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import CachedEncoder, encoder

SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"
#: Longer pieces are left to the second tier.
MOST_CHARS = 64


def frequent_pieces(docs: DataFrame, path: str, table_size: int, sample_docs: int, seed: int = 11) -> list[str]:
    """The commonest pieces of a random sample of all rows, by descending count."""
    total = docs.count()
    if not total:
        return []

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, seen = encoder(path, 1_000_001), Counter()

        def flush() -> pa.RecordBatch:
            b = pa.RecordBatch.from_arrays([pa.array(seen.keys(), pa.string()), pa.array(seen.values(), pa.int64())], names=["piece", "n"])
            seen.clear()
            return b

        for b in batches:
            for text in b.column("text").to_pylist():
                # the first piece has no blank in front
                seen.update(p for p in (enc._pieces(text) or [])[1:] if len(p) <= MOST_CHARS)
                if len(seen) > 4 * table_size:
                    yield flush()
        if seen:
            yield flush()

    drawn = docs.select("text").where(F.col("text").isNotNull() & (F.rand(seed) < min(1.0, sample_docs / total)))
    counted = drawn.mapInArrow(pieces, "piece string, n long").groupBy("piece").agg(F.sum("n").alias("n"))
    return [r["piece"] for r in counted.orderBy(F.desc("n"), "piece").limit(table_size).collect()]


def frequent_lengths(docs: DataFrame, path: str, table_size: int = 65_536, sample_docs: int = 1_500) -> tuple[str, bytes]:
    """The pieces, joined by blanks (no piece has one), and their numbers of tokens; pieces of more than 255 are out."""
    enc = CachedEncoder(path)
    pieces = frequent_pieces(docs, path, table_size, sample_docs)
    blank = " " if enc.keeps_blank else ""  # a piece's tokens include the blank in front of it
    lengths = [len(e.ids) for e in enc.library.encode_batch_fast([blank + p for p in pieces], add_special_tokens=False)]
    kept = [(p, n) for p, n in zip(pieces, lengths) if n < 256 and " " not in p]
    return " ".join(p for p, _ in kept), bytes(n for _, n in kept)


def count_tokens(docs: DataFrame, path: str, limit: int = 512, table_size: int = 65_536, sample_docs: int = 1_500) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit (n_tokens > limit) for every row of docs(doc_id, text)."""
    table = docs.sparkSession.sparkContext.broadcast(frequent_lengths(docs, path, table_size, sample_docs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # one encoder for counting in each worker and table
        enc = encoder(path, 1_000_001)
        if not enc._seeded:
            names, lengths = table.value
            # an empty piece (between two blanks) is told by the length alone
            enc.seed(dict(zip(names.split(" "), np.frombuffer(lengths, np.uint8).tolist())) if lengths else {})
        for b in batches:
            texts = [t or "" for t in b.column("text").to_pylist()]
            n = enc.count_many(texts)
            sizes = [len(t.encode("utf-8", "surrogatepass")) for t in texts]
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(sizes, pa.int64()), pa.array(n, pa.int64()), pa.array(n > limit)], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)
