"""Document quality by a byte convolutional network over overlapping chunks of the whole text.

Chunks overlap by the widest filter less one, so that every filter position is seen. A chunk's max-pooled filter
responses become hidden features; a document's largest and mean features become one probability of label 1. The
network learns from about `per_class` labelled texts of each label, drawn by a hash of the id.

Null counts as an empty text, and empty texts get a score too. Repeated rows are scored each. Without labels of both
kinds every score is 0.5. Other columns are passed by; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .byte_conv import ByteConv
from .language_id import TAUGHT_CHARS, sample_by_class
from .shared import bucket_of_id

THRESHOLD = 0.3


def train(docs: DataFrame, labels: DataFrame, per_class: int = 1_500, epochs: int = 8) -> ByteConv | None:
    """labels(doc_id, quality); rows whose label is null or not 0 or 1 teach nothing."""
    marked = labels.where(F.col("quality").isin(0, 1)).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    picked = sample_by_class(marked, "quality", per_class)
    # at most 4 * per_class ids are broadcast; an id whose text repeats teaches once by each text, most of them bounded
    texts_ = docs.select("doc_id", F.substring("text", 1, TAUGHT_CHARS).alias("text")).join(F.broadcast(picked), "doc_id")
    rows = texts_.distinct().orderBy(F.xxhash64("doc_id", "text"), "doc_id", "text").limit(8 * per_class).orderBy("doc_id", "text").collect()
    if len({r.quality for r in rows}) < 2:
        return None
    texts, y = [r.text or "" for r in rows], [r.quality for r in rows]
    # short good texts are rare among labels: every third good text teaches again by its beginning
    rng = np.random.default_rng(3)
    short = [t[: int(n)] for t, n in zip((t for t, q in zip(texts, y) if q == 1), rng.integers(8, 250, len(texts)))][::3]
    texts, y = texts + short, np.array(y + [1] * len(short), np.int64)
    net = ByteConv(2, window=256, filters=8, hidden=16)
    weights = (0.5 / np.bincount(y))[y] * len(y)
    net.fit([t.encode("utf-8", "surrogatepass") for t in texts], y, weights, epochs=epochs)
    return net


def score_texts(net: ByteConv | None, texts: list[str | None]) -> np.ndarray:
    if net is None:
        return np.full(len(texts), 0.5)
    return np.clip(net.predict([(t or "").encode("utf-8", "surrogatepass") for t in texts])[:, 1], 0, 1) if texts else np.zeros(0)


def score(docs: DataFrame, net: ByteConv | None) -> DataFrame:
    """doc_id, score."""
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(score_texts(shared.value, b.column("text").to_pylist()), pa.float64())], names=["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")


def in_held_out_fold() -> F.Column:
    return bucket_of_id("doc_id", 5) == 0


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Learn from labels that are not held out; doc_id, held_out, score, predicted for all rows of docs."""
    held_out = F.coalesce(in_held_out_fold(), F.lit(False))
    net = train(docs, labels.where(~held_out))
    return score(docs, net).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def good_quality(docs: DataFrame, net: ByteConv | None, threshold: float = THRESHOLD) -> DataFrame:
    """Filter: the rows that score at least threshold; columns as they were."""
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                yield b.filter(pa.array(score_texts(shared.value, b.column("text").to_pylist()) >= threshold))

    return docs.mapInArrow(run, docs.schema)
