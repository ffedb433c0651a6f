"""Language identification by a byte convolutional network over batched fixed-length windows.

The network learns from a bounded sample of labelled texts: about `per_language` of each language, drawn by a hash of
the id, so the sample is the same in every run. It then sees every window of every text. Texts that are null or have
no letter are `und` with score 0. Repeated rows are predicted each; ties go to the language first in order; languages
without a sampled text are not predicted. With no labelled text at all, every text is `und`. Other columns are
passed by; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .byte_conv import ByteConv
from .shared import bucket_of_id

UNKNOWN = "und"
#: A sampled text teaches by at most its first so many characters, which bounds what the driver holds.
TAUGHT_CHARS = 200_000


def has_letter(text: str | None) -> bool:
    """Whether any character is a letter; signs for numbers, such as fractions and circled digits, are none."""
    return text is not None and any(map(str.isalpha, text))


def sample_by_class(rows: DataFrame, label: str, per_class: int) -> DataFrame:
    """About per_class rows of each class, by a hash of doc_id; a class with fewer rows is taken whole. At most
    2 * per_class rows a class in all, however often an id repeats."""
    known = rows.where(F.col(label).isNotNull())
    counts = {r[0]: r[1] for r in known.groupBy(label).count().collect()}
    if not counts:
        return rows.limit(0)
    share = F.create_map(*[F.lit(x) for k, n in counts.items() for x in (k, min(1.0, per_class / n))])
    picked = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share[F.col(label)] * (1 << 20))
    # an id that repeats is picked with all its rows: of those, the hash of the whole row decides
    return picked.orderBy(F.xxhash64(*rows.columns), *rows.columns).limit(2 * per_class * len(counts))


def letters_of(texts: list[str]) -> frozenset[str]:
    """The letters that occur, in lower case."""
    return frozenset(c for c in set().union(*(t.lower() for t in texts)) if c.isalpha())


class LanguageModel:
    """letters: those of the taught texts; none: any letter counts as taught."""

    def __init__(self, languages: list[str], net: ByteConv | None, letters: frozenset[str] = frozenset()) -> None:
        self.languages, self.net, self.letters = languages, net, letters

    def taught_share(self, text: str) -> float:
        """Share of the text's letters that occur in taught texts."""
        lower = text.lower()
        if not self.letters or not any(c.isalpha() for c in set(lower) - self.letters):
            return 1.0
        counts = {c: n for c, n in Counter(lower).items() if c.isalpha()}
        return sum(n for c, n in counts.items() if c in self.letters) / sum(counts.values())

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        names, scores = [UNKNOWN] * len(texts), np.zeros(len(texts))
        told = [i for i, t in enumerate(texts) if has_letter(t)]
        if told and self.net is not None:
            p = self.net.predict([texts[i].lower().encode("utf-8", "surrogatepass") for i in told])
            best = p.argmax(axis=1)
            for i, k in zip(told, best.tolist()):
                names[i] = self.languages[k]
            scores[told] = np.clip(p[np.arange(len(told)), best], 0, 1)
        return names, scores


def train(docs: DataFrame, per_language: int = 500, epochs: int = 6) -> LanguageModel:
    """docs(doc_id, text, lang): only rows with a lang and a text teach."""
    told = docs.where(F.col("text").isNotNull()).select("doc_id", F.substring("text", 1, TAUGHT_CHARS).alias("text"), "lang")
    rows = sample_by_class(told, "lang", per_language).orderBy("doc_id", "text").collect()
    rows = [r for r in rows if has_letter(r.text)]
    languages = sorted({r.lang for r in rows})
    if not languages:
        return LanguageModel([], None)
    y = np.array([languages.index(r.lang) for r in rows])
    weights = 1 / np.bincount(y)[y]
    net = ByteConv(len(languages), window=160, filters=8, hidden=16)
    net.fit([r.text.lower().encode("utf-8", "surrogatepass") for r in rows], y, weights * len(y) / len(languages), epochs=epochs)
    return LanguageModel(languages, net, letters_of([r.text for r in rows]))


def predict(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                names, scores = shared.value.predict(b.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def in_held_out_fold() -> F.Column:
    return bucket_of_id("doc_id", 3) == 1


def identify(docs: DataFrame) -> DataFrame:
    """Learn from the rows that are not held out; doc_id, held_out, lang_pred, score for all."""
    model = train(docs.where(~F.coalesce(in_held_out_fold(), F.lit(False))))
    return predict(docs, model).select("doc_id", F.coalesce(in_held_out_fold(), F.lit(False)).alias("held_out"), "lang_pred", "score")


#: The network knows no language but the learned ones and divides every text among them. A text is in one of them where
#: this one has more than all others together.
MAJORITY = 0.5


def known_language(docs: DataFrame, model: LanguageModel, floor: float | None = None, languages: tuple[str, ...] | None = None) -> DataFrame:
    """Filter: the rows whose text has a letter and a language, at a score of at least floor; columns as they were.

    The score here is the network's times the share of the text's letters that taught texts have, so that a text in another
    script, which the network may well take for a language of its own, has no language. floor None: MAJORITY. languages:
    only these stay (None: every learned one). A model without languages has no ground to reject a text with letters.
    """
    least = MAJORITY if floor is None else floor
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 500):
                b = big.slice(at, 500)
                texts = b.column("text").to_pylist()
                if shared.value.net is None:
                    keep = [has_letter(t) for t in texts]
                else:
                    keep = [n != UNKNOWN and bool(s * shared.value.taught_share(t) >= least) and (languages is None or n in languages) for t, n, s in zip(texts, *shared.value.predict(texts))]
                yield b.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
