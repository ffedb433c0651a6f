"""From raw documents to packed sequences: quality, language, near-duplicates, packing.

Each stage takes (spark, docs, sf_dir), where docs has the columns of `documents`, and works on every row that its
predecessor kept. run() writes each stage's rows as Parquet in the shared folder and reads them again.

Odd rows: null and empty texts are scored like any other by the first stage, have no language and go in the second.
Repeated rows are near-duplicates of each other, so one stays. Texts of any length are seen whole. Other columns are
passed on, whatever they are called; packing returns its own. Empty tables give an empty result. Where labels teach
only one kind, or no text has a lang, the stages without a model keep every text, or every text with a letter.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmask.llm import language_id, packing, quality, simhash
from gridmask.llm.shared import materialize, table
from gridmask.llm.tokens import tokenizer_path


def by_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below the classifier's threshold go."""
    labels = table(spark, sf_dir, "labels").where(~F.coalesce(quality.in_held_out_fold(), F.lit(False)))
    return quality.good_quality(docs, quality.train(docs, labels))


def by_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language go: no letter, letters that no taught text has, or no language that the network gives
    more than all others together."""
    taught = docs.where(~F.coalesce(language_id.in_held_out_fold(), F.lit(False)))
    return language_id.known_language(docs, language_id.train(taught))


def without_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of rows with near-duplicate texts one stays: of the smallest doc_id, or without one if none has any.

    Texts are near-duplicates at an estimated similarity of 0.8 or more of their sets of five-word shingles.

    Rows are told apart by doc_id and a hash of all columns, so rows that share a doc_id but no text are judged apart.
    """
    columns = [x for c in docs.columns for x in (F.col(c), F.col(c).isNull())]
    keyed = docs.withColumn(simhash.ROW, F.xxhash64(*columns))
    first = materialize(simhash.first_of_groups(keyed), "first-of-groups").withColumnRenamed("doc_id", "first_id")

    def of(some: DataFrame) -> DataFrame:
        return keyed.join(some, keyed.doc_id.eqNullSafe(some.first_id) & (keyed[simhash.ROW] == some[simhash.ROW]), "left_semi")

    # rows of one key are equal in every column
    repeated = of(first.where("rows > 1")).dropDuplicates(["doc_id", simhash.ROW])
    return of(first.where("rows = 1")).unionByName(repeated).drop(simhash.ROW)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents that are left, in sequences of at most 4096 tokens."""
    return packing.pack(docs, tokenizer_path("word_bpe_49k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_classifier", by_quality),
    ("language_id", by_language),
    ("simhash_near_dedup", without_near_duplicates),
    ("packing", packed),
]

#: Learned classifiers and tokenizers are beyond SQL; tests/llm/test_learned.py holds the rows against plain code.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        rows = materialize(stage(spark, rows, sf_dir), name)
    return rows
