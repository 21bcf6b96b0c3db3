"""A corpus pipeline of five stages: repetition rules, near-duplicates, decontamination, pseudonyms, packing.

Each stage takes (spark, docs, sf_dir), docs being a written table of doc_id and text with any further columns, and
returns all its rows as a DataFrame; the caller writes them before it calls the next stage, as `run` does.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from hyperslab.llm import common, decontam, neardup, pii, queries, repetition
from hyperslab.shipping import ship

_scratch: list[str] = []  # tables that near_duplicates made and its written result no longer needs


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that pass the repetition rules, with all their columns.

    Cases: a null or empty text, or one of fewer than ten words, goes; null and repeated ids and equal rows are judged
    row by row; very long texts are read whole; no documents give none; other columns are kept, whatever their names.
    """
    ship(spark)
    return repetition.kept_rows(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: that of the least id, with all its columns.

    Cases: null and empty texts are near-duplicates of nothing and stay; rows of one id are one document, of which the
    row with the most shingles stays; rows without an id are judged like others and stay if no row with an id is in
    their group; of equal rows one stays; no documents give none; other columns are kept, whatever their names.
    """
    ship(spark)
    before = common.made()
    out = neardup.deduplicated(docs)
    _scratch.extend(common.made_since(before))
    return out


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that repeat no benchmark item, with all their columns.

    Cases: null and empty texts stay; ids play no part; equal rows go or stay together; a text shorter than an item is
    compared whole; an empty benchmark keeps all; no documents give none; other columns are kept, whatever their names.
    """
    ship(spark)
    common.remove(_scratch)  # docs is written
    return decontam.clean_rows(docs, queries.table(spark, sf_dir, "benchmark"))


def pseudonyms(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data in their texts replaced.

    Cases: a null text stays null and an empty one empty; ids play no part; equal values become equal pseudonyms in all
    rows; no documents give none; other columns are kept as they are, whatever their names.
    """
    return pii.pseudonymised(docs, queries.PSEUDONYM_KEY)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their token ids and their places in sequences.

    Cases: a null or empty text is its end id alone; null and repeated ids and equal rows are pieces of their own; long
    documents are cut into sequences; no documents give no pieces; other columns are left out.
    """
    ship(spark)
    return queries.packed_digests(docs, with_ids=True)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("pseudonyms", pseudonyms),
    ("packing", packing),
]

#: SQL has no tokenizer and no linear program: tests/llm/ holds run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each one's rows written and read again; a stage's table goes once the next is written."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, stage in STAGES:
        path = f"{common.shared_folder(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        common.remove(before)
        before = [path]
    return docs
