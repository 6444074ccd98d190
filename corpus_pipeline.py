"""Corpus pipeline: language ID, quality classifier, exact dedup, SimHash near-dedup, best-fit packing.

Each stage gets what the one before it kept, as `documents` rows, and its decisions take effect. Columns beyond those of
documents are left out. Null and empty texts have no letter and go in the first stage; labels that are null teach nothing. Of
repeated rows exact dedup keeps one. A row without a doc_id can be named by no class of near copies and stays in that stage; rows that
share a doc_id but not their text stay or go together there. Empty tables give empty results. Whole texts count, however long.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepsql.llm import exact, langid, packing, quality, simhash
from stepsql.llm.common import pick, read, written

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: No SQL: two stages score with models that are trained here, and the last one tokenises.
ORACLE_SQL = None


def _keep(docs: DataFrame, decisions: DataFrame) -> DataFrame:
    """Rows of docs whose doc_id is among the decisions' (one column, distinct), and those without one."""
    docs = pick(docs, *COLUMNS)
    return docs.join(decisions, "doc_id", "left_semi").select(*COLUMNS).union(docs.where("doc_id is null"))


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is told with enough confidence; the rest, and texts without a letter, go."""
    model = langid.fit(docs)
    return langid.keep(pick(docs, *COLUMNS), model)


def classify_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality model accepts."""
    model = quality.fit(docs, read(spark, sf_dir, "labels"))
    return quality.keep(pick(docs, *COLUMNS), model)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id."""
    return exact.keep(pick(docs, *COLUMNS))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one with the smallest doc_id."""
    found = simhash.components(docs).where("doc_id = component_id").select("doc_id").distinct()
    return _keep(docs, found)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 2048 tokens, as rows of pieces."""
    return packing.pack(docs)


STAGES = [
    ("language_id", identify_language),
    ("quality_classifier", classify_quality),
    ("exact_dedup", drop_copies),
    ("simhash_near_dedup", drop_near_copies),
    ("best_fit_packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = read(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
