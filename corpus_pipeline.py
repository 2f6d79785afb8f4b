"""documents -> windows: language, near duplicates, source mixture, packing; each stage reads what its predecessor kept.

All stages but the last return rows of ``docs`` unchanged, with its columns in their order, whatever further columns it has. An empty
table gives an empty result of the same columns at every stage. Texts are read whole, however long.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from catalogflow.llm import language, mixing, neardup, packing
from catalogflow.session import ship, staged, table


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text has an identifiable language; those without words or mostly of no known language go.

    So null and empty texts and texts of digits and signs go. A null ``lang`` doesn't train, but its row is judged like any other; where
    no row has a ``lang``, all go. Null ids and null sources stay. Repeated rows are judged each, alike. Ties between languages don't
    matter here: only rejection does.
    """
    ship(spark)
    return language.identify(docs, language.fit(docs), keep=docs.columns, accepted_only=True)


def deduplicated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest id.

    Rows that repeat an id are one document, and one of them stays, that of the smallest digest of its text. Rows without id all stay. Null
    texts are copies of each other, and so are empty ones. Ties in similarity don't matter: a pair is a match or not.
    """
    ship(spark)
    return neardup.drop_near_duplicates(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at weights that grow with the 0.9th power of their tokens: a hot source is damped a little, a small one is kept whole.

    A null ``source`` is a source like any other. Rows with equal ids, or without, are taken or left together. Null and empty texts have
    no tokens, cost nothing and are taken where their hash lies below the threshold.
    """
    return mixing.mix_documents(docs, temperature=0.9)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Windows of 2,048 words: (doc_id, piece, window_id, start, tokens, used).

    A longer text is cut into pieces; null and empty texts are listed without window. Rows without id are placed, with a null id;
    repeated rows are placed each. Ties in room go to the window opened first, ties in order to the smaller id.
    """
    ship(spark)
    return packing.pack(docs)


STAGES = [("language", identified), ("near_duplicates", deduplicated), ("mixture", mixed), ("packing", packed)]
#: Expectation-maximisation, connected groups of near copies and best-fit packing are beyond SQL; tests/llm compares with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
