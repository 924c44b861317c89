"""A corpus pipeline: language, exact copies, near copies, mixture, packing.

Every stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept and returns a
DataFrame; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

import os
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import DataFrame, SparkSession  # noqa: E402

from prefixcode.llm import exthash, hdlang, icws, packing, pivotal  # noqa: E402
from prefixcode.llm.common import cut, table  # noqa: E402


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language (no letter at all) go: null, empty and letterless texts. Nothing else
    does, whatever its length; repeated rows stay; of an empty table nothing is left."""
    return hdlang.identified_documents(docs)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the largest doc_id stays, a null doc_id before none; of rows that tie
    exactly one. A null text equals the empty one and comes back empty; columns are as they were."""
    return exthash.distinct_documents(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates stays, the one with the largest doc_id, of rows that tie
    exactly one. Texts without words are alike only if equal; a text of fewer than five words is one shingle."""
    return icws.representatives(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mixture takes it: not at all, once or twice. A null source is a source;
    a document of no words is settled by its own coin; rows that agree share their unit's copies evenly."""
    return pivotal.mix_documents(docs)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their sequence and offset. An empty text is its end token alone; a long one is cut, only its
    first piece may be shorter; a null doc_id is passed on; an empty table gives no piece."""
    return packing.packed(docs)


STAGES = [("language_id", language), ("exact_dedup", exact_copies), ("near_dedup", near_copies), ("mix_sources", mixture), ("best_fit_packing", sequences)]

#: Language profiles, samples and packing are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; between two the rows are written and read again."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = cut(docs, f"pipeline-{name}")
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
