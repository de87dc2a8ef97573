"""The corpus pipeline: quality, near copies, source mix, packing.

Each stage takes (spark, docs, sf_dir) and gives a DataFrame; all but the last
give rows with the columns of ``documents``.  The pipeline writes every stage's
rows as Parquet and reads them again, so a lost executor costs one stage at most.
A null or empty text passes or fails by its score like any other, is no copy of
anything, and leaves at the mix, which takes words.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from polyprov.llm.common import fresh_folder, table
from polyprov.llm.near_dup import one_of_each
from polyprov.llm.packing import pack_documents
from polyprov.llm.quality import accepted, fit
from polyprov.llm.source_mix import mixed_documents

#: Vocabulary of the tokens that are packed.
TOKENIZER = "piece_bpe_32k.model"


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression classifier does not reject (operator 2)."""
    return accepted(docs, fit(docs, table(spark, sf_dir, "labels")))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (operator 8)."""
    return one_of_each(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the source mix takes them (operator 9)."""
    return mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents, by their tokens, in bins of permitted lengths (operator 4)."""
    from public_tokenizers import path

    return pack_documents(docs, model_path=path(TOKENIZER))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality classifier", keep_quality),
    ("MinHash near-dedup", drop_copies),
    ("mixing sources to target weights", mix_sources),
    ("best-fit packing", pack),
]

#: SQL cannot express the classifier, the similarity join or the packing.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, folder = table(spark, sf_dir, "documents"), fresh_folder(spark, "pipeline")
    for i, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{i}")
        docs = spark.read.parquet(f"{folder}/{i}")
    return docs


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
