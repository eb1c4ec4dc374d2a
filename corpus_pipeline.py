"""From documents to token ids: quality rules, near-duplicates, decontamination, personal data, encoding.

Each stage works on all that the stage before kept. The first four return the columns of documents;
the last returns what op7's query returns. Edge cases are those of the operators: rows without text fail the
quality rules, rows without doc_id are kept by the stages that name rows by it, an empty table stays
empty, further columns ride along to the last stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hgpart.llm import decontamination, pieces, pii, quality, simhash
from hgpart.llm.tables import table, written


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_one_per_group(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def with_surrogates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.replace_entities(docs, pii.session_key(spark)).select(*docs.columns)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pieces.token_digests(docs)


STAGES = [
    ("quality rules", good_quality),
    ("SimHash near-duplicates", one_of_each_group),
    ("benchmark decontamination", without_benchmark),
    ("surrogates", with_surrogates),
    ("piece ids", token_ids),
]

#: The stages are tested one by one against brute force; their hashes have no DuckDB form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs, f"stage{k}")
    return docs
