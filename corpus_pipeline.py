"""A corpus from rules to packed sequences; each stage is written as Parquet and read again as the next one's input."""

from __future__ import annotations

from dgprop.llm.common import documents, save
from dgprop.llm.mixing import mix, source_group
from dgprop.llm.packing import pack_documents
from dgprop.llm.personaldata import redact
from dgprop.llm.qualityrules import keep_good
from dgprop.llm.shinglejoin import one_of_each
from pyspark.sql import DataFrame, SparkSession

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Share of the tokens that mixing keeps.
MIX_SHARE = 0.9


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_good(docs.select(*COLUMNS))


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return one_of_each(docs.select(*COLUMNS))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return redact(docs.select(*COLUMNS))


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mix(docs.select(*COLUMNS), source_group(), {}, MIX_SHARE, max_epochs=1, seed=7)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("quality rules", quality_rules),
    ("n-gram Jaccard join", ngram_jaccard_join),
    ("personal data", personal_data),
    ("source mixing", source_mixing),
    ("best-fit packing", best_fit_packing),
]

#: The stages can't be written in SQL: expectation-maximisation, boosted trees and a search.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = save(docs, f"stage-{i + 1}")
    return docs
