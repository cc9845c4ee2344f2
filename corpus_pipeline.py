"""A cleaning pipeline over documents: classify, apply rules, drop near duplicates, replace personal data, pack.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written and read again as the next one's
docs. All but the last return the columns of documents. A null text is an empty document and goes in the second
stage at the latest; repeated rows meet in the third, where a document without an id, or with another's, counts by
its text like any other; an empty table runs through to an empty result.
"""

from __future__ import annotations

import os
import warnings

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from streamfill.llm.classifier import classify, fit, graded
from streamfill.llm.common import settle, table
from streamfill.llm.neardup import near_duplicates
from streamfill.llm.packing import pack
from streamfill.llm.pii import replace_private
from streamfill.llm.quality import judge

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: SQL can express neither the classifier nor the fingerprints.
ORACLE_SQL = None


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose probability of the top grade is one half or more."""
    model = fit(*graded(docs, table(spark, sf_dir, "labels")))
    return classify(docs, model, carry=COLUMNS).where("kept").select(*COLUMNS)


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and are not depleted once boilerplate lines are taken out."""
    return judge(docs, carry=COLUMNS).where("kept").select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates one document, once even where its row repeats: that with the least id (ids
    before nulls), among equal ids the one whose columns have the least hash. Rows are told apart by a hash of all
    their columns, not by their ids."""
    whole = F.to_json(F.struct(*COLUMNS), {"ignoreNullFields": "false"})
    rows = docs.select(*COLUMNS).withColumn("q_key", F.substring(F.sha2(whole, 256), 1, 32))
    found = near_duplicates(rows, carry=("q_key",))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "q_key"))
    leaders = found.groupBy("root").agg(first.alias("first")).select("first.q_key")
    return rows.dropDuplicates(["q_key"]).join(leaders, "q_key", "left_semi").select(*COLUMNS)


def private_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced; n_chars follows the new text. The key comes from the environment; without
    one a public key is used, with a warning, as it lets anyone test guesses."""
    key = os.environ.get("SURROGATE_KEY")
    if not key:
        warnings.warn("SURROGATE_KEY is not set: surrogates are made with a public key", stacklevel=2)
        key = "example key of the test pipeline"
    out = replace_private(docs, key, carry=("lang", "source", "n_chars"))
    return out.withColumn("n_chars", F.when(F.col("n_replaced") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents, with their token ids."""
    import public_tokenizers

    return pack(docs, public_tokenizers.path("byte_bpe_50k.json"), 1024)


STAGES = [
    ("quality_classifier", quality_classifier),
    ("quality_rules", quality_rules),
    ("near_dedup", near_dedup),
    ("private_data", private_data),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
