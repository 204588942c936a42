"""A corpus pipeline: quality rules, near duplicates, personal data, mixing, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows it is given; all but the last
return the columns of documents, and further columns of theirs, with the names and types they came with. The mix repeats
documents of scarce sources, so a doc_id may come several times to packing, once per copy.

Defined cases: a null or empty text has no words, so the first stage drops it; a null lang or source is a group and a
source of its own; a null doc_id is kept as it is and ordered first; equal rows are copies, of which the second stage keeps
one; an empty table, or one whose rows are all dropped, gives no row in any stage; n_chars is counted anew once personal
data is replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from branchwise.llm import mixing, near_duplicates, packing, pii, quality_rules
from branchwise.llm.common import documents, settled


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_duplicates.keep_one(docs)


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    clean = pii.redact(docs, pii.fit(docs))
    return clean.withColumn("n_chars", F.length("text").cast("bigint"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [("quality rules", rules), ("n-gram Jaccard join", near), ("PII", private), ("mixing sources to target weights", mixed), ("best-fit packing", packed)]

#: Shingle classes, boosted trees and subword ids have no SQL; the tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = settled(docs, f"stage-{i + 1}")
    return docs
