"""From raw documents to token files: five stages, each written as Parquet and read again by the next.

Each stage is one operator of netan.llm over all rows that the stage before it has kept. All stages but the last return the
columns of documents; the last returns what it has read back from the token files.

Empty tables give empty tables. Columns beyond doc_id, text, lang and source go along unread, those with names that stages use
themselves included. Null and wordless texts fail the quality rules; a null language or source is one named "null". Very long
texts are documents like any other. Rows that repeat are one document from the second stage on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netan.llm import decontamination, mixing, ngram_join, quality, token_files
from netan.llm.common import table
from netan.llm.queries import node_weight, source_domain
from netan.storage import drop, lasting, scratch, written


def _without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """docs less the rows (doc_id, rid) of gone; equal rows go together."""
    gone = gone.select(F.col("doc_id").alias("_gone_id"), F.col("rid").alias("_gone_rid")).distinct()
    rid = F.xxhash64(docs["doc_id"], docs["text"])
    return docs.join(gone, (rid == gone["_gone_rid"]) & docs["doc_id"].eqNullSafe(gone["_gone_id"]), "left_anti")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rule and their language's perplexity band keep."""
    return _without(docs, quality.assess(docs).where("NOT kept"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of similar ones (five words, 0.80), that with the smallest id; of equal rows, one."""
    members = ngram_join.similar(docs, size=5, per_cent=80).where("component IS NOT NULL")
    first = members.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "rid")).alias("first"))
    gone = F.expr("NOT (doc_id <=> first.doc_id AND rid = first.rid)")
    marks = members.join(first, "component").groupBy(F.col("doc_id").alias("_id"), F.col("rid").alias("_rid")).agg(F.max(gone).alias("_gone"), F.count("*").alias("_times"))
    marks = written(marks.where("_gone OR _times > 1"), "marks")
    # who goes is settled by ids, so that texts are dealt once; both joins read the same exchange of them
    same = (F.xxhash64(docs["doc_id"], docs["text"]) == marks["_rid"]) & docs["doc_id"].eqNullSafe(marks["_id"])
    equal = docs.join(marks.where("NOT _gone"), same, "left_semi").dropDuplicates(["doc_id", "text"])
    return docs.join(marks, same, "left_anti").unionByName(equal)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no more than the allowed share of benchmark windows."""
    return _without(docs, decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark")).where("contaminated"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Nine tenths of the tokens, mixed by weight with two epochs at most; a document of two epochs is there twice."""
    columns = docs.columns
    chosen = mixing.mix(docs, source_domain(), node_weight(), 0.9, 2, seed=23, keep=tuple(columns))
    rows = chosen.select(F.explode(F.sequence(F.lit(1), "copies")), *(F.col(f"_{c}").alias(f"_{c}") for c in columns))
    return rows.select(*(F.col(f"_{c}").alias(c) for c in columns))


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files of all rows, read back."""
    return token_files.read_ids(token_files.write_ids(docs))


STAGES = [
    ("quality rules", quality_rules),
    ("n-gram jaccard join", near_duplicates),
    ("benchmark decontamination", decontaminated),
    ("mixing to target weights", mixed),
    ("token-id output", token_ids),
]

#: No SQL: the perplexity model and the tokenizer are beyond it. tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, from the documents table on."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        before = docs
        with scratch():
            docs = lasting(stage(spark, before, sf_dir), name.replace(" ", "-"))
        drop(before)
    return docs
