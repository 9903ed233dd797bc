"""The operators' queries with production parameters, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import functions as F

from netan.llm import decontamination, html_text, language_id, mixing, ngram_join, quality, sharding, substring_dedup, token_counts, token_files
from netan.llm.common import table

#: Shards and their turns a round in op9.
SHARDS = {f"shard-{k:02d}": 1 + k % 3 for k in range(16)}
SHARD_SLOTS = 1009


def source_domain():
    """Domain of a row in op1 and the pipeline: sources fall in four domains by the last digit of their name."""
    return F.concat(F.lit("domain-"), (F.coalesce(F.try_to_number(F.right("source", F.lit(1)), F.lit("9")), F.lit(0)).cast("int") % 4).cast("string"))


def node_weight():
    """Weights in op1 and the pipeline: domains 4 to 1, English three times another language, even sources twice odd ones."""
    last = F.coalesce(F.try_to_number(F.right("source", F.lit(1)), F.lit("9")), F.lit(0)).cast("int")
    return (
        F.when(F.col("source").isNotNull(), 2 - last % 2)
        .when(F.col("lang").isNotNull(), F.when(F.col("lang") == "en", 3).otherwise(1))
        .otherwise(4 - F.right("domain", F.lit(1)).cast("int"))
    )


def op1_mixing(spark, sf_dir):
    """Half the corpus's tokens, mixed by node_weight(), with at most four epochs."""
    return mixing.mix(table(spark, sf_dir, "documents"), source_domain(), node_weight(), 0.5, 4, seed=11)


def op2_substring_dedup(spark, sf_dir):
    return substring_dedup.remove(table(spark, sf_dir, "documents"))


def op3_html_text(spark, sf_dir):
    return html_text.main_text(table(spark, sf_dir, "pages"))


def op4_language_id(spark, sf_dir):
    return language_id.identify(table(spark, sf_dir, "documents"))


def op5_decontamination(spark, sf_dir):
    judged = decontamination.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return judged.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op6_quality(spark, sf_dir):
    return quality.assess(table(spark, sf_dir, "documents")).drop("rid")


def op7_token_files(spark, sf_dir):
    return token_files.read_ids(token_files.write_ids(table(spark, sf_dir, "documents")))


def op8_ngram_join(spark, sf_dir):
    return ngram_join.similar(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


def op9_sharding(spark, sf_dir):
    return sharding.place(table(spark, sf_dir, "documents"), SHARDS, SHARD_SLOTS)


def op10_token_counts(spark, sf_dir):
    return token_counts.count_tokens(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {
        "op1_mixing": op1_mixing,
        "op2_substring_dedup": op2_substring_dedup,
        "op3_html_text": op3_html_text,
        "op4_language_id": op4_language_id,
        "op5_decontamination": op5_decontamination,
        "op6_quality": op6_quality,
        "op7_token_files": op7_token_files,
        "op8_ngram_join": op8_ngram_join,
        "op9_sharding": op9_sharding,
        "op10_token_counts": op10_token_counts,
    }


def oracle_sql() -> dict:
    last = "coalesce(try_cast(right(source, 1) AS INT), 0)"
    weights = ("4 - right(domain, 1)::INT", "CASE WHEN lang = 'en' THEN 3 ELSE 1 END", f"2 - {last} % 2")
    return {"op1_mixing": mixing.sql(f"'domain-' || {last} % 4", weights, 0.5, 4, 11), "op9_sharding": sharding.sql(SHARDS, SHARD_SLOTS)}
