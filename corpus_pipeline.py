"""The corpus pipeline: five stages over documents, each written as Parquet and read again by the next.

1 language     drops documents without a letter and those whose language the codes cannot tell apart
2 near_dups    keeps the least doc_id of each group of near copies (five-word shingles, similarity 0.8); equal rows once
3 benchmark    drops documents that the contamination rule catches
4 secrets      replaces every secret span by [SECRET] and sets n_chars anew; drops nothing
5 mix          draws the mixture: one row per copy, with the output shard

Texts that a stage judges are those its predecessor kept.  Nulls: a null text is `und` and goes with stage 1; rows without
a doc_id stay in stage 2 (they have no group).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopjoin.llm import op1_langid, op3_mix, op9_decontaminate, op10_secrets, shingles
from hopjoin.llm.common import materialize, safe_prefix, table

#: A language decision below this score that is also ambiguous is rejected.
LEAST_SCORE = 0.45


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    p = safe_prefix(docs, "li")
    model = op1_langid.train(docs, "text", "lang", "doc_id")
    out = op1_langid.identify(docs, model, names=(f"{p}lang", f"{p}score", f"{p}ambiguous"))
    unsure = F.col(f"{p}ambiguous") & (F.col(f"{p}score") < LEAST_SCORE)
    return out.where((F.col(f"{p}lang") != "und") & ~unsure).select(*docs.columns)


def near_dups(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    groups = materialize(shingles.near_duplicate_groups(docs))
    keep = groups.where("d = root").groupBy("d").agg(F.count(F.lit(1)).alias("n"))
    keep = materialize(keep)
    # the kept ids grow with the documents: they are never broadcast
    kept = docs.join(keep.select(F.col("d").alias("doc_id")).hint("merge"), "doc_id", "left_semi")
    if keep.where("n > 1").limit(1).count():  # rows that share an id: one of each stays
        kept = kept.dropDuplicates(["doc_id"])
    return kept.select(*docs.columns).union(docs.where(F.col("doc_id").isNull()))


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out, p = op9_decontaminate.overlaps(docs, table(spark, sf_dir, "benchmark"))
    return out.where(~op9_decontaminate.contaminated(p)).select(*docs.columns)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found, p = op10_secrets.secret_spans(docs)
    spans = F.col(f"{p}spans")
    clean = op10_secrets.redact(F.col("text"), spans)
    n = F.when(F.size(spans) > 0, F.length(clean).cast("long")).otherwise(F.col("n_chars"))
    return found.withColumns({"text": clean, "n_chars": n}).select(*docs.columns)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return op3_mix.mix(docs)


STAGES = [("language", language), ("near_dups", near_dups), ("benchmark", benchmark), ("secrets", secrets), ("mix", mix)]

ORACLE_SQL = None  # the learned language model and the component search have no SQL form; tests hold the stages against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
