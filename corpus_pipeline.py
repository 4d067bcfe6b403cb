"""A corpus pipeline of five stages, each one of the training-data operators on all that its predecessor kept.

Every stage but the last returns the columns of `documents`. Rows without a doc_id pass the filters
on their own merits; texts that are null count as empty.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldpack.llm.bpe import default_files, encode_documents
from fieldpack.llm.common import bound_batches, read_table, stage
from fieldpack.llm.line_quality import fit, judge_documents
from fieldpack.llm.mixing import mix_documents
from fieldpack.llm.near_dedup import NearDup, near_duplicates, text_mark
from fieldpack.llm.secrets import find_secrets, redact


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the line labelling or the base rule rejects go."""
    model = fit(docs, read_table(spark, sf_dir, "labels"))
    return judge_documents(docs, model, into="_verdict").where("_verdict.kept").select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five words, 0.8) stays: that with the smallest id. Rows are told
    apart by id and text: other texts under the same id are other documents, equal rows are copies. Documents
    without words and rows without an id all stay."""
    found = near_duplicates(docs.select("doc_id", "text"), NearDup())
    chosen = stage(found.where("chosen AND doc_id IS NOT NULL AND n_shingles > 0").select("doc_id", "mark").distinct(), "near-chosen")
    alone = stage(found.where("doc_id IS NOT NULL AND n_shingles = 0").select("doc_id", "mark").distinct(), "near-alone")
    marked = docs.where(F.col("doc_id").isNotNull()).withColumn("_mark", text_mark(F.col("text")))
    of = lambda ids: marked.join(ids.withColumnsRenamed({"doc_id": "_id", "mark": "_of"}), (F.col("doc_id") == F.col("_id")) & (F.col("_mark") == F.col("_of")), "left_semi")
    out = of(chosen).dropDuplicates(["doc_id", "_mark"]).unionByName(of(alone)).drop("_mark")
    return out.unionByName(docs.where(F.col("doc_id").isNull())).select(*docs.columns)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are cut out of the texts; every document stays."""
    found = find_secrets(docs, prefix="_secret_")
    out = found.withColumn("text", F.when(F.col("text").isNotNull(), redact(F.col("text"), F.col("_secret_all"))))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.size("_secret_all") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are mixed to their target weights; a document may come up to twice."""
    return mix_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids (little-endian unsigned 32 bits each, binary) of every text."""
    bound_batches(spark)
    return encode_documents(docs, *default_files()).select("doc_id", "source", "lang", "n_tokens", "token_ids")


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality_rules),
    ("near_dedup", near_dedup),
    ("secret_scan", secret_scan),
    ("mix_sources", mix_sources),
    ("byte_bpe", encode),
]

#: The line labeller and the merges of the ranks have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; each stage's rows are staged and read again."""
    docs = read_table(spark, sf_dir, "documents")
    for i, (name, step) in enumerate(STAGES):
        docs = step(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = stage(docs, f"pipeline-{name}")
    return docs
