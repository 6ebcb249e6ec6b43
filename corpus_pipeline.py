"""Corpus preparation: five operators in a row, each over all that its predecessor kept.

Rows are told apart by doc_id and text, so rows that repeat or lack a doc_id are
kept or dropped by their own text.  In every stage an empty table stays empty,
null and empty texts and ties have the result named in the stage, and extra
columns, of any name, are carried along as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubejoin.llm import bpe_codec, contextual_pii, decontaminate, language_gru, minhash_join
from cubejoin.llm.queries import vocabulary_path
from cubejoin.llm.workspace import Workspace, transient

#: Jaccard similarity, in percent, from which documents are near duplicates.
SIMILARITY = 80
#: Rows of a list of identities (three numbers each) that may be broadcast.
BROADCAST_ROWS = 500_000


def _named(columns: list[str], *names: str) -> list[str]:
    """Names that no column has."""
    taken = {c.lower() for c in columns}
    out = []
    for name in names:
        while name in taken:
            name += "_"
        out.append(name)
    return out


def _same(docs: DataFrame, of: DataFrame) -> tuple[DataFrame, Column]:
    """Identities (doc_id, text_key, ...) under fresh names, broadcast if few, and the condition that a document has one."""
    own, key = _named(docs.columns, "of_doc", "of_text")
    renamed = of.withColumnsRenamed({"doc_id": own, "text_key": key})
    if of.count() <= BROADCAST_ROWS:
        renamed = F.broadcast(renamed)
    return renamed, F.col("doc_id").cast("long").eqNullSafe(F.col(own)) & (F.xxhash64(F.col("text").cast("string")) == F.col(key))


def _columns(docs: DataFrame) -> list[Column]:
    return [F.col(f"`{c}`") for c in docs.columns]


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the network rejects go: those without letters (null and empty ones among them).

    The network learns from the documents themselves, by their ``lang``; what a
    kept document holds is not changed.  Nothing is shuffled but the sample.
    """
    lang, score = _named(docs.columns, "lang_pred", "score")
    labelled = language_gru.with_language(spark, docs, language_gru.train(docs), lang, score)
    return labelled.where(F.col(lang) != "und").select(*_columns(docs))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays: that of smallest doc_id (of equal ones, of smallest text hash).

    Documents without doc_id stay only if no other one of their group has one; of
    rows equal in doc_id and text one stays; documents without words stay.
    """
    work = Workspace(spark, "dedup_stage")
    rows = minhash_join.near_duplicates(spark, docs, minhash_join.JoinSettings.for_similarity(SIMILARITY)).where("group_id is not null")
    copies = work.table("copies", rows.groupBy("group_id", "doc_id", "text_key").agg(F.count("*").alias("copies")))
    first = copies.groupBy("group_id").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key")).alias("m"))
    marked = copies.join(first, "group_id").withColumn("stays", F.col("doc_id").eqNullSafe(F.col("m.doc_id")) & (F.col("text_key") == F.col("m.text_key")))
    marked = work.table("marked", marked.where("copies > 1 or not stays").select("doc_id", "text_key", "stays"))
    others, same = _same(docs, marked.select("doc_id", "text_key"))
    single = docs.join(others, same, "left_anti")
    repeated, same = _same(docs, marked.where("stays").select("doc_id", "text_key"))
    own, key = _named(docs.columns, "of_doc", "of_text")
    one_each = docs.join(repeated, same).dropDuplicates([own, key])
    return single.select(*_columns(docs)).unionAll(one_each.select(*_columns(docs)))


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark window go; those without words hold none."""
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    dirty = decontaminate.contamination(spark, docs, benchmark).where("contaminated").select("doc_id", "text_key").distinct()
    others, same = _same(docs, dirty)
    return docs.join(others, same, "left_anti").select(*_columns(docs))


def pii_redaction(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in texts is replaced by its kind; n_chars follows; null texts stay null."""
    found = contextual_pii.personal_data(spark, docs).where(F.size("found") > 0)
    spans = Workspace(spark, "pii_spans").table("found", found.select("doc_id", "text_key", "found"))
    return contextual_pii.redact(docs, spans)


def tokenised(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token count and digests of every document that is left; null text counts as empty."""
    return bpe_codec.round_trip(spark, docs, vocabulary_path())


STAGES = [
    ("language_id", language_id),
    ("minhash_near_dedup", near_dedup),
    ("benchmark_decontamination", decontamination),
    ("pii_redaction", pii_redaction),
    ("bpe_round_trip", tokenised),
]

#: Networks, signatures and bootstrapped patterns have no SQL form; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are written and reread, and what a stage no longer needs is deleted."""
    work = Workspace(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        with transient():
            docs = work.table(name, stage(spark, docs, sf_dir))
        if k:
            work.drop(STAGES[k - 1][0])
    return docs
