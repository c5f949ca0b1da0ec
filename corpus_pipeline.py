"""A corpus pipeline of five of the text operators, in order.

Each stage takes ``(spark, docs, sf_dir)`` and works on all that its predecessor kept; its
result is written and read again before the next one starts. All but the last return the
columns of ``documents``. ``run`` deletes each stage's table when the next one is written.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from manifold_dp.llm import decontaminate, jaccard, linededup, pieces, quality
from manifold_dp.llm.common import Scratch, free, table


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose quality score is at least the threshold."""
    free(spark)
    model = quality.fitted(spark, docs, sf_dir)
    return quality.score(docs, model).where("predicted = 1").select(*docs.columns)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without later repeated runs of lines; a document of which nothing is left goes."""
    free(spark)
    out = linededup.clean(docs)
    changed = F.col("n_removed") > 0
    kept = out.where(~changed | (F.length(F.trim("text", F.lit(" \t\r\n"))) > 0))
    return kept.withColumn("n_chars", F.when(changed, F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: the one of least id, then of least hash of its text.

    Texts that share an id are documents of their own, so none goes but for a near copy of
    it that stays. Equal rows of one id and text are one document: the least row stays.
    Rows without id stay.
    """
    free(spark)
    known = docs.where("doc_id IS NOT NULL").withColumn("_hash", F.xxhash64("text"))
    texts = known.select("doc_id", "_hash").groupBy("doc_id").agg(F.min("_hash").alias("a"), F.max("_hash").alias("b"), F.count(F.lit(1)).alias("n"))
    several = texts.where("n > 1").select("doc_id", (F.col("a") != F.col("b")).alias("_differ"))
    if not several.head(1):
        stay = jaccard.classes(docs).where("doc_id = component_id").select("doc_id")
        return docs.join(stay, "doc_id", "left_semi").unionByName(docs.where("doc_id IS NULL")).select(*docs.columns)
    # ids of several texts get a key for each text
    key = F.when(F.col("_differ"), F.xxhash64("doc_id", "_hash")).otherwise(F.col("doc_id").cast("long"))
    marked = Scratch(spark).keep(known.join(several, "doc_id", "left").withColumn("_key", key), "marked")
    groups = jaccard.classes(marked.select(F.col("_key").alias("doc_id"), "text")).select(F.col("doc_id").alias("_key"), "component_id").distinct()
    ids = marked.where("_differ").select("_key", F.col("doc_id").alias("_id")).distinct()
    order = F.struct(F.coalesce("_id", "_key").alias("id"), F.col("_key").alias("key"))
    stay = groups.join(ids, "_key", "left").groupBy("component_id").agg(F.min(order).alias("_least")).select(F.col("_least.key").alias("_key"))
    kept = marked.join(stay, "_key", "left_semi")
    once = kept.where("_differ IS NULL").select(*docs.columns)
    least = kept.where("_differ IS NOT NULL").groupBy("_key").agg(F.min(F.struct(*docs.columns)).alias("r")).select("r.*")
    return once.unionByName(least).unionByName(docs.where("doc_id IS NULL")).select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that overlap no benchmark item."""
    free(spark)
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def to_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The columns of documents, with the pieces of each text."""
    free(spark)
    return pieces.encode(docs)


STAGES = [
    ("quality_classifier", keep_good),
    ("line_dedup", drop_repeated_lines),
    ("ngram_jaccard_join", drop_near_copies),
    ("benchmark_decontamination", drop_contaminated),
    ("sentencepiece", to_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs, last = table(spark, sf_dir, "documents"), None
    results = Scratch(spark)
    for name, stage in STAGES:
        with Scratch.owned():  # what a stage wrote on its way goes once its result is written
            docs = results.keep(stage(spark, docs, sf_dir), name)
        if last is not None:
            results.drop(last)
        last = docs
    return docs


#: The classifier, the near-copy classes and the pieces are beyond SQL; tests compare with brute force.
ORACLE_SQL = None
