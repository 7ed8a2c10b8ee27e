"""From raw documents to encoded training text: five stages, each written and read again.

toxicity      a document whose score reaches one half goes
near_dedup    of each group of near copies (five words, similarity 0.8) one stays
substrings    words of windows of 20 that also start earlier go; a document left without words goes
mixing        sources to target weights: whole copies, and of the last document the words that fit
encode        ids of the merge-type model, read back by decoding
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from negseq.llm import bpe_pieces, minhash_dedup, mixing, substring_dedup, toxicity
from negseq.llm.queries import model_path
from negseq.llm.shared import shared_dir, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
KEPT = ("lang", "source", "n_chars")


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learns from all labelled documents, and drops those that score as toxic; unknown ones stay."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"), usable=F.lit(True))
    scored = toxicity.score(docs.select(*COLUMNS), model, carry=COLUMNS)
    return scored.where("score < 0.5").select(*COLUMNS)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of least id of each group stays."""
    kept = minhash_dedup.minhash_dedup(docs).where("kept").select(F.col("doc_id").alias("_id")).distinct()
    known = docs.select(*COLUMNS).where("doc_id is not null").join(kept, F.col("doc_id") == F.col("_id"), "left_semi")
    return known.unionAll(docs.select(*COLUMNS).where("doc_id is null"))


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The kept words stand for a text of which words go; n_chars follows."""
    cut = substring_dedup.substring_dedup(docs, carry=("lang", "source"))
    return cut.where("n_words > n_removed or n_removed = 0").select("doc_id", F.col("kept_text").alias("text"), "lang", "source", F.coalesce(F.length("kept_text"), F.lit(0)).cast("long").alias("n_chars"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per copy that the mix takes; the copy that the budget ends keeps its first words."""
    rows = docs.select(*COLUMNS)
    plan = mixing.mix(rows).where("taken > 0").groupBy("doc_id", "digest").agg(F.max("epochs").alias("epochs"), F.max("part").alias("part"))
    keyed = rows.withColumn("digest", F.xxhash64(F.col("doc_id").cast("string"), F.col("text")))
    both = keyed.join(plan.withColumnsRenamed({"doc_id": "_id", "digest": "_digest"}), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("digest") == F.col("_digest")))
    size = mixing.n_words(F.col("text"))
    words = F.concat(F.array_repeat(size, F.col("epochs").cast("int")), F.when(F.col("part") > 0, F.array(F.col("part"))).otherwise(F.array().cast("array<long>")))
    copies = both.withColumn("_size", size).withColumn("_words", F.explode(words))
    begun = F.array_join(F.slice(F.split(F.btrim(F.col("text"), F.lit(" \t\n\x0b\f\r")), r"[\x20\x09-\x0D]+"), F.lit(1), F.col("_words").cast("int")), " ")
    text = F.when(F.col("_words") == F.col("_size"), F.col("text")).otherwise(begun)
    return copies.select("doc_id", text.alias("text"), "lang", "source", F.length(text).cast("long").alias("n_chars"))


def encode_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe_pieces.encode(docs, model_path())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", toxicity_stage),
    ("near_dedup", near_dedup_stage),
    ("substrings", substring_stage),
    ("mixing", mixing_stage),
    ("encode", encode_stage),
]

#: Scores, keys and the encoding are not SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = f"{shared_dir(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
