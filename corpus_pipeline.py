"""The corpus pipeline: five stages, each over all that the one before it kept."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm.decontaminate import decontaminate
from geocentra.llm.kneser_ney import classify
from geocentra.llm.minhash import near_duplicates
from geocentra.llm.packing import near_cluster_names, pack_best_fit
from geocentra.llm.plan import load
from geocentra.llm.substring_dedup import substring_dedup
from geocentra.plans.checkpoint import delete_folder, own_folder

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
OTHERS = ["doc_id", "lang", "source", "n_chars"]


def _again(got: DataFrame, text: str) -> DataFrame:
    """The columns of documents from an operator's carried ones."""
    return got.select("carried.doc_id", F.col(text).alias("text"), "carried.lang", "carried.source", F.length(text).cast("long").alias("n_chars"))


def _version(text: str) -> Column:
    return F.xxhash64(F.col(text).cast("string"))


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go: their perplexity under trusted text of their language is too high.

    Null and empty texts stay, as do texts of a language without trusted text; a null
    language is one of its own; texts of any length are judged whole. Rows are judged
    one by one, so that repeated rows, and rows without an id or with a repeated one,
    fare as their text does; a perplexity at the limit stays. An empty table gives an
    empty one. Further columns, whatever their names, are left out.
    """
    good = classify(docs, load(spark, sf_dir, "labels")).where("kept").select(F.col("id").alias("kept_id"), F.col("version").alias("kept_version")).distinct()
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("kept_id")) & (_version("text") == F.col("kept_version"))
    return docs.join(good, same, "left_semi").select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (five words, similarity 0.8) the document of the smallest id stays.

    Null and empty texts are like no other and stay; long texts are compared whole.
    Documents without an id stay. Of rows that repeat an id and a text one stays; of
    different texts of one id the largest is judged, and the others stay. An empty
    table gives an empty one. Further columns, whatever their names, are left out.
    """
    judged = near_duplicates(docs, width=5, percent=80).where("id is not null").select(F.col("id").alias("judged_id"), F.col("version").alias("judged_version"), F.col("kept").alias("judged_kept"))
    named = docs.where("doc_id is not null").select(*COLUMNS)
    several = not named.groupBy("doc_id").count().where("count > 1").limit(1).isEmpty()
    stays = (_version("text") != F.col("judged_version")) | F.col("judged_kept")
    named = named.join(judged, F.col("doc_id").cast("long") == F.col("judged_id")).where(stays).select(*COLUMNS)
    if several:
        named = named.dropDuplicates(["doc_id", "text"])
    return named.unionByName(docs.where("doc_id is null").select(*COLUMNS))


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 20 words and more that occur earlier (smaller id, or earlier in the text) are cut out; every document stays.

    Null texts become empty ones; passages are found in texts of any length. A row without an id loses nothing and protects nothing; rows
    that repeat an id are versions of one document and lose nothing to each other. An
    empty table gives an empty one. Further columns, whatever their names, are left out.
    """
    return _again(substring_dedup(docs, carry=OTHERS, in_place=True), "kept_text")


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of benchmark items, 10 words and more, or whole shorter items, are cut out; every document stays.

    Null and empty texts hold nothing and come out empty; texts of any length are searched. Rows are judged
    one by one, repeated ones and those without an id too; items that occur several
    times or overlap are cut once. An empty table, or an empty benchmark, changes
    nothing. Further columns, whatever their names, are left out.
    """
    return _again(decontaminate(docs, load(spark, sf_dir, "benchmark"), carry=OTHERS, clean_text=True), "clean_text")


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All texts in bins of 2048 words, no two of one source or two near copies together.

    Null and empty texts are one piece of no words; a text longer than a bin is cut in
    pieces. A null source conflicts with nothing. Ties of length go by a hash of id and
    text. Repeated rows, and rows without an id, are packed as any other, and an empty
    table gives no rows. Further columns, whatever their names, are left out.
    """
    return pack_best_fit(docs, clusters=near_cluster_names(docs)).withColumnRenamed("id", "doc_id")


STAGES = [("quality classifier", quality), ("near-dedup", near_dedup), ("substring dedup", substrings), ("decontamination", leaks), ("packing", packing)]

# SQL cannot express the model of the first stage.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what each returns is written as Parquet to the shared folder and read by the next.

    A stage's rows are deleted once the next has written its own; the last one's go
    when the driver ends, and all of them if a stage fails.
    """
    docs = load(spark, sf_dir, "documents")
    folder = f"{own_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    done = False
    try:
        for k, (_, stage) in enumerate(STAGES):
            stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
            docs = spark.read.parquet(f"{folder}/{k}")
            if k:
                delete_folder(spark, f"{folder}/{k - 1}")
        done = True
    finally:
        if not done:
            delete_folder(spark, folder)
    return docs
