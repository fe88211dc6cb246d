"""From raw documents to packed sequences: five stages, each a table for the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semigrid.llm import exact_dedup, language_id, packing, simhash_dedup, suffix_dedup
from semigrid.llm.queries import vocabulary
from semigrid.plans.scratch import guarded_broadcast, materialize


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Rows whose doc_id is not among ``ids``; a null id is never among them."""
    gone = materialize(ids.filter("doc_id is not null").select("doc_id").distinct(), "gone")
    return docs.join(guarded_broadcast(gone, 32), "doc_id", "left_anti").select(docs.columns)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Gives documents without a language the predicted one, and drops those in which none is found.

    The languages are learned from the labelled rows of ``docs``. A null text, an empty one and
    one without any letter are dropped. Rows that repeat an id are judged one by one, rows
    with a null id as any other. Without a labelled row no language is known, and nothing
    is changed.
    """
    model = language_id.fit(docs)
    if not model.languages:
        return docs
    names = {"lang_pred", "score"} & set(docs.columns)
    away = {n: n + "_" * max(map(len, docs.columns)) for n in names}  # names that the prediction takes
    said = language_id.identify(docs.withColumnsRenamed(away), model, whole_rows=True).filter(F.col("lang_pred") != language_id.UNKNOWN)
    said = said.withColumn("lang", F.coalesce("lang", "lang_pred")).drop("lang_pred", "score")
    return said.withColumnsRenamed({v: k for k, v in away.items()}).select(docs.columns)


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the smallest doc_id stays; of rows that repeat id and text, one."""
    kept = _without(docs, exact_dedup.exact_dedup(docs).filter(~F.col("kept")))
    again = materialize(docs.groupBy("doc_id").count().filter("count > 1").select("doc_id"), "again")
    if again.isEmpty():
        return kept
    same = docs["doc_id"].eqNullSafe(again["doc_id"])
    alone = docs.join(guarded_broadcast(again, 32), same, "left_semi").dropDuplicates(["doc_id", "text"])
    alone = _without(alone, exact_dedup.exact_dedup(docs).filter(~F.col("kept")))
    return kept.join(guarded_broadcast(again, 32), kept["doc_id"].eqNullSafe(again["doc_id"]), "left_anti").unionByName(alone)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of near copies (five-word shingles, similarity 0.8) the smallest doc_id of each group stays.

    A null text counts as empty, and texts without a word are near copies of each other. Rows
    with a null id stay; rows that repeat an id are one document, and stay or go together.
    """
    return _without(docs, simhash_dedup.similar_groups(docs).select(F.col("node").alias("doc_id")))


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes repeated strings of 100 bytes from the texts; every document stays.

    The first place of a string, by doc_id and then in the text, keeps it. A null text stays
    null; a row with a null id is left as it is; rows that repeat an id are one document.
    """
    cut = suffix_dedup.without_repeats(docs)
    return cut.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else cut


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 2048 tokens; a null text is its end id alone, repeated rows are packed each."""
    return packing.pack(docs, vocabulary("word_bpe_49k.json"))


STAGES = [("language_id", language), ("exact_dedup", exact), ("simhash_near_dedup", near), ("suffix_array_dedup", repeats), ("packing", packed)]

#: The stages hash, decode codes, sort suffixes and tokenize; SQL has no words for that.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``, each written as a table and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
