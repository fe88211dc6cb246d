"""Exact deduplication by a 128-bit content hash, with a byte comparison inside every hash group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semigrid.plans.scratch import BROADCAST_BYTES, guarded_broadcast, materialize, text_or_empty

#: ASCII white space that counts as one space.
BLANKS = r"[\x20\x09-\x0D]+"


def content_hash(text: Column) -> Column:
    """128 bits as 16 bytes."""
    return F.unhex(F.md5(text))


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hash_of=content_hash) -> DataFrame:
    """One row per row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when their bytes are, after each run of ASCII white space became
    one space; a null text is an empty one. Of equal texts the smallest id stays; rows
    that repeat an id count as members of their group and carry the same decision.
    A null id never wins over another one. Other columns of ``docs`` are not read.

    Only digests are shuffled for all rows. Texts travel for rows whose hash occurs
    twice, and are combined on the map side first, so a text that a third of all rows
    share leaves each task once. Grouping by (hash, text) compares the bytes: texts
    that merely collide fall into different classes, told apart by their SHA-256.
    """
    texts = docs.select(F.col(id_col).alias("doc_id"), F.regexp_replace(text_or_empty(text_col), BLANKS, " ").alias("body"))
    digests = materialize(texts.select("doc_id", hash_of(F.col("body")).alias("h"), F.sha2("body", 256).alias("text_sha256")), "digests")
    repeated = materialize(digests.groupBy("h").count().filter("count > 1").select("h"), "repeated")
    n = repeated.count()
    hashed = texts.withColumn("h", hash_of(F.col("body")))
    combined = [F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size")]
    if n * 64 <= BROADCAST_BYTES:
        grouped = hashed.join(F.broadcast(repeated), "h", "left_semi").groupBy("h", "body").agg(*combined)
    else:  # too many to send out: equal texts are combined in each task first, and only then shuffled
        grouped = hashed.groupBy("h", "body").agg(*combined).join(repeated, "h", "left_semi")
    classes = (
        grouped
        .select("h", F.sha2("body", 256).alias("text_sha256"), "keep_id", "group_size")
        .groupBy("h", "text_sha256")
        .agg(F.min("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"), F.count(F.lit(1)).alias("texts"))
        .withColumn("group_size", F.when(F.col("texts") == 1, F.col("group_size")).otherwise(F.raise_error(F.lit("two texts share both digests")).cast("long")))
    )
    classes = materialize(classes.select("h", "text_sha256", "keep_id", "group_size"), "classes")
    keep = F.coalesce("keep_id", "doc_id")
    return digests.join(guarded_broadcast(classes, 160), ["h", "text_sha256"], "left").select(
        "doc_id", keep.alias("keep_id"), F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"), keep.eqNullSafe(F.col("doc_id")).alias("kept"), "text_sha256"
    )


ORACLE = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept, sha256(body) AS text_sha256
FROM t WINDOW w AS (PARTITION BY body)
"""
