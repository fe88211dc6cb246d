"""Quality rules: a threshold table compiled into one projection of native functions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semigrid.plans.scratch import text_or_empty

#: Frequent short words of English, German, French and Spanish.
STOP_WORDS = (
    "the", "of", "and", "to", "in", "is", "that", "it", "for", "on", "was", "as", "with", "be", "by", "are", "this", "at", "from", "or",
    "der", "die", "das", "und", "den", "von", "zu", "mit", "ist", "ein", "eine", "nicht", "im", "dem", "auf", "für",
    "le", "la", "les", "de", "des", "du", "et", "un", "une", "que", "qui", "est", "en", "dans", "pour", "par", "sur",
    "el", "los", "las", "y", "del", "con", "no", "se", "su", "por", "una", "al", "lo",
)


@dataclass(frozen=True)
class Rule:
    """Reject when ``weight * measure`` is over (or under) ``bound`` times ``per``; all integers."""

    name: str
    measure: str
    weight: int
    over: bool
    bound: int
    per: str


#: The threshold table.
RULES = (
    Rule("too_many_symbols", "n_symbols", 10, True, 1, "n_words"),
    Rule("too_few_stop_words", "n_stop_words", 100, False, 2, "n_words"),
    Rule("words_too_short", "word_chars", 1, False, 2, "n_words"),
    Rule("words_too_long", "word_chars", 1, True, 14, "n_words"),
    Rule("repeated_lines", "n_dup_lines", 10, True, 5, "n_lines"),
    Rule("shouting", "n_shouts", 10, True, 3, "n_words"),
)


def _words(text: Column) -> Column:
    return F.array_remove(F.split(text, "[ \\t-\\r]+", -1), "")


def measures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Whole-text counts behind the rules, in native expressions only.

    A word is a run of other than ASCII white space. The repeat count hashes every
    3-word window; only a text with two equal hashes sorts its windows, by hash and
    then by the words themselves, so the count is exact and costs n log n for any text.
    """
    base = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("body"))
    split = base.select(
        "doc_id",
        _words(F.col("body")).alias("w"),
        F.filter(F.split("body", "\n", -1), lambda x: x.rlike("[^ \\t-\\r]")).alias("lines"),
        F.length(F.regexp_replace("body", "[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        (F.length("body") - F.length(F.replace("body", F.lit("!"), F.lit("")))).cast("long").alias("n_shouts"),
    )
    windows = F.when(
        F.size("w") >= 3,
        F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda i: F.xxhash64(F.element_at("w", i), F.element_at("w", i + 1), F.element_at("w", i + 2))),
    ).otherwise(F.array().cast("array<bigint>"))
    hashed = split.withColumn("h", windows)
    keyed = F.transform(
        "h",
        lambda x, i: F.struct(x.alias("x"), F.concat_ws(" ", F.element_at("w", i + 1), F.element_at("w", i + 2), F.element_at("w", i + 3)).alias("s"), i.alias("i")),
    )
    hashed = hashed.withColumn("k", F.when(F.size(F.array_distinct("h")) < F.size("h"), F.sort_array(keyed)))
    same = lambda a, b: F.coalesce((a["x"] == b["x"]) & (a["s"] == b["s"]), F.lit(False))
    starts = F.transform(F.filter("k", lambda e, j: same(e, F.get("k", j - 1)) | same(e, F.get("k", j + 1))), lambda e: e["i"])
    located = hashed.withColumn("at", starts)
    covered = F.size(F.array_distinct(F.concat("at", F.transform("at", lambda i: i + 1), F.transform("at", lambda i: i + 2))))
    return located.select(
        "doc_id",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        "n_symbols",
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.when(F.col("at").isNull(), F.lit(0)).otherwise(covered).cast("long").alias("n_repeat_words"),
        F.size("lines").cast("long").alias("n_lines"),
        F.size(F.filter("w", lambda x: F.lower(x).isin(*STOP_WORDS))).cast("long").alias("n_stop_words"),
        "n_shouts",
    )


def quality_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, the measures, base_failed, failed_rules and kept, for each row of ``docs``.

    A null text counts as empty: no words, base_failed. Repeated rows are judged one by
    one; other columns are not read. ``kept`` is false if the base rules fail, else
    it says that no rule of the table rejects the text.
    """
    m = measures(docs, id_col, text_col)
    base = (F.col("n_words") < 50) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 50)

    def hit(r: Rule) -> Column:
        left, right = F.col(r.measure) * r.weight, F.col(r.per) * r.bound
        return left > right if r.over else left < right

    failed = F.filter(F.array(*[F.when(hit(r), F.lit(r.name)) for r in rules]), lambda x: x.isNotNull())
    return m.withColumns({"base_failed": base, "failed_rules": failed}).withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))


def digest(docs: DataFrame) -> DataFrame:
    return quality_rules(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_stop_words", "n_shouts", "base_failed", "kept")


def _rule_sql(r: Rule) -> str:
    return f"({r.measure} * {r.weight} {'>' if r.over else '<'} {r.per} * {r.bound})"


ORACLE = rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS body FROM documents),
s AS (SELECT doc_id, body, [x FOR x IN regexp_split_to_array(body, '[\x20\x09-\x0D]+') IF x <> ''] AS w,
             [x FOR x IN string_split(body, chr(10)) IF regexp_matches(x, '[^\x20\x09-\x0D]')] AS lines FROM t),
g AS (SELECT doc_id, unnest(range(1, len(w) - 1)) AS i, w FROM s WHERE len(w) >= 3),
k AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i], w[i + 1], w[i + 2]) AS c FROM g),
r AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, i + unnest([0, 1, 2]) AS p FROM k WHERE c > 1) GROUP BY doc_id),
m AS (SELECT s.doc_id, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars,
             length(body) - length(regexp_replace(body, '[#*$%&|<>]', '', 'g')) AS n_symbols,
             len(lines) - len(list_distinct(lines)) AS n_dup_lines, coalesce(r.n, 0) AS n_repeat_words, len(lines) AS n_lines,
             len([x FOR x IN w IF lower(x) IN ({", ".join(f"'{x}'" for x in STOP_WORDS)})]) AS n_stop_words,
             length(body) - length(replace(body, '!', '')) AS n_shouts
      FROM s LEFT JOIN r ON s.doc_id = r.doc_id),
b AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_stop_words, n_shouts, base_failed,
       NOT base_failed AND NOT ({" OR ".join(map(_rule_sql, RULES))}) AS kept FROM b
"""
