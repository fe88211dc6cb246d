"""Language identification: known words first, then ever shorter character n-grams."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructField, StructType

from semigrid.functions.worker import lean, small_batches
from semigrid.plans.scratch import materialize

_WORDY = re.compile(r"[^\W\d_]+")
#: Label of texts without a letter.
UNKNOWN = "und"


@dataclass
class LanguageModel:
    """Log frequencies for each language: of known words, and of n-grams by length."""

    languages: list[str]
    words: dict[str, int]
    grams: dict[str, int]
    table: np.ndarray  # one row for each word and gram, one column for each language
    floor: np.ndarray
    longest: int


def fit(docs: DataFrame, lang_col: str = "lang", text_col: str = "text", id_col: str = "doc_id", sample: int = 4000, words_each: int = 15_000, longest: int = 4, grams_each: int = 20_000) -> LanguageModel:
    """Word and n-gram frequencies of ``sample`` labelled documents at most (repeated rows count once).

    The sample is the rows with the least hashes of id, label and text, so it is the same on
    every run, and a row that is repeated often fills no more of it. It keeps ``words_each`` most frequent words and ``grams_each`` n-grams of each
    length for each language; of the words of equal count, those of one hash bucket in
    16 stay or go together, so a few more may stay. Rows without a label or text are
    not used; without any labelled row the model knows no language.
    """
    rows = docs.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    rows = rows.withColumn("at", F.xxhash64("id", "lang", "text"))
    end = rows.select("at").distinct().orderBy("at").limit(sample).agg(F.max("at")).first()[0]
    rows = rows.filter(F.lit(False) if end is None else F.col("at") <= end).dropDuplicates(["at"])  # only hashes are sorted, and few texts shuffled
    counted = rows.select("lang", F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word")).filter("word <> ''").groupBy("lang", "word").count()
    counted = materialize(counted.withColumn("part", F.pmod(F.xxhash64("word"), F.lit(16))), "words")
    kept = F.lit(False)
    room: dict[str, int] = {}
    sizes = counted.groupBy("lang", "count", "part").agg(F.count(F.lit(1)).alias("n")).collect()  # bounded as the sample is
    last: dict[str, tuple[int, int]] = {}
    for r in sorted(sizes, key=lambda r: (r["lang"], -r["count"], r["part"])):
        if room.setdefault(r["lang"], words_each) > 0:
            room[r["lang"]] -= r["n"]
            last[r["lang"]] = (r["count"], r["part"])
    for lang, (n, part) in last.items():
        kept |= (F.col("lang") == lang) & ((F.col("count") > n) | (F.col("count") == n) & (F.col("part") <= part))
    found = sorted((r["lang"], r["word"], r["count"]) for r in counted.filter(kept).select("lang", "word", "count").collect())
    languages = sorted({x[0] for x in found})
    column = {x: k for k, x in enumerate(languages)}
    words: dict[str, int] = {}
    counts: list[tuple[int, int, float]] = []
    totals = np.ones(len(languages))
    grams: dict[str, int] = {}
    by_length: dict[tuple[str, int], Counter] = {}
    for lang, word, n in found:
        counts.append((words.setdefault(word, len(words)), column[lang], n))
        totals[column[lang]] += n
        marked = f"<{word}>"
        for size in range(1, longest + 1):
            c = by_length.setdefault((lang, size), Counter())
            for i in range(len(marked) - size + 1):
                c[marked[i : i + size]] += n
    table = np.full((len(words), len(languages)), 0.5)
    for row, col, n in counts:
        table[row, col] = n + 0.5
    parts = [np.log(table / (totals + 0.5 * max(1, len(words))))]
    for size in range(1, longest + 1):
        kept = {lang: by_length.get((lang, size), Counter()).most_common(grams_each) for lang in languages}
        names = {g: k for k, g in enumerate(sorted({g for v in kept.values() for g, _ in v}))}
        part = np.full((len(names), len(languages)), 0.5)
        for lang, v in kept.items():
            for g, n in v:
                part[names[g], column[lang]] += n
        base = len(words) + len(grams)
        grams |= {g: base + k for g, k in names.items()}
        parts.append(np.log(part / part.sum(0)) if len(names) else part)
    return LanguageModel(languages, words, grams, np.concatenate(parts).astype(np.float32), np.zeros(len(languages), np.float32), longest)


def letter_words(text: str) -> list[str]:
    """The runs of letters (Unicode categories L) of a text, in lower case."""
    words = _WORDY.findall(text.lower())
    if "".join(words).isalpha():
        return words
    # some characters count as numbers and still as parts of words, such as superscripts and fractions
    return [x for w in words for x in ([w] if w.isalpha() else "".join(c if c.isalpha() else " " for c in w).split())]


class Scorer:
    """Adds log frequencies over the words of a text; unseen words are remembered up to a bound."""

    def __init__(self, model: LanguageModel, remembered: int = 100_000):
        self.model, self.bound = model, len(model.words) + remembered
        self.reset()

    def reset(self) -> None:
        m, k = self.model, len(self.model.words)
        self.rows = dict(m.words)
        self.table = np.concatenate([m.table[:k], np.zeros((self.bound - k, len(m.languages)), np.float32)])

    def unseen(self, word: str) -> np.ndarray:
        """Mean log frequency of the longest n-grams of the word that are known."""
        m, marked = self.model, f"<{word}>"
        for size in range(min(m.longest, len(marked)), 0, -1):
            rows = [r for i in range(len(marked) - size + 1) if (r := m.grams.get(marked[i : i + size])) is not None]
            if rows:
                return m.table[rows].mean(0)
        return m.floor

    def predict(self, text: str | None) -> tuple[str, float]:
        words = letter_words(text) if text else []
        if not words or not self.model.languages:
            return UNKNOWN, 0.0
        total = np.zeros(len(self.model.languages), np.float64)
        for at in range(0, len(words), 100_000):
            part = words[at : at + 100_000]
            new = set(part).difference(self.rows)
            if len(self.rows) + len(new) > self.bound:
                self.reset()
                new = set(part).difference(self.rows)
            for w in new:
                self.table[len(self.rows)] = self.unseen(w)
                self.rows[w] = len(self.rows)
            total += self.table[np.fromiter(map(self.rows.__getitem__, part), np.int64, len(part))].sum(0, dtype=np.float64)
        mean = total / len(words) * min(len(words), 12)
        odds = np.exp(mean - mean.max())
        best = int(np.argmax(total))
        return self.model.languages[best], float(odds[best] / odds.sum())


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text", whole_rows: bool = False) -> DataFrame:
    """doc_id, lang_pred and score (0 to 1) from the whole text alone, row by row.

    A text that is null or has no letter gets ``und`` and score 0; equal scores go to the
    language first in order. The score is the best language's share when the mean
    evidence of a word is weighed for at most twelve words. ``whole_rows`` gives all
    columns of ``docs`` instead of doc_id; a column of ``docs`` that bears one of the two
    names is an error then.
    """
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for batch in batches:
            said = [scorer.predict(text.as_py()) for text in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in kept), pa.array([x for x, _ in said], pa.string()), pa.array([s for _, s in said], pa.float64())], names)

    if whole_rows:
        read, at, kept = docs, docs.columns.index(text_col), range(len(docs.columns))
    else:
        read, at, kept = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")), 1, range(1)
    schema = StructType([*(read.schema.fields[k] for k in kept), StructField("lang_pred", StringType()), StructField("score", DoubleType())])
    names = schema.names
    if len(set(names)) < len(names):
        raise ValueError("a column of the documents is named as one of the prediction")
    return read.mapInArrow(lean(run), schema)


def held_out(id_col: str = "doc_id"):
    """Whether the remainder is 1; not so for a null id."""
    return (F.crc32(F.col(id_col).cast("string")) % 3).eqNullSafe(1)


def query(docs: DataFrame) -> DataFrame:
    """Fit on the documents that are not held out, predict for all."""
    model = fit(docs.filter(~held_out()))
    return identify(docs, model).withColumn("held_out", held_out()).select("doc_id", "held_out", "lang_pred", "score")
