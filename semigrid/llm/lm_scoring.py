"""Masked pseudo-likelihood: a bidirectional window network predicts every token from both sides.

A token is a word, and every word of the corpus has a probability of its own: the network
gives that of its class from the classes on both sides, and the counts of all words give that
of the word within its class. The counts are a table as large as the vocabulary, however
large that is; only words frequent enough for a bounded list travel with the code, the
occurrences of all others are joined with the table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semigrid.functions.worker import lean, small_batches
from semigrid.plans.scratch import materialize, text_or_empty

#: Token classes: one for the edge of a text, some for unknown words by their length, the rest for frequent words.
CLASSES, LENGTHS = 128, 23
#: About so many words, the most frequent, travel to every worker with their probabilities.
CARRIED = 200_000


class TokenClasses(dict):
    """Word to class; words outside the vocabulary go by their length."""

    def __init__(self, vocabulary: list[str], lengths: int = LENGTHS):
        super().__init__((w, 1 + lengths + k) for k, w in enumerate(vocabulary))
        self.lengths = lengths

    def __missing__(self, word: str) -> int:
        return min(len(word), self.lengths)

    def of(self, text: str) -> np.ndarray:
        words = text.split()
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


def word_counts(docs: DataFrame, text_col: str = "text", held: int = 150_000) -> DataFrame:
    """(word, n) over all words of all texts; tasks hold ``held`` words at most before they send counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from collections import Counter

        def sent() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(counts), pa.string()), pa.array(list(counts.values()), pa.int64())], ["word", "n"])

        counts: Counter = Counter()
        for batch in batches:
            for text in batch.column(0):
                counts.update(text.as_py().split())
                if len(counts) > held:
                    yield sent()
                    counts.clear()
        yield sent()

    return docs.select(text_or_empty(docs[text_col]).alias("text")).mapInArrow(lean(run), "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def window_counts(docs: DataFrame, classes: TokenClasses, size: int = CLASSES, text_col: str = "text") -> DataFrame:
    """(window, n): how often a class stands between two others, over every token of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(size**3, np.int64)
        held: list[np.ndarray] = []
        room = 2_000_000

        def add() -> None:
            if held:
                seen[:] += np.bincount(np.concatenate(held), minlength=size**3)
                held.clear()

        for batch in batches:
            for text in batch.column(0):
                codes = _windows(classes.of(text.as_py()), size)
                held.append(codes)
                room -= len(codes)
                if room < 0:
                    add()
                    room = 2_000_000
        add()
        at = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(seen[at], pa.int64())], ["window", "n"])

    return docs.select(text_or_empty(docs[text_col]).alias("text")).mapInArrow(lean(run), "window long, n long").groupBy("window").agg(F.sum("n").alias("n"))


def _windows(ids: np.ndarray, size: int) -> np.ndarray:
    """left * size^2 + right * size + middle for each token; the edge class stands outside the text."""
    edged = np.zeros(len(ids) + 2, np.int64)
    edged[1:-1] = ids
    return (edged[:-2] * size + edged[2:]) * size + edged[1:-1]


@dataclass
class WindowNetwork:
    """Embeds the token on each side, adds them, squashes, and scores every class for the middle."""

    left: np.ndarray
    right: np.ndarray
    bias: np.ndarray
    out: np.ndarray
    out_bias: np.ndarray

    @classmethod
    def fresh(cls, size: int, width: int, seed: int) -> WindowNetwork:
        r = np.random.default_rng(seed)
        init = lambda *shape: r.normal(0, 0.3, shape)
        return cls(init(size, width), init(size, width), np.zeros(width), init(width, size), np.zeros(size))

    def log_probs(self) -> np.ndarray:
        """log P(middle | left, right) for every pair of sides, (size * size, size)."""
        size, width = self.left.shape
        hidden = np.tanh(self.left[:, None] + self.right[None] + self.bias).reshape(size * size, width)
        logits = hidden @ self.out + self.out_bias
        logits -= logits.max(1, keepdims=True)
        return logits - np.log(np.exp(logits).sum(1, keepdims=True))

    def gradient(self, counts: np.ndarray) -> tuple[float, list[np.ndarray]]:
        """Mean loss over all counted windows and its gradient; ``counts`` is (sides, middle)."""
        size, width = self.left.shape
        total, each = counts.sum(), counts.sum(1)
        hidden = np.tanh(self.left[:, None] + self.right[None] + self.bias).reshape(size * size, width)
        logits = hidden @ self.out + self.out_bias
        logits -= logits.max(1, keepdims=True)
        p = np.exp(logits)
        norm = p.sum(1, keepdims=True)
        loss = -float((counts * (logits - np.log(norm))).sum() / total)
        d = (p / norm * each[:, None] - counts) / total
        d_hidden = (d @ self.out.T * (1 - hidden**2)).reshape(size, size, width)
        return loss, [d_hidden.sum(1), d_hidden.sum(0), d_hidden.sum((0, 1)), hidden.T @ d, d.sum(0)]

    def train(self, counts: np.ndarray, steps: int, rate: float = 0.05) -> list[float]:
        """Adam on the whole corpus at each step: the counts are all that the loss depends on."""
        values = [self.left, self.right, self.bias, self.out, self.out_bias]
        first, second, losses = [np.zeros_like(v) for v in values], [np.zeros_like(v) for v in values], []
        for t in range(1, steps + 1):
            loss, slopes = self.gradient(counts)
            losses.append(loss)
            for v, g, m, s in zip(values, slopes, first, second):
                m += 0.1 * (g - m)
                s += 0.01 * (g * g - s)
                v -= rate * (m / (1 - 0.9**t)) / (np.sqrt(s / (1 - 0.99**t)) + 1e-9)
        return losses


@dataclass
class WordModel:
    """Classes and network; counts of all words as a table (word, n); tokens in each class; words in ``carried`` have over ``rare`` tokens."""

    classes: TokenClasses
    network: WindowNetwork
    counts: DataFrame
    totals: np.ndarray
    carried: dict[str, int]
    rare: int


def fit(docs: DataFrame, text_col: str = "text", width: int = 24, steps: int = 60, seed: int = 7, carried: int = CARRIED) -> WordModel:
    """Word counts and network from the whole corpus.

    The window is one token on either side, so the counts of (left, middle, right)
    classes are sufficient for the network's likelihood: they are gathered from every token
    of every document, and the network is trained on them in full batches. What comes to
    the driver is bounded by the classes cubed and twice ``carried`` words.
    """
    small_batches(docs.sparkSession)
    counts = materialize(word_counts(docs, text_col), "counts")
    top = counts.orderBy(F.desc("n"), "word").limit(CLASSES - 1 - LENGTHS).collect()
    classes = TokenClasses([r["word"] for r in top])
    own = {r["word"]: r["n"] for r in top}
    total = np.zeros(CLASSES)
    by_length = counts.groupBy(F.least(F.length("word"), F.lit(LENGTHS)).alias("k")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("words")).collect()
    for r in by_length:
        total[r["k"]] = r["n"]
    for w, n in own.items():
        total[min(len(w), LENGTHS)] -= n
        total[classes[w]] = n
    words, rare = sum(r["words"] for r in by_length), 0
    if words > carried:
        rare = counts.agg(F.percentile_approx("n", 1 - carried / words, 10_000)).first()[0]
        while counts.filter(F.col("n") > rare).count() > 2 * carried:  # the percentile is not exact
            rare *= 2
    often = counts.filter(F.col("n") > rare).toArrow()
    found = window_counts(docs, classes, CLASSES, text_col).toPandas()
    seen = np.zeros(CLASSES**3)
    seen[found["window"].to_numpy(np.int64)] = found["n"].to_numpy(np.float64)
    network = WindowNetwork.fresh(CLASSES, width, seed)
    if len(found):
        network.train(seen.reshape(CLASSES**2, CLASSES), steps)
    return WordModel(classes, network, counts, total, dict(zip(often["word"].to_pylist(), often["n"].to_pylist())) | own, rare)


def score(docs: DataFrame, model: WordModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, pseudo_log_likelihood (the sum over all tokens) and mean_log_prob.

    A token is a word between white space, predicted with itself masked. A null or empty
    text has no token and scores 0 in both; repeated rows score alike; other columns
    are not read. A word that the model has not counted is taken as one token of its class.

    One pass over the texts gives a row for each document, with the part of its sum that
    the carried words and the network give, and one for each of its rarer words; those are
    joined with the counts, and summed for each document.
    """
    small_batches(docs.sparkSession)
    table = model.network.log_probs().astype(np.float32).ravel()
    vocabulary, lengths = list(model.classes), model.classes.lengths
    totals = np.maximum(model.totals, 1.0)
    words = list(model.carried)
    logs = np.log(np.array([model.carried[w] for w in words], np.float64) / totals[[model.classes[w] for w in words]]).astype(np.float32)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from collections import Counter

        from pyspark import TaskContext

        classes, known = TokenClasses(vocabulary, lengths), dict(zip(words, logs.tolist()))
        row = TaskContext.get().partitionId() << 40
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.string(), pa.int64())
        for batch in batches:
            out: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text = text.as_py()
                codes, said = _windows(classes.of(text), CLASSES), text.split()
                within = np.fromiter(map(known.get, said, repeat(1.0)), np.float64, len(said))  # logs are not over zero
                other = within > 0
                rarer = Counter(said[k] for k in np.flatnonzero(other))
                out.append((row, doc, len(said), float(table[codes].sum(dtype=np.float64) + within[~other].sum()), None, None))
                out += [(row, None, None, None, w, m) for w, m in rarer.items()]
                row += 1
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], ["row", "doc_id", "n_tokens", "total", "word", "m"])

    read = docs.select(docs[id_col].cast("long").alias("doc_id"), text_or_empty(docs[text_col]).alias("text"))
    parts = materialize(read.mapInArrow(lean(run), "row long, doc_id long, n_tokens long, total double, word string, m long"), "parts")
    rarer = parts.filter("word is not null").select("row", "word", "m").join(model.counts, "word", "left")
    whole = F.element_at(F.array(*[F.lit(float(totals[k])) for k in range(1, LENGTHS + 1)]), F.least(F.length("word"), F.lit(LENGTHS)))
    sums = rarer.groupBy("row").agg(F.sum(F.col("m") * F.log(F.coalesce("n", F.lit(1)) / whole)).alias("more"))
    scored = parts.filter("word is null").select("row", "doc_id", "n_tokens", "total").join(sums, "row", "left")
    sum_ = F.col("total") + F.coalesce("more", F.lit(0.0))
    mean = F.when(F.col("n_tokens") > 0, F.col("pseudo_log_likelihood") / F.col("n_tokens")).otherwise(0.0)
    return scored.select("doc_id", "n_tokens", sum_.alias("pseudo_log_likelihood")).withColumn("mean_log_prob", mean)


def query(docs: DataFrame) -> DataFrame:
    return score(docs, fit(docs))
