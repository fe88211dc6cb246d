"""URL filter: host and path rules, then logistic regression on hashed character n-grams."""

from __future__ import annotations

import hashlib
import random
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


#: The rules of the contract.
RULES = (
    UrlRule("allow", "org", "/"),
    UrlRule("block", "example.org", "/es/"),
    UrlRule("block", "example.org", "/en/1"),
    UrlRule("allow", "com", "/fr/"),
    UrlRule("block", "com", "/de/"),
)

#: Words in addresses of either class of the labelled table, and syllables of hosts that tell nothing.
BAD = ("casino", "poker", "slots", "jackpot", "bets", "bonus", "pills", "loans", "xxx", "cams", "clicks", "track", "ads", "cheap", "free", "win", "spam", "warez")
GOOD = ("news", "library", "garden", "weather", "history", "university", "docs", "science", "recipes", "museum", "school", "travel", "music", "health", "forum", "archive", "kitchen", "station")
SYLLABLES = ("th", "er", "on", "an", "re", "he", "st", "en", "at", "nd", "ti", "es", "or", "sh", "ly", "wh", "ing", "ion")


def labelled_urls(rows: int = 600, seed: int = 11) -> list[tuple[str, int]]:
    """(url, 1 to block): the small labelled table, drawn by a rule; any table of this shape may be given instead.

    Words of a class stand in the host or in the path, or both; the other part is made of
    syllables and numbers that occur in either class. Half of the rows are of each class.
    """
    r, out = random.Random(seed), []
    plain = lambda: "".join(r.choice(SYLLABLES) for _ in range(r.randint(2, 4)))
    for k in range(rows):
        words = (GOOD, BAD)[k % 2]
        told = lambda: r.choice(words) + r.choice(("", "-", "")) + r.choice((plain(), r.choice(words), ""))  # noqa: B023, E731
        in_host, in_path = r.choice(((True, True), (True, False), (True, False), (False, True)))
        host = r.choice(("www.", "m.", "blog.", "")) + (told() if in_host else plain()).strip("-") + "." + r.choice(("example.net", "example.com", "test"))
        path = r.choice(("en", "de", "fr", "es")) + "/" + (told().strip("-") if in_path else str(r.randint(1, 999))) + r.choice(("", "/", ".html"))
        out.append((f"{r.choice(('http', 'https'))}://{host}/{path}", k % 2))
    return out


LABELLED = tuple(labelled_urls())

GRAM_SIZES = (3, 4)
BUCKETS = 2048
#: Weights are whole numbers of this unit, so that sums do not depend on their order.
UNIT = 1 << 16


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first ``://`` to ``/``, ``?``, ``#`` or the end; path: on to ``?``, ``#`` or the end."""
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    part = lambda k: F.coalesce(F.regexp_extract(url, pattern, k), F.lit(""))
    return F.translate(part(1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), part(2)


def _split(url: str) -> tuple[str, str]:
    if "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host, tail = rest[:cut], rest[cut:]
    cut = min([tail.find(c) for c in "?#" if c in tail], default=len(tail))
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host), tail[:cut]


def _bucket(gram: str) -> int:
    return int(hashlib.md5(gram.encode()).hexdigest()[:4], 16) % BUCKETS


def _buckets(text: str) -> list[int]:
    return [_bucket(text[i : i + n]) for n in GRAM_SIZES for i in range(len(text) - n + 1)]


def train(labelled=LABELLED, steps: int = 400, rate: float = 4.0, decay: float = 1e-3, most: int = 100_000) -> tuple[list[int], int]:
    """Weights and bias in units, by gradient descent over at most ``most`` labelled rows.

    Features are gram shares: each gram counts 1 / number of grams of its url.
    """
    rows = list(labelled)[:most]
    x, y = np.zeros((len(rows), BUCKETS)), np.array([r[1] for r in rows], float)
    for k, (url, _) in enumerate(rows):
        host, path = _split(url)
        found = _buckets(f"^{host}|{path}$")
        np.add.at(x[k], found, 1 / max(1, len(found)))
    w, b = np.zeros(BUCKETS), 0.0
    scale = 50.0  # shares are small; larger features let few steps do
    for _ in range(steps):
        p = 1 / (1 + np.exp(-(scale * (x @ w) + b)))
        w -= rate * (scale * (x.T @ (p - y)) / len(y) / scale + decay * w)
        b -= rate * (p - y).mean()
    return [int(v) for v in np.rint(w * scale * UNIT)], int(np.rint(b * UNIT))


def held_out_accuracy(labelled=LABELLED, parts: int = 4) -> float:
    """Share of labelled rows judged right by a model that saw no url of their host: cross-validation over hosts."""
    part = lambda url: int(hashlib.md5(_split(url)[0].encode()).hexdigest()[:8], 16) % parts
    right = 0
    for k in range(parts):
        weights, bias = train([x for x in labelled if part(x[0]) != k])
        for url, label in (x for x in labelled if part(x[0]) == k):
            host, path = _split(url)
            found = _buckets(f"^{host}|{path}$")
            right += (sum(weights[b] for b in found) + max(1, len(found)) * bias > 0) == (label == 1)
    return right / len(labelled)


def _score(host: Column, path: Column, weights: list[int], bias: int) -> Column:
    """The log-odds, times the number of grams, in units."""
    table = F.split(F.lit(",".join(map(str, weights))), ",").cast("array<bigint>")  # folded into a literal
    text = F.concat(F.lit("^"), host, F.lit("|"), path, F.lit("$"))
    total, grams = F.lit(0).cast("long"), F.lit(0).cast("long")

    def weight(n: int):
        return lambda i: F.get(table, F.conv(F.substring(F.md5(F.substring(text, i, F.lit(n))), 1, 4), 16, 10).cast("int") % BUCKETS)

    for n in GRAM_SIZES:
        count = F.greatest(F.length(text) - (n - 1), F.lit(0))
        found = F.when(count > 0, F.transform(F.sequence(F.lit(1), count), weight(n)))
        total += F.coalesce(F.aggregate(found, F.lit(0).cast("long"), lambda a, v: a + v), F.lit(0))
        grams += count
    return total + F.greatest(grams, F.lit(1)) * bias


def url_filter(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES, labelled=LABELLED, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, score and verdict for each row of ``pages``.

    A rule fits its host and all subdomains when the path starts with the rule's; the
    longest rule decides, of equally long ones the last in order of text. Elsewhere the verdict is the classifier's: block when its
    log-odds are over zero. A null url, or one without ``://``, has an empty host and
    path. Repeated rows are judged alike; other columns are not read. Every step on
    the pages is a native expression in one projection; nothing is shuffled.
    """
    weights, bias = train(labelled)
    host, path = host_and_path(F.col("url"))
    parts = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url")).select("page_id", host.alias("host"), path.alias("path"))
    fits = lambda r: ((F.col("host") == r.host) | F.col("host").endswith("." + r.host)) & F.col("path").startswith(r.path)
    rule, verdict = F.lit(None).cast("string"), F.when(F.col("score") > 0, "block").otherwise("allow")
    for r in sorted(rules, key=lambda r: (len(r.text), r.text)):
        rule = F.when(fits(r), F.lit(r.text)).otherwise(rule)
        verdict = F.when(fits(r), F.lit(r.verdict)).otherwise(verdict)
    scored = parts.withColumn("score", _score(F.col("host"), F.col("path"), weights, bias))
    return scored.select("page_id", "host", "path", rule.alias("rule"), "score", verdict.alias("verdict"))


def oracle() -> str:
    weights, bias = train()
    grams = " + ".join(f"greatest(length(x) - {n - 1}, 0)" for n in GRAM_SIZES)
    sums = " + ".join(f"coalesce(list_sum([w[1 + ('0x' || md5(substr(x, i, {n}))[1:4])::INT % {BUCKETS}] FOR i IN range(1, length(x) - {n - 2})]), 0)" for n in GRAM_SIZES)
    fits = lambda r: f"(host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}')"
    ordered = sorted(RULES, key=lambda r: (len(r.text), r.text), reverse=True)
    rule = " ".join(f"WHEN {fits(r)} THEN '{r.text}'" for r in ordered)
    verdict = " ".join(f"WHEN {fits(r)} THEN '{r.verdict}'" for r in ordered)
    return f"""
WITH u AS (SELECT page_id, coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', ['a', 'b']), {{'a': '', 'b': ''}}) AS p FROM pages),
h AS (SELECT page_id, translate(p.a, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, p.b AS path FROM u),
t AS (SELECT *, '^' || host || '|' || path || '$' AS x, {weights}::BIGINT[] AS w FROM h),
s AS (SELECT page_id, host, path, CAST({sums} + greatest({grams}, 1) * {bias} AS BIGINT) AS score FROM t)
SELECT page_id, host, path, CASE {rule} END AS rule, score, CASE {verdict} WHEN score > 0 THEN 'block' ELSE 'allow' END AS verdict FROM s
"""
