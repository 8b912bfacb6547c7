"""Quality rules with risk-controlled thresholds.

Base rules reject very short texts and texts that mostly repeat themselves.  Further
rules measure a text in thousandths (marks, capitals, repeated words, repeated lines).
A text's severity is the largest of the four, each at a fixed weight, and the method
rejects from a cutoff of severity up, so one cutoff stands for all rules together.
Cutoffs come from the labelled documents alone: for each stratum (language) they are
tested from the strictest down with the exact binomial law, at most ``alpha`` of the
stratum's good documents being rejected by any rule, and the first failure ends the
sequence, which needs no further correction.  Across strata the error ``delta`` is
divided by their number.  All certified cutoffs hold at once, so any may be chosen: the
one that catches the most bad labelled documents less the good ones, the mildest at a
tie.  A stratum with too few labels to certify anything gets no cutoff.

The guarantee is on good documents that pass the base rule, which is given and has no
parameter; what it rejects is not the method's to limit.  A doc_id counts once, by the
highest severity of its rows, so repeated rows add nothing to the law's sample.  Labels
are joined to all documents and counted per value of severity.  A doc_id whose labels
disagree, or without a label, does not count.

Defined results: a null or empty text has no words and fails the base rule; a null
language is a stratum of its own; a null doc_id has no label; repeated rows give one
result row each; other columns are ignored.
"""

from __future__ import annotations

import math
import string
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import documents, map_rows, numbered
from densesql.plans.staging import Staging

# The base rule.
SYMBOLS, WINDOW, LEAST_WORDS, MOST_REPEATED = "#*$%&|<>", 8, 20, 30

SPACES = " \t\n\x0b\x0c\r"
#: Marks that running text seldom has.
MARKS = "".join(c for c in string.punctuation if c not in ".,'-").encode()
CAPITALS = string.ascii_uppercase.encode()
#: The rules and the weight of each in a text's severity.
RULES = {"marks": 4, "capitals": 2, "repeats": 1, "lines": 1}

#: False rejection allowed to all rules together in a stratum, and the chance that any bound fails.
ALPHA, DELTA = 0.02, 0.05
#: Up to so many strata the cutoffs are broadcast; beyond that they are joined.
BROADCAST_STRATA = 10_000

MEASURED = (
    "doc_id long, stratum string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, marks int, capitals int, repeats int, lines int"
)


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside windows that occur at least twice; exact, by ranks of doubled spans."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    seen: dict[bytes, int] = {}
    rank = np.fromiter((seen.setdefault(w, len(seen)) for w in words), dtype=np.int64, count=len(words))
    span = 1
    while span < window:
        step = min(span, window - span)
        paired = rank[: len(rank) - step] * (int(rank.max()) + 1) + rank[step:]
        _, rank = np.unique(paired, return_inverse=True)
        span += step
    twice = np.flatnonzero(np.bincount(rank)[rank] > 1)
    edges = np.zeros(len(words) + 1, dtype=np.int64)
    np.add.at(edges, twice, 1)
    np.add.at(edges, twice + window, -1)
    return int(np.count_nonzero(np.cumsum(edges)))


def measure(text: str | None) -> tuple:
    """The base measures, the base verdict and the four rule values of a text."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    n_words, word_chars = len(words), len(text) - sum(map(text.count, SPACES))
    n_symbols = sum(map(text.count, SYMBOLS))
    lines = [line for line in text.split("\n") if line.strip(SPACES)]
    n_dup = len(lines) - len(set(lines))
    n_repeat = repeated_words(words)
    failed = n_words < LEAST_WORDS or 100 * n_repeat > MOST_REPEATED * n_words
    marks, capitals = (len(raw) - len(raw.translate(None, c)) for c in (MARKS, CAPITALS))
    values = (1000 * a // max(1, b) for a, b in ((marks, word_chars), (capitals, word_chars), (n_repeat, n_words), (n_dup, len(lines))))
    return n_words, word_chars, n_symbols, n_dup, n_repeat, failed, *values


def measured(docs: DataFrame, stratum: str = "lang", carry: tuple[str, ...] = ()) -> DataFrame:
    def make() -> Callable:
        def step(ids, groups, texts):
            return [(i, "1" if g is None else f"0{g}", *measure(t)) for i, g, t in zip(ids, groups, texts, strict=True)]

        return step

    return map_rows(docs, ["doc_id", stratum, "text"], MEASURED, make, carry)


# --- exact binomial bounds --------------------------------------------------------------


def binomial_cdf(k: int, n: int, p: float) -> float:
    """P(X <= k) for X binomial, by the continued fraction of the incomplete beta function."""
    if k < 0:
        return 0.0
    if k >= n:
        return 1.0
    a, b, x = float(n - k), float(k + 1), 1.0 - p
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    if x > (a + 1) / (a + b + 2):
        return 1.0 - front * _fraction(b, a, 1.0 - x) / b
    return front * _fraction(a, b, x) / a


def _fraction(a: float, b: float, x: float) -> float:
    tiny = 1e-300
    c, d = 1.0, 1.0 / (1.0 - (a + b) * x / (a + 1.0) or tiny)
    value = d
    for m in range(1, 100_000):
        for term in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1.0 / (1.0 + term * d or tiny)
            c = 1.0 + term / c or tiny
            value *= c * d
        if abs(c * d - 1.0) < 1e-14:
            break
    return value


def most_rejections(n: int, alpha: float, delta: float) -> int:
    """The largest k with P(X <= k) <= delta for X binomial(n, alpha); -1 if even 0 is too likely."""
    low, high = -1, n
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (mid, high) if binomial_cdf(mid, n, alpha) <= delta else (low, mid)
    return low


def pick_cutoff(values: np.ndarray, good: np.ndarray, bad: np.ndarray, alpha: float, delta: float) -> int | None:
    """The cutoff for one stratum from label counts by value; None if none is certified or worth it."""
    allowed = most_rejections(int(good.sum()), alpha, delta)
    order = np.argsort(-values, kind="stable")
    values, good, bad = values[order], np.cumsum(good[order]), np.cumsum(bad[order])
    certified = (good <= allowed) & (values > 0)
    worth = np.where(certified, bad - good, 0)
    return int(values[worth.argmax()]) if worth.size and worth.max() > 0 else None


def severity() -> Column:
    return F.greatest(*[F.col(rule) * weight for rule, weight in RULES.items()])


def cutoffs(rows: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """(stratum, cut) with null where nothing is certified."""
    agreed = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("lo"), F.max("quality").alias("hi"))
    agreed = agreed.where("lo = hi").select("doc_id", F.col("lo").alias("quality"))
    held = rows.where("not base_failed").select("doc_id", "stratum", severity().alias("value")).join(agreed, "doc_id")
    once = held.groupBy("stratum", "doc_id", "quality").agg(F.max("value").alias("value"))
    counts = once.groupBy("stratum", "value").agg(F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("quality") != 1).alias("bad"))
    share = delta / max(1, rows.select("stratum").distinct().count())

    def choose(pdf: pd.DataFrame) -> pd.DataFrame:
        cut = pick_cutoff(pdf["value"].to_numpy(), pdf["good"].to_numpy(), pdf["bad"].to_numpy(), alpha, share)
        return pd.DataFrame({"stratum": [pdf["stratum"].iloc[0]], "cut": pd.Series([cut], dtype="Int32")})

    return counts.groupBy("stratum").applyInPandas(choose, "stratum string, cut int")


def judge(rows: DataFrame, labels: DataFrame, staging: Staging, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """``rows`` (staged, from ``measured``) with a boolean column ``kept``."""
    cuts = staging.table(cutoffs(rows, labels, alpha, delta).withColumnRenamed("stratum", "cut_stratum"), "cuts")
    cuts = F.broadcast(cuts) if cuts.count() <= BROADCAST_STRATA else cuts
    joined = rows.join(cuts, F.col("stratum") == F.col("cut_stratum"), "left")
    return joined.withColumn("kept", ~(F.col("base_failed") | F.coalesce(severity() >= F.col("cut"), F.lit(False)))).select(*rows.columns, "kept")


def quality(docs: DataFrame, labels: DataFrame, stratum: str = "lang", alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """Measures, base verdict and verdict for every document."""
    staging = Staging(docs.sparkSession, "quality")
    return judge(staging.table(measured(docs, stratum), "measured"), labels, staging, alpha, delta)


def keep_good(docs: DataFrame, labels: DataFrame, stratum: str = "lang", alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """The rows that pass, with the columns of ``docs``."""
    staging = Staging(docs.sparkSession, "quality")
    own, names = numbered(docs, "doc_id", stratum, "text")
    judged = judge(staging.table(measured(own, stratum, tuple(names)), "measured"), labels, staging, alpha, delta)
    return judged.where("kept").select(*[f"k{n}" for n in range(len(names))]).toDF(*docs.columns)


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality(documents(spark, sf_dir), documents(spark, sf_dir, "labels"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
