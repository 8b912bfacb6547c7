"""Accuracy, diversity, signal and length measures over candidates, choices and traces."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from densesql.functions.text import ngrams, tokens
from densesql.plans.staging import Staging

#: Words of one pass of Self-BLEU, which shuffles as many n-grams of one size.
BLEU_PASS = 48 << 20


def execution_accuracy(selected: DataFrame, by: tuple[str, ...] = (), cube: bool = False) -> DataFrame:
    """(by..., n, ex) in per cent; ``cube`` adds every subtotal."""
    grouped = selected.cube(*by) if cube else selected.groupBy(*by)
    return grouped.agg(F.count(F.lit(1)).alias("n"), (100 * F.avg(F.col("correct").cast("double"))).alias("ex"))


def pass_at_k(cands: DataFrame, ks: tuple[int, ...], estimator: str = "empirical", by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., k, pass_at_k): share of questions with a correct one among k candidates.

    ``empirical`` looks at the first k; ``unbiased`` averages over all choices of k.
    """
    if estimator == "empirical":
        rank = F.row_number().over(Window.partitionBy(*by, "question_id").orderBy("rollout_id"))
        ranked = cands.withColumn("_r", rank).withColumn("k", F.explode(F.array(*map(F.lit, ks)))).where("_r <= k")
        per = ranked.groupBy(*by, "k", "question_id").agg(F.max("correct").cast("double").alias("p"))
    else:
        counts = cands.groupBy(*by, "question_id").agg(F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("c"))
        each = counts.withColumn("k", F.explode(F.array(*map(F.lit, ks))))
        first, miss = F.col("n") - F.col("c") + 1, F.lit(0.0)
        logs = F.aggregate(F.sequence(first, F.col("n")), miss, lambda s, i: s + F.log1p(-F.col("k") / i))
        per = each.withColumn("p", F.when(F.col("c") == 0, 0.0).when(F.col("n") - F.col("c") < F.col("k"), 1.0).otherwise(1.0 - F.exp(logs)))
    return per.groupBy(*by, "k").agg(F.avg("p").alias("pass_at_k"))


def syntax_error_rate(cands: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by..., n, parse, analyse, rate): candidates that fail to parse or analyse."""
    bad = F.col("status").isin("parse", "analyse", "forbidden")
    return cands.groupBy(*by).agg(
        F.count(F.lit(1)).alias("n"), F.count_if(F.col("status") == "parse").alias("parse"),
        F.count_if(F.col("status") == "analyse").alias("analyse"), F.avg(bad.cast("double")).alias("rate"),
    )


def exec_groups(cands: DataFrame, by: tuple[str, ...] = ("question_id",), approximate: bool = False) -> DataFrame:
    """(by..., groups): distinct results; a sketch where ``approximate``."""
    count = F.approx_count_distinct("result") if approximate else F.count_distinct("result")
    return cands.groupBy(*by).agg(count.alias("groups"))


def vote_profile(cands: DataFrame) -> DataFrame:
    """(question_id, k, groups, top_share, entropy): how votes spread over results."""
    sizes = cands.where("result is not null").groupBy("question_id", "result").agg(F.count(F.lit(1)).alias("n"))
    total = F.sum("n").over(Window.partitionBy("question_id"))
    shares = sizes.withColumn("p", F.col("n") / total)
    return shares.groupBy("question_id").agg(
        F.sum("n").alias("k"), F.count(F.lit(1)).alias("groups"), F.max("p").alias("top_share"), (-F.sum(F.col("p") * F.log("p"))).alias("entropy")
    )


def policy_variance(cands: DataFrame, reward: str = "total") -> DataFrame:
    """(question_id, reward_var, result_entropy)."""
    var = cands.groupBy("question_id").agg(F.var_pop(reward).alias("reward_var"))
    return var.join(vote_profile(cands).select("question_id", F.col("entropy").alias("result_entropy")), "question_id", "left").fillna(0.0, ["result_entropy"])


def signal_density(scored: DataFrame, reward: str) -> DataFrame:
    """One row: share of rollouts with a reward, and of groups whose rewards differ."""
    per = scored.groupBy("question_id").agg(F.stddev_pop(reward).alias("s"), F.avg((F.col(reward) > 0).cast("double")).alias("p"), F.count(F.lit(1)).alias("n"))
    return per.agg((F.sum(F.col("p") * F.col("n")) / F.sum("n")).alias("rollout_share"), F.avg((F.col("s") > 1e-12).cast("double")).alias("group_share"))


def ablation_delta(runs: DataFrame, full: str = "full") -> DataFrame:
    """(tier, variant, ex, delta) from (tier, variant, ex): each variant against the full reward."""
    base = runs.where(F.col("variant") == full).select("tier", F.col("ex").alias("full_ex"))
    return runs.join(base, "tier").select("tier", "variant", "ex", (F.col("ex") - F.col("full_ex")).alias("delta"))


def curve(steps: DataFrame, value: str = "ex", by: tuple[str, ...] = ("tier",)) -> DataFrame:
    """Add the change from the step before."""
    return steps.withColumn("change", F.col(value) - F.lag(value).over(Window.partitionBy(*by).orderBy("step")))


def trace_length(traces: DataFrame, by: tuple[str, ...], text: str = "trace", long: int = 8000) -> DataFrame:
    """(by..., n, mean, p50, longest, over): characters of traces and the share over ``long``."""
    size = F.length(text)
    return traces.groupBy(*by).agg(
        F.count(F.lit(1)).alias("n"), F.avg(size).alias("mean"), F.percentile(size, F.lit(0.5)).alias("p50"), F.max(size).alias("longest"),
        F.avg((size > long).cast("double")).alias("over"),
    )


def length_histogram(traces: DataFrame, text: str = "trace", low: float = 0, high: float = 8000, bins: int = 16) -> DataFrame:
    """(bin, n): bins 1..n inside the range, 0 and n+1 outside."""
    at = F.width_bucket(F.length(text).cast("double"), F.lit(float(low)), F.lit(float(high)), F.lit(bins))
    return traces.groupBy(at.alias("bin")).agg(F.count(F.lit(1)).alias("n"))


# --- Self-BLEU


def bleu(hypothesis: list[str], references: list[Counter], sizes: Iterable[int], order: int = 4, smooth: float = 0.1) -> float:
    """BLEU of tokens against the n-gram maxima of the references, with add-epsilon smoothing."""
    logs = 0.0
    for n in range(1, order + 1):
        own = Counter(tuple(hypothesis[k : k + n]) for k in range(len(hypothesis) - n + 1))
        hit = sum(min(c, references[n - 1].get(g, 0)) for g, c in own.items())
        total = max(1, sum(own.values()))
        logs += math.log((hit or smooth) / total)
    c = len(hypothesis)
    r = min(sizes, key=lambda s: (abs(s - c), s), default=c)
    penalty = 1.0 if c > r else math.exp(1 - r / c) if c else 0.0
    return penalty * math.exp(logs / order) if c else 0.0


def self_bleu_of(texts: list[list[str]], order: int = 4, smooth: float = 0.1) -> float:
    """Mean BLEU of each text against the others of its group.

    For every n-gram the two largest counts are kept: the largest count among the others is
    the second where the text holds the first, so a group costs its tokens and not its pairs.
    """
    if len(texts) < 2:
        return 0.0
    counts = [[Counter(tuple(t[k : k + n]) for k in range(len(t) - n + 1)) for n in range(1, order + 1)] for t in texts]
    tops: list[dict] = []
    for n in range(order):
        top: dict = {}
        for own in (c[n] for c in counts):
            for g, x in own.items():
                a, times, b = top.get(g, (0, 0, 0))
                top[g] = (x, 1, a) if x > a else (a, times + 1, b) if x == a else (a, times, max(b, x))
        tops.append(top)

    class Others(dict):
        def __init__(self, own: Counter, top: dict):
            self.own, self.top = own, top

        def get(self, g, default=0):
            a, times, b = self.top[g]
            return b if self.own[g] == a and times == 1 else a

    scores = []
    for i, t in enumerate(texts):
        refs = [Others(counts[i][n], tops[n]) for n in range(order)]
        scores.append(bleu(t, refs, [len(x) for j, x in enumerate(texts) if j != i], order, smooth))
    return sum(scores) / len(scores)


def _nearest_sizes(rows: DataFrame, by: str) -> DataFrame:
    """(by, c, r): for each size of a group's texts the nearest size among the group's others, the smaller of two."""
    sizes = rows.groupBy(by, "c").agg(F.count(F.lit(1)).alias("n"))
    order = Window.partitionBy(by).orderBy("c")
    near = sizes.withColumns({"low": F.lag("c").over(order), "high": F.lead("c").over(order)})
    lower = F.col("high").isNull() | (F.col("c") - F.col("low") <= F.col("high") - F.col("c"))
    return near.select(by, "c", F.when(F.col("n") > 1, F.col("c")).when(lower, F.col("low")).otherwise(F.coalesce("high", "c")).alias("r"))


def _clipped(rows: DataFrame, n: int, k: int, passes: int) -> DataFrame:
    """(_id, h): the n-grams of each text that its group's others hold, by the k-th of so many parts of their hashes.

    One shuffle, by the two hashes of group and n-gram, serves the counts and the order among a group's texts.
    """
    hashed = F.transform(ngrams(F.col("_toks"), n), lambda g: F.struct(F.xxhash64(F.lit(1), "_by", g).alias("g"), F.xxhash64(F.lit(2), "_by", g).alias("h")))
    each = rows.select("_id", F.inline(F.filter(hashed, lambda g: F.pmod(g["g"], F.lit(passes)) == k)))
    grams = each.repartition("g", "h").groupBy("g", "h", "_id").agg(F.count(F.lit(1)).alias("x"))
    w = Window.partitionBy("g", "h").orderBy(F.desc("x"), "_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    tops = grams.withColumns({"at": F.row_number().over(w), "top": F.first("x").over(whole), "second": F.nth_value("x", 2).over(whole)})
    others = F.when(F.col("at") == 1, F.col("second")).otherwise(F.col("top"))
    return tops.where("second is not null").groupBy("_id").agg(F.sum(F.least("x", others)).alias("h"))


def self_bleu(traces: DataFrame, by: str, text: str = "trace", order: int = 4, smooth: float = 0.1) -> DataFrame:
    """(by, k, self_bleu): the mean BLEU of each text against all others of its group, of any size.

    As in ``self_bleu_of`` the two largest counts of every n-gram of a group are enough.  Two
    hashes stand for an n-gram.  N-grams go in passes by size and hash, whose shuffles end one
    by one: their number changes what is on disk at once and nothing else.
    """
    staging = Staging(traces.sparkSession, "self-bleu")
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"(?U)[\s\x1c-\x1f]+"), lambda w: w != "")
    rows = staging.table(traces.select(F.col(by).alias("_by"), words.alias("_toks")), "rows", row_id="_id")
    rows = rows.withColumn("c", F.size("_toks"))
    passes = max(1, -(-(rows.agg(F.sum("c")).first()[0] or 0) // BLEU_PASS))
    hits = None
    for n in range(1, order + 1):
        for k in range(passes):
            new = staging.table(_clipped(rows, n, k, passes), f"hits-{n}-{k}").select("_id", F.lit(n).alias("n"), "h")
            hits = new if hits is None else hits.union(new)
    hits = hits.groupBy("_id").agg(*[F.sum(F.when(F.col("n") == n, F.col("h")).otherwise(0)).alias(f"h{n}") for n in range(1, order + 1)])
    near = _nearest_sizes(rows, "_by").select(F.col("_by").alias("_b"), F.col("c").alias("_c"), "r")
    each = rows.drop("_toks").join(hits, "_id", "left").join(near, F.col("_by").eqNullSafe(F.col("_b")) & (F.col("c") == F.col("_c")))
    logs = [F.log(F.when(F.col(f"h{n}") > 0, F.col(f"h{n}").cast("double")).otherwise(smooth) / F.greatest(F.lit(1), F.col("c") - (n - 1))) for n in range(1, order + 1)]
    penalty = F.when(F.col("c") > F.col("r"), 1.0).otherwise(F.exp(1 - F.col("r") / F.nullif("c", F.lit(0))))
    score = F.when(F.col("c") == 0, 0.0).otherwise(penalty * F.exp(sum(logs[1:], logs[0]) / order))
    per = each.select("_by", score.alias("s")).groupBy("_by").agg(F.count(F.lit(1)).alias("k"), F.avg("s").alias("s"))
    return per.select(F.col("_by").alias(by), "k", F.when(F.col("k") > 1, F.col("s")).otherwise(0.0).alias("self_bleu"))


def self_overlap(traces: DataFrame, by: str, key: str, text: str, n: int = 2) -> DataFrame:
    """(by, k, overlap): the relational form for one n: clipped n-gram precision against the group's other texts."""
    split = traces.withColumn("_toks", tokens(F.col(text)))  # a column of its own, so that it is computed once
    grams = split.select(by, key, F.explode(ngrams(F.col("_toks"), n)).alias("g")).groupBy(by, key, "g").agg(F.count(F.lit(1)).alias("c"))
    w = Window.partitionBy(by, "g")
    order = w.orderBy(F.desc("c"), key)
    tops = grams.withColumns({"top": F.max("c").over(w), "r": F.row_number().over(order)})
    second = F.max(F.when(F.col("r") == 2, F.col("c"))).over(w)
    clipped = tops.withColumn("others", F.when(F.col("r") == 1, F.coalesce(second, F.lit(0))).otherwise(F.col("top")))
    per = clipped.groupBy(by, key).agg((F.sum(F.least("c", "others")) / F.sum("c")).alias("p"))
    return per.groupBy(by).agg(F.count(F.lit(1)).alias("k"), F.avg("p").alias("overlap"))


def share(flag: Column) -> Column:
    return F.avg(flag.cast("double"))
