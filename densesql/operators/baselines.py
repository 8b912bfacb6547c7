"""The compared systems' ideas over derived candidates: repair, demonstrations, choosers, search, preferences."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from densesql.functions.similarity import jaccard
from densesql.functions.text import ngrams, tokens
from densesql.operators import corpus, execute, selection


def _columns_of(columns: DataFrame) -> dict[str, list[str]]:
    """Column names by database: the catalogue, which is small by nature."""
    found: dict[str, list[str]] = {}
    for db, name in columns.select("db_id", "column_name").distinct().collect():
        found.setdefault(db, []).append(name)
    return {db: sorted(names) for db, names in found.items()}


def _distance(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def repair_sql(sql: str, known: list[str]) -> str:
    """One repair: misspelt keywords, a missing bracket, an unknown column, a missing grouping."""
    import re

    from densesql.operators.sqlast import RESERVED, ParseError, lex

    text = re.sub(r"\bselct\b", "select", sql)
    text += ")" * max(0, text.count("(") - text.count(")"))
    try:
        words = {v for k, v in lex(text) if k == "word"}
    except ParseError:
        return text
    aliases = set(re.findall(r"\b(?:as|from|join)\s+(\w+)", text)) | set(re.findall(r"\b(?:from|join)\s+\w+\s+(\w+)", text))
    called = set(re.findall(r"\b(\w+)\s*\(", text))
    for w in sorted(words - RESERVED - set(known) - aliases - called):
        if "_" in w and known:
            text = re.sub(rf"\b{w}\b", min(known, key=lambda c: (_distance(w, c), c)), text)
    m = re.match(r"select\s+([\w.]+)\s*,\s*(count|sum|avg|min|max)\(.*\)\s+from\b", text)
    if m and " group by " not in text:
        text = re.sub(r"( having | order by | limit |$)", rf" group by {m[1]}\1", text, count=1)
    return text


def repair(spark: SparkSession, sf_dir: str, judged: DataFrame, questions: DataFrame, columns: DataFrame, rounds: int = 1) -> DataFrame:
    """Judged candidates after up to ``rounds`` repairs of those that failed, run again; ``repaired`` counts them."""
    known = _columns_of(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dbs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            fixed = [repair_sql(s, known.get(d, [])) for d, s in zip(dbs, texts, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fixed, pa.string())], names=["db_id", "sql", "fixed"])

    kept = [c for c in judged.columns if c not in ("status", "error_class", "n_rows", "result", "gold_result", "gold_rows", "correct")]
    out = judged.withColumn("repaired", F.lit(0))
    for _ in range(rounds):
        failed = out.where("status != 'runs'").select("db_id", "sql").distinct()
        fixes = failed.mapInArrow(run, "db_id string, sql string, fixed string").where("sql != fixed")
        again = out.join(fixes, ["db_id", "sql"], "left")
        changed = again.withColumns({"repaired": F.col("repaired") + F.col("fixed").isNotNull().cast("int"), "sql": F.coalesce("fixed", "sql")})
        out = execute.judge(spark, sf_dir, changed.select(*kept, "repaired"), questions)
    return out


def select_demos(questions: DataFrame, bank: DataFrame, k: int = 3, text: str = "question") -> DataFrame:
    """(question_id, demo_id, overlap, rank): the k most similar other questions by word overlap."""
    q = questions.select("question_id", F.array_distinct(tokens(F.col(text))).alias("a"))
    b = bank.select(F.col("question_id").alias("demo_id"), F.array_distinct(tokens(F.col(text))).alias("b"))
    shared = q.select("question_id", "a", F.explode("a").alias("w")).join(b.select("demo_id", "b", F.explode("b").alias("w")), "w").where("question_id != demo_id")
    pairs = shared.groupBy("question_id", "demo_id").agg(F.count(F.lit(1)).alias("n"), (F.first(F.size("a")) + F.first(F.size("b"))).alias("sizes"))
    scored = pairs.withColumn("overlap", F.col("n") / (F.col("sizes") - F.col("n")))
    order = Window.partitionBy("question_id").orderBy(F.round("overlap", 9).desc(), "demo_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("question_id", "demo_id", "overlap", "rank")


def _pairs(cands: DataFrame) -> DataFrame:
    """Ordered pairs of a question's candidates; a question has as many candidates as were sampled, a parameter."""
    a = cands.select("question_id", F.col("rollout_id").alias("a_id"), F.col("op_keys").alias("a_ops"))
    b = cands.select("question_id", F.col("rollout_id").alias("b_id"), F.col("op_keys").alias("b_ops"))
    return a.join(b, "question_id").where("a_id != b_id")


def medoid(cands: DataFrame) -> DataFrame:
    """(question_id, rollout_id, agreement): the candidate with the largest mean overlap with the others."""
    per = _pairs(cands).groupBy("question_id", "a_id").agg(F.avg(jaccard(F.col("a_ops"), F.col("b_ops"))).alias("agreement"))
    order = Window.partitionBy("question_id").orderBy(F.round("agreement", 9).desc(), "a_id")
    return per.withColumn("_r", F.row_number().over(order)).where("_r = 1").select("question_id", F.col("a_id").alias("rollout_id"), "agreement")


def tournament(cands: DataFrame, strength: str) -> DataFrame:
    """(question_id, rollout_id, wins): pairwise matches won by the larger ``strength``, ties to the smaller id."""
    s = F.round(F.col(strength).cast("double"), 9)
    a = cands.select("question_id", F.col("rollout_id").alias("a_id"), s.alias("a"))
    b = cands.select("question_id", F.col("rollout_id").alias("b_id"), s.alias("b"))
    won = (F.col("a") > F.col("b")) | ((F.col("a") == F.col("b")) & (F.col("a_id") < F.col("b_id")))
    wins = a.join(b, "question_id").where("a_id != b_id").groupBy("question_id", "a_id").agg(F.count_if(won).alias("wins"))
    best = F.max_by(F.struct(F.col("a_id").alias("rollout_id"), "wins"), F.struct("wins", -F.col("a_id"))).alias("b")
    return wins.groupBy("question_id").agg(best).select("question_id", "b.rollout_id", "b.wins")


def unit_test_vote(cands: DataFrame, tests: list[tuple[str, Column]]) -> DataFrame:
    """(question_id, rollout_id, passed): the candidate that passes most tests on its result's shape."""
    passed = sum((F.coalesce(t, F.lit(False)).cast("int") for _, t in tests), F.lit(0))
    scored = cands.withColumn("passed", passed)
    best = F.max_by(F.struct("rollout_id", "passed", "correct"), F.struct("passed", -F.col("rollout_id"))).alias("b")
    return scored.groupBy("question_id").agg(best).select("question_id", "b.*")


def shape_tests() -> list[tuple[str, Column]]:
    return [
        ("runs", F.col("status") == "runs"),
        ("has rows", F.col("n_rows") > 0),
        ("asks how many", ~F.col("question").rlike("(?i)^how many") | F.col("sql").rlike(r"(?i)count\(")),
        ("groups when each", ~F.col("question").rlike(r"(?i)\beach\b") | F.col("sql").rlike("(?i)group by|partition by")),
    ]


def valid_only(cands: DataFrame) -> DataFrame:
    """The first candidate that parses: what constrained decoding would have kept."""
    return selection.single(cands, "first_valid")


def search_pipelines(cands: DataFrame, question_text: DataFrame) -> DataFrame:
    """(config, ex, best): every combination of candidate count, layout filter and selector, measured on one pool."""
    rows = []
    for k in (1, 10, 30):
        for filtered in (False, True):
            pool = cands.where(F.col("rollout_id") < k)
            pool = pool.where("format_ok") if filtered else pool
            for how, chosen in (("vote", selection.majority(pool)), ("first", selection.single(pool)), ("logp", selection.single(pool, "best_logp"))):
                rows.append(chosen.agg(F.lit(f"k={k},filter={filtered},pick={how}").alias("config"), F.avg(F.col("correct").cast("double")).alias("ex"), F.count(F.lit(1)).alias("n")))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    total = question_text.count()
    scored = out.withColumn("ex", F.col("ex") * F.col("n") / total).drop("n")
    top = F.max(F.round("ex", 9)).over(Window.partitionBy(F.lit(1)))
    return scored.withColumn("best", F.round("ex", 9) == top)


def preference_pairs(scored: DataFrame, per_question: int | None = None) -> DataFrame:
    """(question_id, chosen, rejected, margin): every correct against every wrong candidate of a question.

    ``per_question`` keeps so many of a question's pairs in hash order, where a method samples them.
    """
    good = scored.where("correct").select("question_id", F.col("rollout_id").alias("chosen"), F.col("logp").alias("up"))
    bad = scored.where("not correct").select("question_id", F.col("rollout_id").alias("rejected"), F.col("logp").alias("down"))
    pairs = good.join(bad, "question_id")
    if per_question is not None:
        order = Window.partitionBy("question_id").orderBy(F.xxhash64("chosen", "rejected"), "chosen", "rejected")
        pairs = pairs.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= per_question)
    return pairs.select("question_id", "chosen", "rejected", (F.col("up") - F.col("down")).alias("margin"))


def preference_loss(pairs: DataFrame, beta: float = 0.1) -> DataFrame:
    """One row (n, loss): the logistic loss of the margins."""
    return pairs.agg(F.count(F.lit(1)).alias("n"), F.avg(F.log1p(F.exp(-F.lit(beta) * F.col("margin")))).alias("loss"))


def preference_loss_whole(scored: DataFrame, beta: float = 0.1) -> DataFrame:
    """``preference_loss`` over all pairs, from a question's different log-probabilities and how often each occurs."""
    good = scored.where("correct").groupBy("question_id", F.col("logp").alias("up")).agg(F.count(F.lit(1)).alias("a"))
    bad = scored.where("not correct").groupBy("question_id", F.col("logp").alias("down")).agg(F.count(F.lit(1)).alias("b"))
    both = good.join(bad, "question_id").withColumn("n", F.col("a") * F.col("b"))
    loss = F.log1p(F.exp(-F.lit(beta) * (F.col("up") - F.col("down"))))
    return both.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), (F.sum(loss * F.col("n")) / F.sum("n")).alias("loss"))


def step_check(trace: Column, sql: Column) -> Column:
    """A rule-based process check: the share of a trace's steps that name something in the statement."""
    steps = F.filter(F.split(trace, r"[.;]"), lambda s: F.trim(s) != "")
    used = F.filter(steps, lambda s: F.arrays_overlap(ngrams(tokens(s), 1), ngrams(tokens(sql), 1)))
    return F.when(F.size(steps) > 0, F.size(used) / F.size(steps)).otherwise(0.0)


def judge_cost(n_queries: int, price: float = 0.24) -> float:
    return n_queries * price


def tree_search(spark: SparkSession, sf_dir: str, questions: DataFrame, cands: DataFrame, rounds: int = 6, width: int = 4, explore: float = 1.4) -> DataFrame:
    """(question_id, sql, visits, value, correct): tree search from sampled candidates, all questions advancing together.

    A node is a statement; the root is the question's first candidate of ``cands``.  Expanding
    a node adds one more sampled candidate and rewrites of the node; the gold is never seen.
    A node's reward is the share of the question's visited statements with the same result.  Each round picks every question's
    best node by upper confidence bound, expands ``width`` children, runs them in one batch
    and backs the rewards up to the parents.
    """
    db = {r["question_id"]: r["db_id"] for r in questions.select("question_id", "db_id").collect()}  # the question set, which is authored
    pools: dict[int, list[str]] = {q: [] for q in db}
    for r in cands.where(F.col("rollout_id") <= rounds).select("question_id", "rollout_id", F.coalesce("sql", F.lit("")).alias("sql")).orderBy("question_id", "rollout_id").collect():
        pools[r["question_id"]].append(r["sql"])
    nodes: dict[int, list[dict]] = {q: [{"sql": pool[0], "parent": None, "visits": 1, "value": 0.0}] for q, pool in pools.items() if pool}
    moves = ("M07", "M06", "M10", "M13", "M12", "M02", "M04", "M09")
    seen: dict[tuple[str, str], str | None] = {}
    for turn in range(rounds):
        fresh = []
        for q, tree in nodes.items():
            total = sum(n["visits"] for n in tree)
            best = max(range(len(tree)), key=lambda k: (tree[k]["value"] / tree[k]["visits"] + explore * (max(1.0, total) ** 0.5) / (1 + tree[k]["visits"]), -k))
            base = tree[best]["sql"]
            for w in range(width):
                child = corpus.mutate(base, moves[int(corpus.draw(q, turn, w) * len(moves))]) if w else pools[q][min(turn + 1, len(pools[q]) - 1)]
                tree.append({"sql": child, "parent": best, "visits": 0, "value": 0.0})
                fresh.append((db[q], child))
        todo = [x for x in dict.fromkeys(fresh) if x not in seen]
        ran = execute.run(spark, sf_dir, spark.createDataFrame(todo, "db_id string, sql string")) if todo else None
        for r in ran.collect() if ran is not None else []:
            seen[(r["db_id"], r["sql"])] = f"{r['n_cols']}:{r['n_rows']}:{r['h_a']}" if r["status"] == "runs" else None
        for q, tree in nodes.items():
            results = [seen.get((db[q], n["sql"])) for n in tree]
            for k in range(len(tree) - width, len(tree)):
                reward = sum(r == results[k] for r in results) / len(results) if results[k] else 0.0
                at: int | None = k
                while at is not None:
                    tree[at]["visits"] += 1
                    tree[at]["value"] += reward
                    at = tree[at]["parent"]
    out = []
    for q, tree in nodes.items():
        pick = max(tree, key=lambda n: (n["value"] / max(1, n["visits"]), n["visits"]))
        out.append((q, db[q], pick["sql"], pick["visits"], pick["value"]))
    chosen = spark.createDataFrame(out, "question_id long, db_id string, sql string, visits int, value double")
    return execute.judge(spark, sf_dir, chosen, questions).select("question_id", "sql", "visits", "value", "correct")
