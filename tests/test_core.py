"""Worked numbers, parser rows, mutation properties and brute-force checks of the core methods."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from densesql.functions import completion as C
from densesql.functions import similarity as S
from densesql.functions import text as T
from densesql.operators import (
    atoms, baselines, corpus, embed, execute, grpo, memory, metrics, relational, rewards, selection, setjoin, sft,
)
from densesql.operators.sqlast import ParseError, parse
from densesql.queries.rewards import COMPLETIONS


def keys(sql, **options):
    return {o.key for o in atoms.operations(sql, atoms.Options(**options))}


def overlap(a, b, **options):
    x, y = keys(a, **options), keys(b, **options)
    return len(x & y) / len(x | y) if x | y else 0.0


GOLD = "select c_mktsegment, avg(c_acctbal) from customer group by c_mktsegment"


def test_worked_overlaps():
    assert overlap(GOLD, "select c_mktsegment, count(*) from customer group by c_mktsegment") == 0.6
    assert overlap(GOLD, "select c_mktsegment, avg(c_acctbal) from customer") == 0.75
    assert overlap(GOLD, "select c_mktsegment, avg(c_acctbal) from (customer") == 0


def test_alias_and_operand_options():
    a = "select o.o_orderkey from orders o join customer c on o.o_custkey = c.c_custkey"
    b = "select x.o_orderkey from orders x join customer y on y.c_custkey = x.o_custkey"
    assert overlap(a, b) < 1 and overlap(a, b, alias="resolved", commute=True) == 1


@pytest.mark.parametrize(
    "sql,kinds",
    [
        ("select a from t", {"from.table", "select.column"}),
        ("select distinct a, b + 1 from t", {"select.distinct", "select.expression"}),
        ("select a from t x left join u on x.i = u.i and x.j > u.j", {"from.join", "on.equal", "on.other"}),
        ("select count(*) from t where a between 1 and 2 and b in (1, 2)", {"select.aggregate", "where.condition"}),
        ("select a from t group by a having count(*) > 1 order by a desc limit 3", {"group.key", "having.condition", "order.key", "limit.count"}),
        ("select a from t union select b from u", {"set.union"}),
        ("select a from t intersect select b from u", {"set.intersect"}),
        ("select a from t except all select b from u", {"set.except"}),
        ("with q as (select 1) select * from q", {"with.name"}),
        ("select a from t where b > (select avg(b) from t)", {"subquery.begin", "subquery.end"}),
        ("select rank() over (partition by a order by b) as r from t", {"select.window", "select.over", "select.alias"}),
    ],
)
def test_every_kind_is_emitted(sql, kinds):
    found = {o.kind for o in atoms.operations(sql)}
    assert kinds <= found <= set(atoms.KINDS)


def test_literals_and_scopes():
    assert keys("select a from t where b = 1.0") == keys("select a from t where b = 1")
    assert any(o.kind == "literal.value" for o in atoms.operations("select a from t where b = 1", atoms.Options(consts="separate")))
    assert not any(o.kind.startswith("scope") for o in atoms.operations("select a from t where b in (select b from u)", atoms.Options(markers=False)))


@pytest.mark.parametrize("sql", ["selct a", "select", "select a from", "select (a from t", "select a from t;; select b", "drop table t", ""])
def test_what_is_no_statement(sql):
    with pytest.raises(ParseError):
        parse(sql)
    assert atoms.operations(sql) == []


def test_gold_and_mutations_parse():
    for _, _, _, sql in corpus.QUESTIONS:
        assert atoms.parses(sql), sql
        for m in corpus.KEEPING:
            assert atoms.parses(corpus.mutate(sql, m)), (m, corpus.mutate(sql, m))


def test_front_ends_agree_on_clauses(spark):
    for _, _, _, sql in corpus.QUESTIONS[:20]:
        mine = {o.kind for o in atoms.operations(sql)}
        for kind in atoms.decompose_catalyst(spark, sql) - {"group.key", "with.name"}:
            assert kind in mine, (kind, sql)


def test_shaping_values(spark):
    want = {"S1": [0, 0.305392, 0.394681, 1], "S2": [0, 0.129538, 0.197694, 0.895], "S3": [0, 0.414735, 0.478533, 0.8005], "S4": [0, 0.040617, 0.080943, 0.8]}
    df = spark.createDataFrame([(x,) for x in (0.0, 0.05, 0.1, 1.0)], "x double")
    for name, values in want.items():
        got = [r[0] for r in df.select(F.round(S.shape_named(F.col("x"), name), 6)).collect()]
        assert got == pytest.approx(values, abs=2e-6)
    assert rewards.check_separation("S3") and not rewards.check_separation("S1")


def test_completion_layouts(spark):
    got = {r["name"]: r["format_error"] for r in C.split(spark.createDataFrame([c[:2] for c in COMPLETIONS], "name string, completion string")).collect()}
    assert got == {n: e for n, _, e in COMPLETIONS}
    lenient = C.split(spark.createDataFrame([("  <think>a</think>select 1",)], "completion string"), strict=False).first()
    assert lenient["format_ok"] and lenient["sql"] == "select 1" and lenient["trace"] == "a"


def test_advantages(spark):
    df = spark.createDataFrame([(1, 4.0), (1, 3.5), (1, 1.6), (1, 0.0), (2, 0.0), (2, 0.0)], "question_id int, total double")
    got = {(r["question_id"], r["total"]): r["advantage"] for r in grpo.advantages(df, eps=0.0).collect()}
    for x, a in ((4.0, 1.085169), (3.5, 0.770627), (1.6, -0.424631), (0.0, -1.431164)):
        assert got[(1, x)] == pytest.approx(a, abs=1e-6)
    assert got[(2, 0.0)] == 0


def test_pass_at_k_unbiased_value(spark):
    df = spark.createDataFrame([(1, k, k < 2) for k in range(5)], "question_id int, rollout_id int, correct boolean")
    assert metrics.pass_at_k(df, (2,), "unbiased").first()["pass_at_k"] == pytest.approx(0.7)


def test_self_bleu_matches_pairs():
    from collections import Counter

    rng = random.Random(2)
    texts = [[rng.choice("abcde") for _ in range(rng.randrange(4, 12))] for _ in range(6)]
    want = 0.0
    for i, t in enumerate(texts):
        refs = []
        for n in range(1, 5):
            top = Counter()
            for j, o in enumerate(texts):
                if j != i:
                    for g, c in Counter(tuple(o[k : k + n]) for k in range(len(o) - n + 1)).items():
                        top[g] = max(top[g], c)
            refs.append(top)
        want += metrics.bleu(t, refs, [len(o) for j, o in enumerate(texts) if j != i])
    assert metrics.self_bleu_of(texts) == pytest.approx(want / len(texts))


def brute_neighbours(vectors, dbs, k, scope):
    unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    cos = np.round(unit @ unit.T, 9)
    out = {}
    for i in range(len(unit)):
        ok = [j for j in range(len(unit)) if j != i and (scope == "mixed" or (dbs[i] == dbs[j]) == (scope == "same"))]
        out[i] = sorted(ok, key=lambda j: (-cos[i, j], j))[:k]
    return out


@pytest.mark.parametrize("scope", memory.SCOPES)
@pytest.mark.parametrize("block", [1 << 26, 2000])
def test_lookup_matches_brute_force(spark, scope, block):
    rng = np.random.default_rng(1)
    v = rng.normal(size=(50, 8))
    rows = [(i, str(i % 3), [float(x) for x in v[i]]) for i in range(50)]
    store = spark.createDataFrame(rows, "entry_id long, db_id string, embedding array<float>")
    got = memory.lookup(store.withColumnRenamed("entry_id", "query_id"), store, 4, scope, block).collect()
    found = {}
    for r in sorted(got, key=lambda r: (r["query_id"], r["rank"])):
        found.setdefault(r["query_id"], []).append(r["entry_id"])
    assert found == brute_neighbours(np.array([r[2] for r in rows], dtype=np.float32).astype(float), [r[1] for r in rows], 4, scope)


def test_greedy_admission_equals_a_scan_in_order(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(6, 6))
    v = np.array([base[rng.integers(6)] + 0.35 * rng.normal(size=6) for _ in range(40)])
    unit = v / np.linalg.norm(v, axis=1, keepdims=True)
    kept = []
    for i in range(40):
        if all(round(float(unit[i] @ unit[j]), 9) < 0.9 for j in kept):
            kept.append(i)
    new = spark.createDataFrame([(i, "a", [float(x) for x in v[i]]) for i in range(40)], "query_id long, db_id string, embedding array<double>")
    none = spark.createDataFrame([], "entry_id long, db_id string, embedding array<double>")
    got = memory.dedup(new, none, 0.9, "greedy_in_order")
    assert sorted(r["query_id"] for r in got.collect()) == kept
    assert memory.dedup(new, none, 0.9).count() == 40


def test_memory_arms(spark):
    df = spark.createDataFrame([(False, True, 0.4), (True, True, 0.4), (True, False, 0.4)], "ok boolean, correct boolean, s double")
    assert [r[0] for r in df.select(memory.memory_reward(F.col("s"), F.col("ok"), F.col("correct"))).collect()] == [0.0, 1.0, 0.4]


def test_encoder():
    assert np.linalg.norm(embed.encode_text("join the tables")) == pytest.approx(1) and not embed.encode_text("").any() and not embed.encode_text(None).any()


@pytest.mark.parametrize("t", [0.5, 0.8])
def test_prefix_join_matches_brute_force(spark, t):
    rng = random.Random(7)
    sets = {i: sorted({rng.choice("abcdefghijkl") for _ in range(rng.randrange(1, 9))}) for i in range(40)}
    df = spark.createDataFrame(list(sets.items()), "id int, items array<string>")
    want = {(i, j) for i in sets for j in sets if i < j and len(set(sets[i]) & set(sets[j])) >= t * len(set(sets[i]) | set(sets[j])) - 1e-9}
    assert {(r["left_id"], r["right_id"]) for r in setjoin.prefix_join(df, "id", "items", t).collect()} == want


def test_guard():
    assert execute.guard("select 1 from customer") is None
    for sql in ("select * from parquet.`/etc/x`", "select java_method('a', 'b')", "drop table x", "select 1; drop table x", 'select * from "/etc/passwd"'):
        assert execute.guard(sql), sql


def test_mutations_keep_results(spark, sf_dir):
    """Renaming, swapping and restructuring never change a result; wrong ones often do."""
    rows = [(q, db, m, corpus.mutate(sql, m)) for q, (db, _, _, sql) in enumerate(corpus.QUESTIONS) for m in corpus.KEEPING]
    parsed = spark.createDataFrame(rows, "question_id long, db_id string, mutator string, sql string")
    judged = execute.judge(spark, sf_dir, parsed, corpus.questions(spark))
    assert [(r["question_id"], r["mutator"], r["sql"], r["status"]) for r in judged.where("not correct").collect()] == []


def test_comparison_modes(spark):
    a = spark.sql("select * from values (1, 'x'), (1, 'x'), (2, 'y') t(a, b)")
    assert execute.compare(a, a.orderBy("b")) and not execute.compare(a, a.distinct()) and execute.compare(a, a.distinct(), "set")
    assert execute.compare(a, a.select("b", "a"), "bag_colperm") and not execute.compare(a.orderBy("a"), a.orderBy(F.desc("a")), "ordered")


def test_majority_ties_and_failures(spark):
    rows = [(1, 0, "runs", "x", False), (1, 1, "runs", "y", True), (2, 0, "parse", None, False), (2, 1, "analyse", None, False)]
    df = spark.createDataFrame(rows, "question_id int, rollout_id int, status string, result string, correct boolean")
    got = {r["question_id"]: (r["rollout_id"], r["correct"]) for r in selection.majority(df).collect()}
    assert got == {1: (0, False), 2: (1, False)}
    assert {r["question_id"]: r["rollout_id"] for r in selection.majority(df, ties="last").collect()}[1] == 1


def test_repairs():
    known = ["c_name", "c_acctbal"]
    assert baselines.repair_sql("selct c_name from customer", known) == "select c_name from customer"
    assert baselines.repair_sql("select count(c_name from customer", known).count(")") == 1
    assert "c_name" in baselines.repair_sql("select c_nome from customer", known)
    assert "group by c_name" in baselines.repair_sql("select c_name, count(*) from customer", known)


def test_ngram_model_is_a_distribution(spark):
    df = spark.createDataFrame([("a b a b c",), ("a b",)], "completion string")
    model = sft.fit_ngram(df, order=2, alpha=0.0).groupBy("context").agg(F.sum(F.exp("logp")).alias("p"))
    assert all(abs(r["p"] - 1) < 1e-9 for r in model.collect())


def test_corpus_does_not_depend_on_partitions(spark):
    a, b = (corpus.rollouts(spark, 4, partitions=p).select("question_id", "rollout_id", "completion") for p in (1, 7))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
    assert corpus.rollouts(spark, 8, temperature=0.0).groupBy("question_id").agg(F.count_distinct("completion").alias("n")).where("n > 1").isEmpty()


def test_diversity_and_density_edges(spark):
    df = spark.createDataFrame([("one",), ("",), ("a b a b a b",)], "t string").withColumn("k", T.tokens(F.col("t")))
    assert [round(r[0], 3) for r in df.select(T.diversity(F.col("k"))).collect()] == [1.0, 1.0, 0.4]


def test_plans(spark, sf_dir):
    """Rank limits sit below the shuffle, filters reach the scan, and look-ups make no cartesian product."""
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    top = relational.explain_text(relational.top_k_per_key(orders, ["o_custkey"], [F.desc("o_totalprice")], 2))
    assert "WindowGroupLimit" in top
    pushed = relational.explain_text(orders.where("o_totalprice > 5").select("o_orderkey"))
    assert "PushedFilters: [IsNotNull(o_totalprice)" in pushed and "o_orderpriority" not in pushed.split("ReadSchema")[1]
    items = spark.createDataFrame([(1, ["a"])], "id int, items array<string>")
    assert "Cartesian" not in relational.explain_text(setjoin.prefix_join(items, "id", "items", 0.8))


def test_asof_join(spark):
    left = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k int, t int")
    right = spark.createDataFrame([(1, 2, "a"), (1, 5, "b"), (3, 1, "c")], "k int, t int, v string")
    got = {(r["k"], r["t"]): r["asof_v"] for r in relational.asof_join(left, right, "k", "t", "v").collect()}
    assert got == {(1, 5): "b", (1, 1): None, (2, 9): None}


def test_surrogate_clips(spark):
    df = spark.createDataFrame([(1.0, 0.5, 0.0), (-1.0, 0.5, 0.0)], "a double, lp double, old double")
    got = [r[0] for r in df.select(grpo.surrogate(F.col("a"), F.col("lp"), F.col("old"), 0.2)).collect()]
    assert got == pytest.approx([-1.2, math.exp(0.5)])


def test_probes_are_calibrated():
    """Fewer cells where vectors have structure, and the recall asked for on the sample either way."""
    import numpy as np

    from densesql.operators import ann

    rng = np.random.default_rng(3)
    centres = rng.normal(size=(12, 16))
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    grouped, plain = unit(centres[rng.integers(12, size=600)] + 0.2 * rng.normal(size=(600, 16))), unit(rng.normal(size=(600, 16)))
    few, many = (ann.calibrate_probes(v, ann.fit_centroids(v, 12), 10, 0.95) for v in (grouped, plain))
    assert few < many <= 12


def test_clipped_step_raises_the_reward():
    import numpy as np

    from densesql.operators import training

    x = [np.eye(3), np.eye(3)]
    rewards = [np.array([0.0, 1.0, 0.0]), np.array([0.0, 1.0, 0.5])]
    theta = np.zeros(3)
    for step in range(300):
        theta, drawn = training.clipped_step(theta, np.zeros(3), x, rewards, np.random.default_rng(step), 16, 0.2, 1.0, 0.2, 0.0, 2)
        assert all(len(d) == 16 for d in drawn)
    assert training.softmax(theta)[1] > 0.9
    held = training.clipped_step(theta, theta, x, [np.ones(3), np.ones(3)], np.random.default_rng(1), 16, 0.2, 1.0, 0.2, 0.5, 2)[0]
    assert np.allclose(held, theta)  # groups that agree teach nothing, and the penalty is flat at its start


def test_training_over_jobs_is_one_run(spark):
    """Steps split over several jobs, each with the questions it needs, give the same checkpoints as one job."""
    import numpy as np

    from densesql.operators import training
    from densesql.plans.staging import Staging

    rows = [(q, c, [float(c == 1), float(c == 2)], float(c == q % 3), c == q % 3) for q in range(12) for c in range(3)]
    cands = spark.createDataFrame(rows, "question_id long, cand_id int, x array<double>, total double, correct boolean")
    runs = [training.train(cands, np.zeros(2), Staging(spark, "t"), "run", 12, 4, 3, steps_per_job=n) for n in (12, 2)]
    assert [c["step"] for c in runs[0]] == [0, 3, 6, 9, 12]
    last = {n: r[-1]["theta"] for n, r in enumerate(runs)}
    assert np.allclose(last[0], last[1])


def test_executor_limits(spark, sf_dir):
    from densesql.operators import execute

    texts = [("sales", "select * from orders"), ("sales", "select count(*) from lineitem a, lineitem b, lineitem c"), ("sales", "select 1 as x")]
    given = spark.createDataFrame(texts, "db_id string, sql string")
    got = {r["sql"]: (r["status"], r["error_class"]) for r in execute.run(spark, sf_dir, given, timeout_s=6, max_rows=100).collect()}
    assert got[texts[0][1]] == ("runtime", "too_many_rows") and got[texts[1][1]] == ("runtime", "timeout") and got[texts[2][1]][0] == "runs"


def test_tree_search_never_sees_the_gold():
    import inspect

    from densesql.operators import baselines

    body = inspect.getsource(baselines.tree_search)
    assert "gold_sql" not in body


def test_stream_files_keep_their_order(spark, sf_dir):
    from densesql.plans.staging import Staging
    from densesql.streaming import engine

    staging = Staging(spark, "order")
    engine.file_stream(spark, sf_dir, "events", staging, "ts", parts=4)
    root = spark._jvm.org.apache.hadoop.fs.Path(staging.path("in-events"))
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    files = sorted((s.getPath().getName(), s.getModificationTime()) for s in fs.listStatus(root) if s.getPath().getName().startswith("part-"))
    times = [t for _, t in files]
    assert len(times) > 1 and all(b - a >= 1000 for a, b in zip(times, times[1:]))
