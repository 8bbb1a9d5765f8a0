"""What showed on larger tables only: keys that collide, and plans that grow too fast."""

import itertools
import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from claimfold.catalog import QUERIES, SQL
from claimfold.operators import learn, resolver
from claimfold.plans import experiments, rules
from claimfold.sources.replicas import replicas


def same_as_sql(spark, name, d, tables):
    """The query's rows are those of its SQL over the tables that d has."""
    con = duckdb.connect()
    for t in tables:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet/*.parquet'")
    want = con.sql(SQL[name])
    got = QUERIES[name](spark, d).select(*want.columns).collect()
    assert sorted(map(tuple, got), key=str) == sorted(want.fetchall(), key=str)
    return got


def test_records_that_share_an_id_have_one_row_of_the_sql(spark, tmp_path):
    rng = random.Random(1)
    rows = [(o, p, float(rng.randint(1, 20)), float(rng.randint(1, 20))) for o in range(40) for p in (3, 4, 10003, 10004, 20003) if rng.random() < 0.8]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_quantity double, l_extendedprice double").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = same_as_sql(spark, "violations_order_join", str(tmp_path), ["lineitem"])
    assert len(got) < len(rows)


@pytest.mark.parametrize("text", ["not(t1.k = t2.k and t1.x > t2.x and t1.y < t2.y)", "not(t1.x > t2.x and t1.y < t2.y)"])
def test_order_rules_keep_a_row_for_each_record(spark, text):
    rng = random.Random(2)
    some = lambda: None if rng.random() < 0.1 else rng.randint(0, 6)
    rows = [(i // 3, some(), some(), some()) for i in range(90)]
    bad = lambda a, b: (a[1] == b[1] is not None or "k" not in text) and None not in (*a[2:], *b[2:]) and (a[2] > b[2] and a[3] < b[3] or a[2] < b[2] and a[3] > b[3])
    want = sorted((a[0], sum(bad(a, b) for b in rows)) for a in rows)
    df = spark.createDataFrame(rows, "id long, k int, x int, y int")
    assert sorted(map(tuple, rules.violations(df, rules.parse_rule(text), "id").collect())) == want


def test_three_tuples_over_equal_records(spark):
    """Many equal records, nulls among them, against all sets of three; and no row a set."""
    rng = random.Random(3)
    rows = [(i, rng.choice([None, 0, 1, 2]), rng.choice([None, 0, 1])) for i in range(36)]
    eq = lambda a, b: a is not None and a == b
    bad = lambda a, b, c: eq(a[1], b[1]) and eq(b[2], c[2]) and c[1] is not None and a[1] > c[1]
    want = {r[0]: 0 for r in rows}
    for s in itertools.combinations(rows, 3):
        if any(bad(*o) for o in itertools.permutations(s)):
            for r in s:
                want[r[0]] += 1
    rule = rules.parse_rule("not(t1.k = t2.k and t2.b = t3.b and t1.k > t3.k)")
    df = spark.createDataFrame(rows, "id long, k int, b int")
    assert {r["id"]: r["n"] for r in rules.violations(df, rule, "id").collect()} == want
    many = spark.range(200_000).selectExpr("id", "id % 5 as k", "id % 3 as b")
    assert rules.violations(many, rule, "id").where("n > 1000000000").count() == 200_000


def test_two_tuples_of_equal_records(spark):
    """A comparison of two columns within a key: equal records pair with one another."""
    rows = [(1, 0, 1, 2), (2, 0, 1, 2), (3, 0, 3, 4), (4, 1, 1, 2), (5, None, 1, 2)]
    df = spark.createDataFrame(rows, "id long, k int, x int, y int")
    got = {r["id"]: r["n"] for r in rules.violations(df, rules.parse_rule("not(t1.k = t2.k and t1.x < t2.y)"), "id").collect()}
    assert got == {1: 2, 2: 2, 3: 2, 4: 0, 5: 0}


def test_predicted_cooccurrence_joins_once(spark, tmp_path):
    spark.range(40).selectExpr("id as p_partkey", "concat('red ', id % 7) as p_name", "concat('Brand#', id % 3) as p_brand", "concat('T', id % 4) as p_type", "cast(id % 5 as int) as p_size", "cast(id as double) as p_retailprice").write.parquet(f"{tmp_path}/part.parquet")
    same_as_sql(spark, "cooccurrence_predicted", str(tmp_path), ["part"])
    plan = QUERIES["cooccurrence_predicted"](spark, str(tmp_path))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join ") == 1


def test_rule_within_entities_moves_no_record(spark):
    """Small blocks are counted where replicas lie: as with two aggregates, and the only exchanges are those of the clean table."""
    d = "/root/testdata/sf0.001"
    rule = rules.parse_rule("not(t1.entity_id = t2.entity_id and t1.o_orderstatus = 'F' and t2.o_orderstatus = 'F' and t1.o_custkey != t2.o_custkey)")
    wide = replicas(spark, d, "orders").withColumn("rid", F.col("entity_id") * 4096 + F.col("source_id"))
    got = QUERIES["violations_conditional"](spark, d)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, rules.violations(wide, rule, "rid").collect()))
    plan = got._jdf.queryExecution().executedPlan().toString()
    above = plan[: plan.index("Generate explode(sequence(0, 36")] if "Generate explode(sequence(0, 36" in plan else plan.split("Generate")[0]
    assert "Window" in above and "Exchange" not in above


@pytest.mark.parametrize("n", [1, 3, 7, 40])
def test_replicas_of_few_keys_and_spans(spark, n, monkeypatch):
    from claimfold.sources import replicas as module

    monkeypatch.setattr(module, "SPAN", 8)
    base = spark.range(n).selectExpr("id as k", "named_struct('a', cast(id as string)) as v")
    got = {r["k"]: [r[f"v{d}"]["a"] for d in range(6)] for r in module._neighbours(base, n).collect()}
    assert got == {k: [str((k + d) % n) for d in range(6)] for k in range(n)}


def test_fits_share_static_features(spark, monkeypatch):
    """Static features are made once for all fits of a workload, over one run; each fit has its own blocks and answers as alone."""
    made = []
    static = resolver._static
    monkeypatch.setattr(resolver, "_static", lambda *a: made.append(1) or static(*a))
    w = experiments.Workload(spark, "/root/testdata/sf0.001", "customer", 0.3, runs=2, limit=30)
    for changes in ({"models": ("format", "vote", "cooc", "rules")}, {"use_source": False}):
        s = w.settings(stages=1, **changes)
        fitted, scored = resolver.fit(w.wide, w.seeds, s, w.prepared)
        assert len(made) == 1
        # Run by run as if it were alone: rules count the partners of their own run.
        for run in range(1, 2):
            of = lambda df, r=run: df.where(F.floor(F.col("entity_id") / resolver.RUN) == r)
            names = resolver._static(of(w._one, 0).limit(0).withColumn("record_id", F.lit(0)), s, resolver.source_list(w._one, s))[1]
            made.pop()
            assert fitted.names[: len(names)] == names
            alone, one = resolver.fit(of(w.wide), of(w.seeds), s)
            made.pop()
            assert alone.names == fitted.names and alone.sources == fitted.sources
            key = ["entity_id", "attr", "value"]
            both = of(scored).join(one.select(*key, F.col("p").alias("q")), key, "full").agg(F.max(F.abs(F.col("p") - F.col("q"))).alias("d"), F.count_if(F.col("p").isNull() | F.col("q").isNull()).alias("n")).first()
            assert both["n"] == 0 and both["d"] < 1e-3


def test_softmax_has_one_answer_from_any_start(monkeypatch):
    """A start near the answer needs fewer steps to the same weights."""
    rng = np.random.default_rng(4)
    group = np.repeat(np.arange(400), 3)
    x = rng.normal(size=(1200, 6))
    y = np.zeros(1200)
    y[np.arange(400) * 3 + (x @ rng.normal(size=6) + rng.gumbel(size=1200)).reshape(400, 3).argmax(axis=1)] = 1
    near = learn.conditional_softmax(x, y, group, np.ones(1200), 0.01)
    steps, solve = [], np.linalg.solve
    monkeypatch.setattr(np.linalg, "solve", lambda *a: steps.append(1) or solve(*a))
    cold = learn.conditional_softmax(x, y, group, np.ones(1200), 0.012)
    n = len(steps)
    warm = learn.conditional_softmax(x, y, group, np.ones(1200), 0.012, start=near)
    assert np.allclose(cold, warm, atol=1e-4) and len(steps) - n < n


def test_adam_steps_are_those_of_the_formula():
    """The steps without new tables against the textbook form."""
    rng = np.random.default_rng(5)
    x, weight = rng.normal(size=(53, 4)), rng.random(53)
    y = rng.integers(0, 3, 53)
    order, z = np.random.default_rng(0), np.hstack([x, np.ones((53, 1))])
    w, m, v, t = np.zeros((5, 3)), 0, 0, 0
    for _ in range(20):
        at = order.permutation(53)
        for lo in range(0, 53, 10):
            i = at[lo : lo + 10]
            t += 1
            g = z[i].T @ ((learn.softmax_rows(z[i] @ w) - np.eye(3)[y[i]]) * weight[i, None]) / len(i) + 1e-3 * w
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            w = w - 0.01 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    assert np.allclose(learn.adam_softmax(x, y, 3, weight, epochs=20), w, atol=1e-12)


def test_packed_fits_are_those_of_the_resolver(spark):
    """one job a stage fits all runs and ablations of a workload; models and precisions are those of fits one by one."""
    w = experiments.Workload(spark, "/root/testdata/sf0.001", "customer", 0.3, runs=2, limit=40)
    few = {"max_train": 8}
    fits = [few, {"use_source": False, **few}, {"models": ("format", "cooc", "running", "rules"), **few}, {"models": ("vote",), "train_on": "seed", **few}]
    w.split = w.packed.split(w.share, w.runs, w.settings(**few))
    made = w.packed.fit([w.settings(**f) for f in fits], w.split, w.runs)
    for changes, fitted, precisions in zip(fits, made, w.resolve(*fits), strict=True):
        alone, expected = w.fit(**changes)
        assert fitted.names == alone.names and precisions == expected
        for m, n in zip(fitted.stages, alone.stages, strict=True):
            assert m.weights.keys() == n.weights.keys() and len(m.weights) == 12
            for k, v in n.weights.items():
                assert m.weights[k] == pytest.approx(v, abs=1e-9) and m.platt[k] == pytest.approx(n.platt[k], abs=1e-9)


def test_packed_rivals_are_those_of_baselines(spark):
    """rivals over packed records, for all runs at once, answer as those over claims."""
    w = experiments.Workload(spark, "/root/testdata/sf0.001", "customer", 0.1, runs=2, limit=100)
    rivals = tuple(m for m in experiments.METHODS if not m.startswith("source_"))
    got = {}
    for m, r, p in experiments.answers(w, rivals):
        got.setdefault(m, []).append((r, p))
    for m in rivals:
        assert got[m] == experiments.answer(w, m), m


def test_packed_static_features_are_those_of_the_resolver(spark):
    """F8 (also F6, F11): static features over arrays, text work once a distinct text, for odd texts as well."""
    from claimfold.operators.packed import Packed, Pack

    odd = ["", "a", "ÉCOLE Straße 12", "x" * 70 + "7", "0123456789" * 4, "١٢ Ω-\U0001d400b", "  ", "a^b$", "Customer#000000012", None, "AA--11  b", "中文字 x"]
    rows = [(e, k, odd[(e + k * (e % 3)) % 12], odd[(e * 5 + k) % 12], f"{e % 4}", f"n{(e + k // 3) % 3}") for e in range(30) for k in range(7)]
    wide = spark.createDataFrame([*rows, (40, None, None, None, None, None)], "entity_id long, source_id int, a string, b string, k string, v string")
    s = resolver.Settings(("a", "b", "k", "v"), embed_dim=8, rules=("not(t1.k = t2.k and t1.v != t2.v)",))
    for dist in ("l2", "l1"):
        made = resolver.prepare(wide, resolver.replace(s, dist=dist))
        expected = {(r["entity_id"], r["attr"], r["value"]): (r["support"], r["slot"], r["static"]) for r in made.cands.collect()}
        packed = Packed(wide, resolver.replace(s, dist=dist), spark.createDataFrame([(e, "a", "b", "1", "n1") for e in range(31)], "entity_id long, a string, b string, k string, v string"))
        assert packed.names == made.names and packed.sources == made.sources
        static = np.concatenate([Pack.read(r, 4).static for r in packed.rows.collect()], axis=1)
        got = {(r["entity_id"], r["attr"], r["value"]): (r["support"], r["slot"], list(x)) for r, x in zip(packed.cands.collect(), static.T, strict=True)}
        assert got.keys() == expected.keys()
        for k, (support, slot, x) in expected.items():
            assert got[k][:2] == (support, slot) and got[k][2] == pytest.approx(x, abs=1e-12), k


def test_softmax_has_each_probability_once(monkeypatch):
    """F11 (also F6): the probabilities of a step's loss are those that the next step begins with."""
    rng = np.random.default_rng(6)
    x, y = rng.normal(size=(600, 4)), np.tile([1.0, 0, 0], 200)
    steps, made, solve, exp = [], [], np.linalg.solve, np.exp
    monkeypatch.setattr(np.linalg, "solve", lambda *a: steps.append(1) or solve(*a))
    monkeypatch.setattr(np, "exp", lambda *a: made.append(1) or exp(*a))
    learn.conditional_softmax(x, y, np.repeat(np.arange(200), 3), np.ones(600), 0.01)
    assert len(steps) > 1 and len(made) <= 1 + len(steps)
