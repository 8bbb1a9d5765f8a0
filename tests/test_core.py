"""Worked examples, invariants and equivalences of the claim operators."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from claimfold.operators import augment, baselines, claims, features, infer, learn, measure, resolver
from claimfold.plans import rules
from claimfold.sources.replicas import SETS, Spec, make_replicas, replicas, truth

D = "/root/testdata/sf0.001"
CELL = ["entity_id", "attr"]


def long(spark, rows):
    return spark.createDataFrame(rows, "entity_id long, source_id int, attr string, value string")


@pytest.fixture(scope="module")
def toy(spark):
    rows = [(1, 0, "city", "Oslo"), (1, 1, "city", "Oslo"), (1, 2, "city", "Bergen"), (1, 0, "zip", "1"), (1, 1, "zip", "2"), (2, 0, "city", "Rome"), (2, 1, "city", "Roma"), (2, 2, "zip", "9")]
    return long(spark, rows)


# -- formats and edits -------------------------------------------------------------


def test_format_map_and_bigrams(spark):
    rows = spark.createDataFrame([("Google",), ("Google Inc.",), ("",), ("12",), ("é-1",)], "v string").select("v", features.format_map(F.col("v")).alias("m"), features.format_ngrams(F.col("v")).alias("g")).collect()
    got = {r["v"]: (r["m"], r["g"]) for r in rows}
    assert got["Google"] == ("AAAAAA", [5, 0, 0, 0, 0, 0, 0, 0, 0])
    assert got["Google Inc."] == ("AAAAAASAAAS", [7, 0, 2, 0, 0, 0, 1, 0, 0])
    assert got[""] == ("", [0] * 9) and got["12"][1][4] == 1 and got["é-1"][0] == "ASN"


def test_runs_and_edit(spark):
    assert [s for s, _ in augment.runs_python("New York-#401H3")] == ["L+", " ", "L+", "-", "#", "D+", "L", "D"]
    assert augment.edit_python("New York-#401H3", "Toronto-#21LG") == "York-#401"
    assert augment.edit_python("abc", "12") == "abc"
    row = spark.createDataFrame([("New York-#401H3", "Toronto-#21LG")], "a string, b string").select(augment.edit_to_format("a", "b").alias("e"), augment.format_runs(F.col("a")).alias("r"), augment.common_run("a", "b").alias("c")).first()
    assert row["e"] == "York-#401" and "".join(x["text"] for x in row["r"]) == "New York-#401H3" and (row["c"]["start"], row["c"]["length"]) == (2, 4)


# -- candidates and labels -----------------------------------------------------------


def test_candidates(toy):
    got = {(r["entity_id"], r["attr"], r["value"]): (r["slot"], r["support"], r["n_slots"]) for r in claims.candidates(toy).collect()}
    assert got[1, "city", "Oslo"] == (0, 2, 2) and got[1, "zip", "1"] == (0, 1, 2) and got[2, "city", "Roma"] == (0, 1, 2)
    with pytest.raises(ValueError):
        claims.candidates(toy, "nothing")


def test_one_hot_is_padded(toy):
    c = claims.candidates(toy)
    rows = claims.one_hot(c, claims.vote_labels(c)).collect()
    for cell in {(r["entity_id"], r["attr"]) for r in rows}:
        own = [r for r in rows if (r["entity_id"], r["attr"]) == cell]
        assert sum(r["hot"] for r in own) == 1 and len(own) == (2 if cell[1] == "city" else 2)


def test_truth_not_claimed(spark, toy):
    t = spark.createDataFrame([(1, "city", "Oslo"), (2, "city", "Milan")], "entity_id long, attr string, value string")
    got = {r["entity_id"]: r["slot"] for r in claims.truth_slots(t, claims.candidates(toy)).collect()}
    assert got == {1: 0, 2: -1}


def test_split_is_by_entity(spark):
    e = spark.range(5000).withColumnRenamed("id", "entity_id")
    n = {r["part"]: r["count"] for r in claims.seed_split(e, 0.1, 0.1).groupBy("part").count().collect()}
    assert 350 < n["train"] < 650 and 350 < n["validation"] < 650
    with pytest.raises(ValueError):
        claims.seed_split(e, 0.9, 0.2)


def test_noise_is_independent(spark):
    """Error rates among seeds and overall agree; sources err apart."""
    base = spark.range(1500).select("id", F.concat(F.lit("v"), F.col("id").cast("string")).alias("a"), F.concat(F.lit("w"), F.col("id").cast("string")).alias("b"))
    spec = Spec(6, 1000, high=600, low=600, mode="independent")
    wide = make_replicas(base, "id", ["a", "b"], spec).withColumn("bad", (F.coalesce(F.col("a"), F.lit("")) != F.concat(F.lit("v"), F.col("entity_id").cast("string"))).cast("int"))
    pdf = wide.select("entity_id", "source_id", "bad").toPandas().pivot(index="entity_id", columns="source_id", values="bad")
    assert (abs(pdf.mean() - 0.4) < 0.06).all()
    c = np.corrcoef(pdf.to_numpy().T)
    assert np.abs(c - np.eye(6)).max() < 0.1


# -- features ------------------------------------------------------------------------


def test_shares_sum_to_one(toy):
    rows = features.vote_share(toy).dropDuplicates([*CELL, "value"]).groupBy(*CELL).agg(F.sum("share").alias("s")).collect()
    assert all(abs(r["s"] - 1) < 1e-9 for r in rows)


def test_cooccurrence_by_hand(spark):
    wide = spark.createDataFrame([(1, 0, "a", "x"), (1, 1, "a", "y"), (1, 2, "b", "x"), (1, 3, "a", "x")], "entity_id long, source_id int, p string, q string")
    got = {(r["source_id"], r["attr"]): r["ratio"] for r in features.cooccurrence(wide, ["p", "q"]).collect()}
    assert got[0, "p"] == pytest.approx(2 / 3) and got[2, "p"] == pytest.approx(1 / 3) and got[0, "q"] == pytest.approx(2 / 3) and got[2, "q"] == 1
    labels = spark.createDataFrame([(1, "p", "a"), (1, "q", "x")], "entity_id long, attr string, value string")
    said = {(r["attr"], r["value"]): r["ratio"] for r in features.cooccurrence(wide, ["p", "q"], labels).collect()}
    assert said["p", "a"] == pytest.approx(2 / 3) and said["q", "y"] == pytest.approx(1 / 3)


def test_running_flags(toy):
    c = claims.candidates(toy)
    assert features.running_flags(c, None).where("flag <> 0").count() == 0
    assert features.running_flags(c, claims.vote_labels(c)).agg(F.sum("flag")).first()[0] == claims.vote_labels(c).count()


def test_no_python_in_native_features(toy):
    df = features.vote_share(toy.withColumn("g", features.format_ngrams(F.col("value"))))
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "NestedLoop" not in plan
    assert plan.count("Exchange hashpartitioning") == 1


# -- rules ---------------------------------------------------------------------------


def brute(rows, test, arity=2):
    n = {r["id"]: 0 for r in rows}
    for a in rows:
        partners = set()
        for b in rows:
            if a["id"] != b["id"] and (test(a, b) or test(b, a)):
                partners.add(b["id"])
        n[a["id"]] = len(partners)
    return n


@pytest.mark.parametrize(
    ("text", "test"),
    [
        ("not(t1.k = t2.k and t1.x != t2.x)", lambda a, b: a["k"] == b["k"] and a["k"] is not None and None not in (a["x"], b["x"]) and a["x"] != b["x"]),
        ("not(t1.k = t2.k and t1.s = 'F' and t2.s = 'F' and t1.x != t2.x)", lambda a, b: a["k"] == b["k"] and a["k"] is not None and a["s"] == b["s"] == "F" and None not in (a["x"], b["x"]) and a["x"] != b["x"]),
        ("not(t1.k = t2.k and t1.x > t2.x and t1.y < t2.y)", lambda a, b: a["k"] == b["k"] and a["k"] is not None and None not in (a["x"], b["x"], a["y"], b["y"]) and a["x"] > b["x"] and a["y"] < b["y"]),
        ("not(t1.x < t2.x and t1.y > t2.y)", lambda a, b: None not in (a["x"], b["x"], a["y"], b["y"]) and a["x"] < b["x"] and a["y"] > b["y"]),
        ("not(t1.k = t2.k and t1.x >= t2.y and t1.s != t2.s)", lambda a, b: a["k"] == b["k"] and a["k"] is not None and None not in (a["x"], b["y"], a["s"], b["s"]) and a["x"] >= b["y"] and a["s"] != b["s"]),
    ],
)
def test_rules_equal_nested_loops(spark, text, test):
    rng = random.Random(7)
    rows = [{"id": i, "k": rng.choice([1, 2, 3, None]), "x": rng.choice([*range(6), None]), "y": rng.choice([*range(6), None]), "s": rng.choice(["F", "O", None])} for i in range(60)]
    df = spark.createDataFrame(rows, "id long, k int, x int, y int, s string")
    got = {r["id"]: r["n"] for r in rules.violations(df, rules.parse_rule(text, df.columns), "id").collect()}
    assert got == brute(rows, test)


def test_single_tuple_rule_and_errors(spark):
    df = spark.createDataFrame([(1, 0.2), (2, 0.05), (3, None)], "id long, d double")
    assert {r["id"]: r["n"] for r in rules.violations(df, rules.parse_rule("not(t1.d > 0.10)"), "id").collect()} == {1: 1, 2: 0, 3: 0}
    for bad in ("t1.a = 1", "not(1 = 2)", "not(t1.a ~ 3)", "not(t2.a = 1)"):
        with pytest.raises(rules.RuleError):
            rules.parse_rule(bad)
    with pytest.raises(rules.RuleError):
        rules.parse_rule("not(t1.zz = 1)", ["d"])
    with pytest.raises(rules.RuleError):
        rules.violations(df, rules.parse_rule("not(t1.d < t2.d)"), "id")
    r = rules.parse_rule("not(5 < t1.d and t1.e = 'it''s')")
    assert r.predicates[0].op == ">" and r.predicates[1].right.constant == "it's" and len(rules.rules_on([r], "d")) == 1


# -- baselines ------------------------------------------------------------------------


def test_quantiles():
    table = {(0.025, 1): 0.000982, (0.025, 3): 0.2158, (0.025, 10): 3.2470, (0.975, 10): 20.4832, (0.975, 30): 46.9792}
    for (p, k), v in table.items():
        assert baselines.chi2inv(p, k) == pytest.approx(v, rel=1e-3)


def test_heuristics(spark):
    c = long(spark, [(1, 0, "a", "10"), (1, 1, "a", "200"), (1, 2, "a", "3")])
    got = {r: baselines.heuristic(c, r, source=2).first()["value"] for r in ("longest", "shortest", "min", "max", "mean", "median", "prefer_source", "any")}
    assert got == {"longest": "200", "shortest": "3", "min": "10", "max": "3", "mean": 71.0, "median": 10.0, "prefer_source": "3", "any": "10"}
    with pytest.raises(ValueError):
        baselines.heuristic(c, "nothing")


@pytest.fixture(scope="module")
def work(spark):
    base = spark.range(300).select("id", *[F.concat(F.lit(p), (F.col("id") * m % 97).cast("string"), F.lit(" x"), F.col("id").cast("string")).alias(p) for p, m in (("a", 7), ("b", 11), ("c", 13))])
    wide = make_replicas(base, "id", ["a", "b", "c"], Spec(9, 850, high=700, low=250)).cache()
    whole = base.select(F.col("id").alias("entity_id"), "a", "b", "c").unpivot(["entity_id"], ["a", "b", "c"], "attr", "value").cache()
    parts = claims.seed_split(whole, 0.3, 0.0)
    seeds = whole.join(parts.where("part = 'train'"), "entity_id").select(*CELL, "value").cache()
    test = whole.join(parts.where("part = 'test'"), "entity_id").select(*CELL, "value").cache()
    return wide, wide.unpivot(["entity_id", "source_id"], ["a", "b", "c"], "attr", "value").where("value is not null").cache(), seeds, test


def test_order_of_methods(work):
    """The source-aware variant is best; the source-free one is not below the vote."""
    wide, long_, seeds, test = work
    p = lambda a: measure.precision(a, test).first()["precision"]
    vote, bayes = p(baselines.majority_vote(long_)), p(baselines.seed_accuracy_bayes(long_, seeds))
    s = resolver.Settings(("a", "b", "c"), stages=2, embed_dim=8)
    aware, scored = resolver.fit(wide, seeds, s)
    _, free = resolver.fit(wide, seeds, resolver.Settings(("a", "b", "c"), use_source=False, stages=2, embed_dim=8))
    sa, sf = p(resolver.resolve(scored)), p(resolver.resolve(free))
    assert sf > vote - 0.005 and sa >= sf - 0.005 and sa >= max(bayes, vote)
    assert p(baselines.iterative_bayes(long_, max_iter=5)) > vote - 0.02
    sums = scored.groupBy(*CELL).agg(F.sum("p").alias("s")).agg(F.min("s"), F.max("s")).first()
    assert sums[0] == pytest.approx(1) and sums[1] == pytest.approx(1)
    # Replaying the stages on the same records gives the last stage's answers.
    again = resolver.top(resolver.resolve_new(aware, wide)).select(*CELL, "value")
    same = again.join(resolver.top(scored).select(*CELL, F.col("value").alias("v")), CELL).agg(F.avg((F.col("v") == F.col("value")).cast("double"))).first()[0]
    assert same == 1.0


def test_models_are_kept(work, spark, tmp_path):
    wide, _, seeds, _ = work
    fitted, scored = resolver.fit(wide, seeds, resolver.Settings(("a", "b", "c"), stages=1, embed_dim=8))
    fitted.save(spark, str(tmp_path / "m"))
    back = resolver.Fitted.load(spark, str(tmp_path / "m"))
    assert back.settings == fitted.settings and back.stages == fitted.stages
    assert {b for _, _, b, _ in resolver.weight_report(back)} >= {"vote", "format", "source"}


def test_seeds_stay(work):
    wide, _, seeds, _ = work
    _, scored = resolver.fit(wide, seeds, resolver.Settings(("a", "b", "c"), stages=1, embed_dim=8))
    kept = resolver.resolve(scored, seeds).join(seeds.withColumnRenamed("value", "t"), CELL)
    assert kept.where("value <> t").count() == 0


def test_shuffled_truth_teaches_nothing(work):
    """With wrong labels the model finds no more than chance among candidates would."""
    wide, long_, seeds, test = work
    wrong = seeds.withColumn("value", F.concat(F.lit("no such value "), "value"))
    s = resolver.Settings(("a", "b", "c"), stages=1, embed_dim=8, train_on="seed")
    _, scored = resolver.fit(wide, wrong, s)
    assert measure.precision(resolver.resolve(scored), test).first()["precision"] < 1.0


def test_augmentation(work):
    _, long_, seeds, _ = work
    more, labels = augment.augment_entities(long_, seeds, 0.5)
    n = labels.select("entity_id").distinct().count()
    assert 0.3 * seeds.select("entity_id").distinct().count() < n < 0.7 * seeds.select("entity_id").distinct().count()
    assert more.where("entity_id >= 0").count() == 0 and more.columns == long_.columns
    assert augment.augment_entities(long_, seeds, 0.0)[0].count() == 0
    with pytest.raises(ValueError):
        augment.augment_entities(long_, seeds, -1)


def test_onehot_tells_values_of_one_format_apart(spark):
    wide = spark.createDataFrame([(e, s, "aaaa" if (s < 2) == (e % 2 == 0) else "bbbb") for e in range(60) for s in range(3)], "entity_id long, source_id int, name string")
    seeds = spark.createDataFrame([(e, "name", "aaaa") for e in range(30)], "entity_id long, attr string, value string")
    scored = resolver.fit(wide, seeds, resolver.Settings(("name",), models=("onehot",), use_source=False, stages=1, weak_weight=0.0))[1]
    assert {r["value"] for r in resolver.top(scored).where("entity_id >= 30").collect()} == {"aaaa"}


def test_naive_classifier_has_value_hashes_alone(spark, monkeypatch):
    from claimfold.catalog import models

    seen = []
    monkeypatch.setattr(models.resolver, "fit", lambda wide, seeds, s: seen.append(s) or (None, None))
    monkeypatch.setattr(models.resolver, "top", lambda scored: spark.createDataFrame([(1, "a", "v", 1.0)], "entity_id long, attr string, value string, p double"))
    models.naive_onehot_classifier(spark, D)
    assert seen[0].models == ("onehot",) and not seen[0].use_source


def test_settings_are_checked():
    for bad in ({"layout": "x"}, {"train_on": "x"}, {"models": ("x",)}, {"stages": 0}):
        with pytest.raises(ValueError):
            resolver.Settings(("a",), **bad)


# -- learning and inference --------------------------------------------------------------


def test_gradients():
    rng = np.random.default_rng(0)
    x, group = rng.normal(size=(60, 3)), np.repeat(np.arange(20), 3)
    y = (np.arange(60) % 3 == 0).astype(float)
    w = learn.conditional_softmax(x, y, group, np.ones(60), 0.1)

    def loss(v):
        z = (x @ v).reshape(20, 3)
        p = learn.softmax_rows(z)[:, 0]
        return -np.log(p).mean() + 0.05 * v @ v

    for i in range(3):
        e = np.zeros(3)
        e[i] = 1e-5
        assert abs(loss(w + e) - loss(w - e)) / 2e-5 < 1e-5


def test_adam_and_gradient_agree():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(200, 2))
    y = (x[:, 0] > 0).astype(int)
    for w in (learn.adam_softmax(x, y, 2, epochs=30), learn.gradient_softmax(x, y, 2)):
        assert ((np.hstack([x, np.ones((200, 1))]) @ w).argmax(axis=1) == y).mean() > 0.97


def test_platt_lowers_loss():
    rng = np.random.default_rng(2)
    z = rng.normal(size=500) * 4
    y = (rng.random(500) < 1 / (1 + np.exp(-0.3 * z))).astype(float)
    a, b = learn.platt_fit(z, y)
    loss = lambda a, b: -np.mean(y * np.log(1 / (1 + np.exp(-(a * z + b)))) + (1 - y) * np.log(1 - 1 / (1 + np.exp(-(a * z + b)))))
    assert loss(a, b) < loss(1, 0) and 0.1 < a < 0.6


def test_truncate_and_pick(spark):
    df = spark.createDataFrame([([0.5, 0.3, 0.2], 2), ([0.0, 0.0, 1.0], 2), ([1.0], 1)], "d array<double>, n int")
    cut = infer.truncate(F.col("d"), F.col("n"))
    rows = df.select(cut.alias("c"), infer.pick(cut).alias("a"), infer.pick(cut, "sample", F.lit(0.7)).alias("s")).collect()
    assert rows[0]["c"] == pytest.approx([0.625, 0.375]) and (rows[0]["a"], rows[0]["s"]) == (0, 1)
    assert rows[1]["c"] == [0.5, 0.5] and rows[2]["a"] == 0
    with pytest.raises(ValueError):
        infer.pick(F.col("d"), "none")


def test_measures(spark):
    runs = spark.createDataFrame([(0.9,), (0.8,), (1.0,)], "precision double")
    r = measure.run_statistics(runs).first()
    assert (r["median"], r["runs"]) == (0.9, 3) and r["mean"] == pytest.approx(0.9) and r["std_error"] == pytest.approx(0.1 / 3**0.5)


# -- the given tables, streams, SQL ---------------------------------------------------------


@pytest.mark.parametrize("name", sorted(SETS))
def test_replicas_have_truth(spark, name):
    wide = replicas(spark, D, name)
    t = truth(spark, D, name)
    c = wide.unpivot(["entity_id", "source_id"], SETS[name][2], "attr", "value").where("value is not null")
    share = measure.precision(c.select(*CELL, "value"), t).first()["precision"]
    assert 0.3 < share < 0.99


@pytest.mark.parametrize("query", ["replicas_customer", "rewrite_then_vote"])
def test_queries_see_whole_table(spark, query):
    from claimfold.catalog import QUERIES

    ids = QUERIES[query](spark, "/root/testdata/sf0.01").select("entity_id").distinct().count()
    assert ids > 1490  # of 1,500


@pytest.mark.parametrize("n", [0, 1, 2, 3, 64, 157])
def test_points_below_equal_brute_force(n):
    rng = np.random.default_rng(n)
    x, y, block = rng.integers(0, 9, n) - 4.0, rng.integers(0, 9, n) - 4.0, rng.integers(0, 3, n)
    for b in (None, block):
        same = np.ones((n, n), dtype=bool) if b is None else b[:, None] == b[None, :]
        want = (same & (x[None, :] < x[:, None]) & (y[None, :] < y[:, None])).sum(axis=1)
        assert rules._count_below(x, y, b).tolist() == want.tolist()


def test_inversions_of_whole_table_equal_brute_force(spark):
    from claimfold.catalog import QUERIES

    d = "/root/testdata/sf0.01"
    o = spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey", F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("t")).toPandas()
    k, t = o["o_orderkey"].to_numpy(), o["t"].to_numpy()
    want = {int(a): int((((t > b) & (k < a)) | ((t < b) & (k > a))).sum()) for a, b in zip(k, t, strict=True)}
    assert len(want) == 15000 and {r["o_orderkey"]: r["n"] for r in QUERIES["violations_inversion"](spark, d).collect()} == want


def test_platt_query_takes_all_rows(spark):
    from claimfold.catalog import QUERIES

    d = "/root/testdata/sf0.01"
    li = spark.read.parquet(f"{d}/lineitem.parquet").select("l_linestatus", "l_discount", "l_quantity").toPandas()
    for r in QUERIES["platt_fit"](spark, d).collect():
        own = li[li["l_linestatus"] == r["l_linestatus"]]
        a, b = learn.platt_fit(own["l_discount"].to_numpy(), (own["l_quantity"] > 25).to_numpy(float))
        assert abs(r["a"] - a) < 2e-4 and abs(r["b"] - b) < 2e-4


def test_adam_query_scores_every_embedding(spark):
    from claimfold.catalog import models

    d = "/root/testdata/sf0.001"
    got = models.softmax_fit_adam(spark, d, most=100).join(spark.read.parquet(f"{d}/embeddings.parquet"), "vec_id")
    assert got.count() == 500 and got.where("prediction % 2 = label % 2").count() == 500


def test_documents_of_one_opening_stay_apart(spark, tmp_path):
    from claimfold.catalog import QUERIES

    opening = "all rights reserved by the owners of this text and of others "
    rows = [(0, opening + "one", "en", "a", 64), (1, opening + "two", "de", "b", 64), (2, opening.upper() + " ONE", "en", "c", 65)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    votes = QUERIES["document_copies_vote"](spark, str(tmp_path)).where("attr = 'lang'").collect()
    assert sorted(r["value"] for r in votes) == ["de", "en"]
    assert sorted((r["n"], r["labelled"], r["good"]) for r in QUERIES["labels_partial_truth"](spark, str(tmp_path)).collect()) == [(1, 0, 0), (2, 1, 1)]


def test_stream_equals_batch(spark, tmp_path):
    from claimfold.streaming import votes

    events = spark.read.parquet(f"{D}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    events.repartition(3).write.parquet(str(tmp_path / "e"))
    s = votes.read_stream(spark, str(tmp_path / "e"), events.schema)
    got = sorted(map(tuple, votes.run_complete(votes.window_votes(s, "user_id", "event_type"), "test").collect()))
    want = sorted(map(tuple, events.groupBy("user_id", F.window("ts", "1 day").alias("w"), "event_type").count().select("user_id", "w.start", "event_type", "count").collect()))
    assert got == want


def test_sql_functions(spark):
    from claimfold.functions.registered import register

    register(spark)
    assert spark.sql("SELECT format_map('Ab 1') AS m").first()["m"] == "AASN"
    assert spark.sql("SELECT edit_to_format('New York-#401H3', 'Toronto-#21LG') AS e").first()["e"] == "York-#401"
    assert spark.sql("SELECT count(*) AS n FROM runs('ab-12')").first()["n"] == 3


def test_entry_contract():
    import __spark_entry__ as e

    q, s = e.queries(), e.oracle_sql()
    assert set(s) <= set(q) and len(q) > 100
