"""The resolver against plain Python: records without sources, layouts, the twin, leaks, runs."""

import math
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from claimfold.operators import augment, claims, measure, resolver
from claimfold.operators.claims import RUN, run_of
from claimfold.plans import modules, rules

CELL = ["entity_id", "attr"]
SCHEMA = "entity_id long, zip string, city string"
RULE = "not(t1.zip = t2.zip and t1.city != t2.city)"


def records():
    """Records without sources; some repeat altogether."""
    rng = random.Random(4)
    rows = []
    for e in range(40):
        zip_, city = str(e % 7), f"town {e % 7}"
        for _ in range(rng.randint(2, 6)):
            rows.append((e, zip_ if rng.random() < 0.8 else str(rng.randrange(7)), city if rng.random() < 0.8 else rng.choice(["town 1", "TOWN", None])))
        rows.append(rows[-1])
    return rows


@pytest.fixture(scope="module")
def wide(spark):
    return spark.createDataFrame(records(), SCHEMA)


@pytest.fixture(scope="module")
def seeds(spark):
    return spark.createDataFrame([(e, a, v) for e in range(0, 40, 2) for a, v in (("zip", str(e % 7)), ("city", f"town {e % 7}"))], "entity_id long, attr string, value string")


def test_source_free_static_features(wide):
    """Supports, vote shares and rule counts, every record counted once."""
    s = resolver.Settings(("zip", "city"), use_source=False, rules=(RULE,), models=("vote", "rules"))
    cands, names = resolver._static(resolver.number_records(wide, s, "test"), s)
    assert names == ["vote_share", "rule0"]
    rows = records()
    broken = [sum(1 for b in rows if a[1] == b[1] and None not in (a[2], b[2]) and a[2] != b[2]) for a in rows]
    want = {}
    for (e, z, c), n in zip(rows, broken, strict=True):
        for attr, v in (("zip", z), ("city", c)):
            if v is not None:
                want.setdefault((e, attr, v), []).append(math.log1p(n))
    got = {(r["entity_id"], r["attr"], r["value"]): r for r in cands.collect()}
    assert set(got) == set(want)
    for key, logs in want.items():
        total = sum(len(v) for k, v in want.items() if k[:2] == key[:2])
        assert got[key]["support"] == len(logs)
        assert got[key]["static"] == pytest.approx([len(logs) / total, sum(logs) / len(logs)])


def test_augmented_records_stay_records(spark, wide, seeds):
    """Synthetic records are as many as those they copy, hold their true values, and edits of the others."""
    s = resolver.Settings(("zip", "city"))
    more, truth = augment.augment_records(resolver.number_records(wide, s, "test"), seeds, ["zip", "city"], 1.0, 0)
    made = more.where("entity_id < 0").collect()
    rows = records()
    copied = {-(e * 64 + 1): e for e in range(0, 40, 2)}
    assert Counter(r["entity_id"] for r in made) == Counter(i for i, e in copied.items() for r in rows if r[0] == e)
    known = {(r["entity_id"], r["attr"]): r["value"] for r in truth.where("entity_id < 0").collect()}
    for i, e in copied.items():
        for attr, at, right in (("zip", 1, str(e % 7)), ("city", 2, f"town {e % 7}")):
            assert known[i, attr] == right
            mine = sorted(r[attr] for r in made if r["entity_id"] == i and r[attr] == right)
            assert len(mine) >= sum(1 for r in rows if r[0] == e and r[at] == right)
    assert more.where("entity_id >= 0").count() == len(rows)


def test_source_free_resolution_with_rules_and_augmentation(wide, seeds):
    s = resolver.Settings(("zip", "city"), use_source=False, rules=(RULE,), augment=0.5, stages=2, embed_dim=8)
    _, scored = resolver.fit(wide, seeds, s)
    answers = resolver.resolve(scored, seeds)
    cells = {(r[0], a) for r in records() for a, v in (("zip", r[1]), ("city", r[2])) if v is not None}
    got = [(r["entity_id"], r["attr"]) for r in answers.collect()]
    assert len(got) == len(set(got)) and set(got) == cells


def test_literal_layout_by_numpy(spark, wide, seeds):
    """Probabilities of the layout 'cell': mean of the claims' softmax outputs, cut to the real slots, renormalised."""
    s = resolver.Settings(("zip", "city"), use_source=False, models=("vote", "format"), layout="cell", stages=1, max_slots=6, calibrate=None, weak_weight=0.0)
    fitted, scored = resolver.fit(wide, seeds, s)
    m = fitted.stages[0]
    t = resolver._tables(wide, None, s, [], "test")
    featured, _ = resolver._featured(t, resolver._first_votes(t), s, 0)
    by = {}
    for r in featured.collect():
        x = (np.array(r["x"]) - m.means[r["attr"]]) / m.scales[r["attr"]]
        z = np.append(x, 1.0) @ np.array(m.weights[r["attr"]])
        e = np.exp(z - z.max())
        by.setdefault((r["entity_id"], r["attr"]), []).append((e / e.sum(), r["value"], r["slot"], r["n_slots"]))
    n_claims = sum(len(v) for v in by.values())
    assert n_claims == sum(1 for r in records() for v in r[1:] if v is not None)
    for r in scored.collect():
        cell = by[r["entity_id"], r["attr"]]
        mean = np.mean([d for d, *_ in cell], axis=0)[: cell[0][3]]
        assert r["p"] == pytest.approx(mean[r["slot"]] / mean.sum(), abs=1e-9)


@pytest.mark.parametrize("changes", [{"layout": "cell_own_slot", "classifier": "tree"}, {"layout": "entity_slots"}, {"layout": "cell", "classifier": "logreg_ovr", "fuse": "weighted"}, {"embed": "word2vec"}, {"cooc_values": "raw", "nulls": "as_value"}, {"rules": (RULE,), "rule_partners": "predicted"}, {"stages": 9, "early_stop": 0.5}, {"slot_order": "value", "pick": "sample", "calibrate": "temperature"}])
def test_variants_give_distributions(wide, seeds, changes):
    s = resolver.Settings(("zip", "city"), **{"stages": 2, "max_slots": 6, "embed_dim": 8, **changes})
    fitted, scored = resolver.fit(wide.withColumn("source_id", F.lit(None).cast("int")), seeds, s)
    low, high, n = scored.groupBy(*CELL).agg(F.sum("p").alias("s")).agg(F.min("s"), F.max("s"), F.count("s")).first()
    assert low == pytest.approx(1) and high == pytest.approx(1) and n >= 79
    assert len(fitted.stages) == (2 if "early_stop" not in changes else len(fitted.stages)) and len(fitted.stages) < 9
    assert resolver.resolve_new(fitted, wide).select(*CELL).distinct().count() == n


def test_weighted_fusion_uses_accuracies(spark):
    """Two good sources outweigh three bad ones that agree."""
    rows = [(e, k, f"v{e}" if k < 2 else f"w{e}") for e in range(60) for k in range(5)]
    wide = spark.createDataFrame(rows, "entity_id long, source_id int, a string")
    seeds = spark.createDataFrame([(e, "a", f"v{e}") for e in range(30)], "entity_id long, attr string, value string")
    s = resolver.Settings(("a",), layout="cell", fuse="weighted", stages=1, max_slots=4, embed_dim=4, weak_weight=0.0)
    _, scored = resolver.fit(wide, seeds, s)
    assert all(r["value"].startswith("v") for r in resolver.resolve(scored).collect())


def test_twin_gives_the_same_answers(wide, seeds):
    s = resolver.Settings(("zip", "city"), use_source=False, stages=3, first_dynamic="zero", embed_dim=8)
    _, stagewise = resolver.fit(wide, seeds, s)
    a = {(r["entity_id"], r["attr"], r["value"]): r["p"] for r in stagewise.collect()}
    b = {(r["entity_id"], r["attr"], r["value"]): r["p"] for r in resolver.resolve_dynamic(wide, seeds, s).collect()}
    assert set(a) == set(b) and all(a[k] == pytest.approx(b[k], abs=1e-9) for k in a)


def test_trust_leaves_its_own_fold_out(spark):
    """Changing the truth of one seed entity doesn't change the feature of its own cells."""
    rows = [(e, k, f"v{e}" if (e + k) % 3 else f"w{e}") for e in range(60) for k in range(4)]
    s = resolver.Settings(("a",), trust=True)
    wide = resolver.number_records(spark.createDataFrame(rows, "entity_id long, source_id int, a string"), s, "trust")
    sums = []
    for truth in ("v", "x"):
        seeds = spark.createDataFrame([(e, "a", f"{'v' if e else truth}{e}") for e in range(30)], "entity_id long, attr string, value string")
        sums.append({(r["entity_id"], r["value"]): r["_trust"] for r in resolver._trust_table(wide, seeds, s)[1].collect()})
    assert all(sums[0][k] == pytest.approx(sums[1][k]) for k in sums[0] if k[0] == 0)
    assert any(sums[0][k] != sums[1][k] for k in sums[0])
    assert not resolver.Settings(("a",)).trust


def test_permuted_truth_teaches_nothing(spark):
    """Seeds whose truth is drawn among the candidates lead to the share that a draw would have."""
    rng = random.Random(3)
    rows = [(e, k, f"{'ab'[rng.randrange(2)]}{e}") for e in range(400) for k in range(2)]
    rows = [r for r in rows if {f"a{r[0]}", f"b{r[0]}"} == {x[2] for x in rows if x[0] == r[0]}]
    wide = spark.createDataFrame(rows, "entity_id long, source_id int, a string")
    ids = sorted({r[0] for r in rows})
    truth = {e: f"{'ab'[rng.randrange(2)]}{e}" for e in ids}
    frame = lambda t: spark.createDataFrame([(e, "a", v) for e, v in t.items()], "entity_id long, attr string, value string")
    half = ids[: len(ids) // 2]
    _, scored = resolver.fit(wide, frame({e: truth[e] for e in half}), resolver.Settings(("a",), stages=1, embed_dim=8, train_on="seed"))
    p = measure.precision(resolver.resolve(scored), frame({e: truth[e] for e in ids if e not in set(half)})).first()["precision"]
    assert 0.35 < p < 0.65


def test_predicted_partners_by_nested_loops(spark):
    rng = random.Random(5)
    rows = [(i, i // 3, rng.choice(["1", "2", None]), rng.choice(["x", "y", None])) for i in range(60)]
    golden = [(e, rng.choice(["1", "2", None]), rng.choice(["x", "y", None])) for e in range(20)]
    df = spark.createDataFrame(rows, "id long, e long, zip string, city string")
    partners = spark.createDataFrame(golden, "e long, zip string, city string")
    for text, test in ((RULE, lambda a, b: None not in (a[0], b[0], a[1], b[1]) and a[0] == b[0] and a[1] != b[1]), ("not(t1.zip = t2.zip and t1.city < t2.city)", lambda a, b: None not in (a[0], b[0], a[1], b[1]) and a[0] == b[0] and a[1] != b[1])):
        got = {r["id"]: r["n"] for r in rules.violations_against(df, partners, rules.parse_rule(text), "id", "e").collect()}
        assert got == {i: sum(1 for f, z, c in golden if f != e and test((zip_, city), (z, c))) for i, e, zip_, city in rows}
    with pytest.raises(rules.RuleError):
        rules.violations_against(df, partners, rules.parse_rule("not(t1.zip < t2.zip)"), "id", "e")


def test_runs_in_one_table_are_strangers(spark, wide, seeds):
    s = resolver.Settings(("zip", "city"), use_source=False, stages=2, embed_dim=8, augment=0.5)
    shift = lambda df, r: df.withColumn("entity_id", F.col("entity_id") + r * RUN)
    other = seeds.where("entity_id % 4 = 0")
    both = resolver.fit(wide.union(shift(wide, 1)), seeds.union(shift(other, 1)), resolver.Settings(**{**s.__dict__, "runs": 2, "augment": 0.0}))[1]
    for r, part in ((0, seeds), (1, other)):
        alone = resolver.fit(shift(wide, r), shift(part, r), resolver.Settings(**{**s.__dict__, "augment": 0.0}))[1]
        a = {(x["entity_id"], x["attr"], x["value"]): x["p"] for x in alone.collect()}
        b = {(x["entity_id"], x["attr"], x["value"]): x["p"] for x in both.where(run_of("entity_id") == r).collect()}
        assert set(a) == set(b) and sum(abs(a[k] - b[k]) > 0.25 for k in a) < 0.1 * len(a)
    assert spark.createDataFrame([(-(5 * RUN + 3) * 64 - 1,)], "entity_id long").select(run_of("entity_id")).first()[0] == 5


def test_modules(spark, wide, seeds, tmp_path):
    augmenter = modules.Augmenter(["zip", "city"], seeds, 0.5)
    records_ = augmenter.transform(wide)
    model = modules.Resolver(attrs=["zip", "city"], seeds=augmenter.truth(), use_source=False, stages=1, embed_dim=8).fit(records_)
    answers = modules.Answers().transform(model.transform(wide))
    assert answers.count() == claims.golden(answers, ["zip", "city"]).select(F.count("zip") + F.count("city")).first()[0]
    model.save(str(tmp_path / "m"))
    assert modules.ResolverModel.load(str(tmp_path / "m")).fitted.stages == model.fitted.stages
    assert modules.Featurizer(resolver.Settings(("zip", "city"))).transform(wide).columns == [*CELL, "value", "support", "slot", "n_slots", "static", "sources"]


@pytest.mark.parametrize("bad", [{"fuse": "x"}, {"classifier": "tree"}, {"dist": "x"}, {"embed": "x"}, {"pick": "x"}, {"calibrate": "x"}, {"runs": 0}, {"rule_partners": "x"}, {"cooc_values": "x"}])
def test_settings_are_checked(bad):
    with pytest.raises(ValueError):
        resolver.Settings(("a",), **bad)
