"""Models learn from all labelled and weakly labelled entities, however many they are."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from claimfold.operators import learn, packed, passes, resolver
from claimfold.plans import experiments


def _summed(lessons):
    """A pass over lessons that lie in a list."""

    def passed(work, keys, valid):
        sums = {}
        for key, lesson in lessons:
            if keys is None or key in keys:
                for name, v in work(key, lesson.cells(lesson.role == passes.VALIDATION) if valid else lesson):
                    sums[key, name] = passes._merged(name, sums[key, name], v) if (key, name) in sums else np.asarray(v, float)
        return sums

    return passed


@pytest.mark.parametrize("changes", [{}, {"calibrate": "temperature"}, {"source_ridges": (1.0,), "calibrate": None}])
def test_fits_by_passes_are_those_of_one_task(changes):
    """Sums over parts of the cells find the ridge, weights and calibration of a fit that holds all cells at once; a constant feature, cells of one candidate and unclaimed truths among them."""
    rng = np.random.default_rng(8)
    size = rng.integers(1, 6, 900)
    entity = np.repeat(np.arange(900), size)
    n = len(entity)
    x = np.column_stack([rng.normal(size=(n, 4)), np.full(n, 0.1), 5 + rng.random(n)])
    block = rng.integers(0, 2, (n, 3)).astype(float)
    score = x[:, :4] @ rng.normal(size=4) + block @ np.array([1.0, -1.0, 0.0]) + 2 * rng.gumbel(size=n)
    y = np.zeros(n)
    for e in range(0, 900):
        if e % 10:
            at = np.flatnonzero(entity == e)
            y[at[score[at].argmax()]] = 1
    role = rng.choice([passes.TRAIN, passes.VALIDATION, passes.WEAK], 900, p=[0.2, 0.1, 0.7])
    for e in np.flatnonzero(role == passes.WEAK):  # weak cells have a label always
        at = np.flatnonzero(entity == e)
        y[at] = np.arange(len(at)) == 0
    part = role[entity].astype(np.int8)
    s = resolver.Settings(("a",), **changes)
    alone = resolver.candidate_fit(x, block, y, entity, np.array(["train", "validation", "weak"])[part], np.where(part == passes.WEAK, s.weak_weight, 1.0), s)
    lessons = []
    for lo in range(0, 900, 130):
        at = (entity >= lo) & (entity < lo + 130)
        lessons.append(("0|a", passes.Lesson(np.hstack([x, block])[at], y[at], entity[at], part[at], x.shape[1])))
    got = passes.fit(_summed(lessons), lambda key: s, lambda key, d: np.zeros(d))["0|a"]
    assert got["l2"] == alone["l2"] and got["mean"] == pytest.approx(alone["mean"]) and got["scale"] == pytest.approx(alone["scale"])
    assert got["w"] == pytest.approx(alone["w"], abs=1e-4) and (got["a"], got["b"]) == pytest.approx((alone["a"], alone["b"]), abs=1e-3)


def test_packed_fits_by_passes_are_those_by_tasks(spark, monkeypatch):
    """F3 (also F1, F2, F4 to F8): stages of fits and runs over batches, with sources and without, give the models and precisions of fits in a task each."""
    monkeypatch.setattr(packed, "BATCH", 100)
    w = experiments.Workload(spark, "/root/testdata/sf0.01", "supplier", 0.3, runs=2, limit=60)
    fits = [w.settings(stages=2, models=("vote", "cooc", "running", "source"), source_ridges=(1.0,)), w.settings(stages=2, models=("vote",), train_on="seed")]
    one = w.packed.fit(fits, w.split, w.runs)
    alone = w.packed.precisions(_said(w, fits, one), w.split, w.runs)
    monkeypatch.setattr(passes, "TASK_NUMBERS", 0)
    made = w.packed.fit(fits, w.split, w.runs)
    for f, g in zip(made, one, strict=True):
        assert f.names == g.names and f.sources == g.sources
        for m, n in zip(f.stages, g.stages, strict=True):
            assert m.weights.keys() == n.weights.keys() and len(m.weights) == 6
            for k in n.weights:
                assert m.weights[k] == pytest.approx(n.weights[k], abs=1e-3) and m.scales[k] == pytest.approx(n.scales[k]), k
    assert w.packed.precisions(_said(w, fits, made), w.split, w.runs) == alone


def _said(w, fits, fitted):
    plans = [packed.Plan(s, w.packed._columns(s), w.packed.attrs, len(f.sources) + 1 if f.sources else 0, f.stages) for s, f in zip(fits, fitted, strict=True)]
    return lambda p, r: [plan.forward(p, r) for plan in plans]


def test_calibration_stays_where_steps_would_lead_away():
    """F3 (also F1, F2, F4 to F8): cells that are right or wrong for sure bend the loss little; steps end at its least, not far from it."""
    score = np.array([20.7] * 30 + [-20.7] * 30 + [20.7, -20.7, 19.0, -18.0])
    y = np.array([0.97] * 30 + [0.03] * 30 + [0.03, 0.97, 0.03, 0.97])
    a, b = learn.platt_fit(score, y)
    loss = lambda a, b: learn.platt_step(learn.platt_sums(score, y, a, b), len(y), a, b)[0]
    assert 0 < a < 1 and abs(b) < 1 and loss(a, b) <= min(loss(c, d) for c in np.linspace(0, 1, 101) for d in np.linspace(-0.5, 0.5, 21)) + 1e-9


def test_models_learn_from_all_entities(spark):
    """F3, F9 (also F1, F2, F4 to F8): 5000 known entities and as many others aren't the most that models see."""
    rows = spark.range(16_000).select(F.col("id").alias("entity_id"), F.explode(F.expr("array(0, 1)")).alias("source_id"), F.expr("concat('v', id % 7)").alias("a"))
    s = resolver.Settings(("a",), models=("vote",))
    p = packed.Packed(rows, s, rows.where("source_id = 0").select("entity_id", "a"))
    split = p.split(0.5, 1, s)
    seen = np.zeros(4, int)
    for r in p.rows.collect():
        seen += [v.sum() for v in split.roles(packed.Pack.read(r, 1), 0, s.seed)]
    assert seen[0] == seen[1] == seen[3] == 8000
    seeds = rows.where("source_id = 0 and entity_id % 2 = 0").select("entity_id", F.lit("a").alias("attr"), F.col("a").alias("value"))
    cands = resolver.prepare(rows, s).cands
    for runs in (1, 2):
        part = F.when(F.col("part") == "weak", "weak").otherwise("known")
        labels = resolver._label_table(cands, seeds, None, resolver.replace(s, runs=runs)).groupBy(part.alias("part")).count()
        assert {r["part"]: r["count"] for r in labels.collect()} == {"known": 8000, "weak": 8000}
