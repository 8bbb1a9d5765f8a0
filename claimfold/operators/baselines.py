"""Rivals: votes, heuristics, and models of source trust.

Claims are (entity_id, source_id, attr, value); answers are (entity_id, attr,
value, score), one row a cell.  Source tables have one row a source and join by
whatever their size allows; each round of a loop writes them to the workspace.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..functions.noise import mix
from ..plans.workspace import settle
from .augment import runs_python
from .claims import CELL, F_ATTR, candidates, vote_labels


def best(scored: DataFrame) -> DataFrame:
    """The highest score of each cell; ties by value.  Scores that differ by less than 1e-9 are ties, in whatever order they were summed."""
    w = Window.partitionBy(*CELL).orderBy(F.desc(F.round("score", 9)), F.asc("value"))
    return scored.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*CELL, "value", "score")


def majority_vote(claims: DataFrame, tie: str = "value", seed: int = 0) -> DataFrame:
    cands = candidates(claims)
    return vote_labels(cands, tie, seed).select(*CELL, "value", F.col("support").cast("double").alias("score"))


HEURISTICS = ("longest", "shortest", "latest", "earliest", "min", "max", "mean", "median", "prefer_source", "any")


def heuristic(claims: DataFrame, rule: str, at: str | None = None, source: int | None = None) -> DataFrame:
    """One answer a cell by a fixed rule; `at` orders latest and earliest, `source` is the preferred one."""
    if rule not in HEURISTICS:
        raise ValueError(f"rule must be one of {HEURISTICS}")
    known = claims.where("value is not null")
    number = F.col("value").cast("double")
    if rule in ("mean", "median"):
        agg = (F.avg if rule == "mean" else F.median)(number).alias("value")
        return known.groupBy(*CELL).agg(agg)
    keys = {
        "longest": [F.length("value").desc(), F.asc("value")], "shortest": [F.length("value").asc(), F.asc("value")],
        "min": [F.asc("value")], "any": [F.asc("value")], "max": [F.desc("value")],
        "prefer_source": [(F.col("source_id") == F.lit(source)).desc_nulls_last(), F.asc("value")] if "source_id" in claims.columns else None,
        "latest": [F.desc(at), F.asc("value")] if at else None, "earliest": [F.asc(at), F.asc("value")] if at else None,
    }[rule]
    if keys is None:
        raise ValueError(f"{rule} needs its column")
    w = Window.partitionBy(*CELL).orderBy(*keys)
    return known.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*CELL, "value")


def supports(claims: DataFrame) -> DataFrame:
    """(entity_id, attr, value, source_id, m): claims with the number of candidates of their cell."""
    rows = claims.select(*CELL, "value", "source_id").distinct()
    return rows.withColumn("m", F.size(F.collect_set("value").over(Window.partitionBy(*CELL))))


def source_accuracy(claims: DataFrame, seeds: DataFrame, smoothing: float = 1.0) -> DataFrame:
    """(source_id, right, labelled, accuracy) from cells of known truth; clipped to [0.01, 0.99]."""
    truth = seeds.select(*CELL, F.col("value").alias("truth"))
    rows = claims.select(*CELL, "value", "source_id").distinct().join(truth, list(CELL), "left")
    per = rows.groupBy("source_id").agg(F.sum(F.when(F.col("truth").isNotNull(), (F.col("value") == F.col("truth")).cast("long")).otherwise(0)).alias("right"), F.sum(F.col("truth").isNotNull().cast("long")).alias("labelled"))
    pooled = per.agg((F.sum("right") / F.sum("labelled")).alias("pooled"))
    a = F.when(F.col("labelled") > 0, (F.col("right") + smoothing) / (F.col("labelled") + 2 * smoothing)).otherwise(F.coalesce("pooled", F.lit(0.5)))
    return per.crossJoin(F.broadcast(pooled)).select("source_id", "right", "labelled", F.greatest(F.lit(0.01), F.least(F.lit(0.99), a)).alias("accuracy"))


def _scores(held: DataFrame, sources: DataFrame, weight: Column) -> DataFrame:
    """Sum of source weights for each candidate."""
    return held.join(sources, "source_id").groupBy(*CELL, "value", "m").agg(F.sum(weight).alias("score"))


def posterior(scored: DataFrame) -> DataFrame:
    """Softmax of scores within each cell, shifted by the largest."""
    w = Window.partitionBy(*CELL)
    e = F.exp(F.col("score") - F.max("score").over(w))
    return scored.withColumn("_e", e).withColumn("p", F.col("_e") / F.sum("_e").over(w)).drop("_e")


def seed_accuracy_bayes(claims: DataFrame, seeds: DataFrame, smoothing: float = 1.0) -> DataFrame:
    a = F.col("accuracy")
    weight = F.log(a) - F.log((1 - a) / F.greatest(F.col("m") - 1, F.lit(1)))
    return best(_scores(supports(claims), source_accuracy(claims, seeds, smoothing), weight))


def _clamp(p: DataFrame, seeds: DataFrame | None) -> DataFrame:
    """Posteriors of seed cells are 0 and 1."""
    if seeds is None:
        return p
    truth = seeds.select(*CELL, F.col("value").alias("_truth"))
    return p.join(truth, list(CELL), "left").withColumn("p", F.when(F.col("_truth").isNull(), F.col("p")).otherwise((F.col("value") == F.col("_truth")).cast("double"))).drop("_truth")


def iterative_bayes(claims: DataFrame, a0: float = 0.8, max_iter: int = 20, eps: float = 1e-4, seeds: DataFrame | None = None, settled: bool = True) -> DataFrame:
    """Accuracies and posteriors in turns, without looking for copying sources."""
    held = settle(supports(claims), "bayes-supports") if settled else supports(claims)
    sources = held.select("source_id").distinct().withColumn("accuracy", F.lit(a0))
    a = F.greatest(F.lit(0.01), F.least(F.lit(0.99), F.col("accuracy")))
    weight = F.log(F.col("m") * a / (1 - a))
    for _ in range(max_iter):
        p = _clamp(posterior(_scores(held, sources, weight)), seeds)
        new = held.join(p.select(*CELL, "value", "p"), [*CELL, "value"]).groupBy("source_id").agg(F.avg("p").alias("accuracy"))
        if not settled:
            sources = new
            continue
        new = settle(new, "bayes-sources")
        change = new.alias("n").join(sources.alias("o"), "source_id").agg(F.max(F.abs(F.col("n.accuracy") - F.col("o.accuracy")))).first()[0]
        sources = new
        if change is None or change < eps:
            break
    return best(posterior(_scores(held, sources, weight)).select(*CELL, "value", F.col("p").alias("score")))


def _gamma_lower(a: float, x: float) -> float:
    """Regularised lower incomplete gamma: a series below a + 1, a continued fraction above."""
    if x <= 0:
        return 0.0
    front = math.exp(a * math.log(x) - x - math.lgamma(a))
    if x < a + 1:
        term = total = 1 / a
        k = a
        while abs(term) > abs(total) * 1e-15:
            k += 1
            term *= x / k
            total += term
        return front * total
    tiny = 1e-300
    b, c = x + 1 - a, 1 / tiny
    d = 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = an * d + b
        d = 1 / (d if abs(d) > tiny else tiny)
        c = b + an / c
        c = c if abs(c) > tiny else tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return 1 - front * h


def chi2inv(p: float, k: float) -> float:
    """Quantile of the chi-square distribution with k degrees of freedom, by bisection."""
    if not 0 < p < 1 or k <= 0:
        raise ValueError("0 < p < 1 and k > 0 are needed")
    lo, hi = 0.0, max(10.0, 4 * k)
    while _gamma_lower(k / 2, hi / 2) < p:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if _gamma_lower(k / 2, mid / 2) < p else (lo, mid)
    return (lo + hi) / 2


def chi2inv_cube(p_normal: float, k: Column) -> Column:
    """The cube formula, fine from ten degrees of freedom; p_normal is the normal quantile of p."""
    return k * F.pow(1 - 2 / (9 * k) + p_normal * F.sqrt(2 / (9 * k)), 3)


@F.pandas_udf(T.DoubleType())
def _chi2inv_column(p: pd.Series, k: pd.Series) -> pd.Series:
    return pd.Series([chi2inv(a, b) for a, b in zip(p, k, strict=True)])


def interval_weighted_vote(claims: DataFrame, alpha: float = 0.05, iters: int = 10, exact: bool = True, numeric: tuple[str, ...] = ()) -> DataFrame:
    """Weights by the chi-square quantile of a source's claims over its losses: few claims weigh little.

    A claim loses 1 if it is not the answer.  For `numeric` attributes the answer is
    the weighted mean, and a claim loses its squared distance to it over the
    variance of its cell; their answers are numbers as text, without exponent.
    """
    held = settle(supports(claims).withColumn("x", F.when(F.col("attr").isin(*numeric), F.col("value").cast("double")) if numeric else F.lit(None).cast("double")), "interval-supports")
    size = held.groupBy("source_id").agg(F.count(F.lit(1)).cast("double").alias("n"))
    quantile = _chi2inv_column(F.lit(alpha / 2), F.col("n")) if exact else chi2inv_cube(-1.959963984540054, F.col("n"))
    size = settle(size.withColumn("q", quantile), "interval-sizes")
    spread = held.where("x is not null").groupBy(*CELL).agg(F.var_pop("x").alias("_v"), F.avg("x").alias("_m"))

    def means(rows: DataFrame, w: Column) -> DataFrame:
        total = rows.where("x is not null").groupBy(*CELL).agg((F.sum(F.col("x") * w) / F.sum(w)).alias("_m"), F.sum(w).alias("score"))
        return total.select(*CELL, F.col("_m").cast("decimal(38,6)").cast("string").alias("value"), "score")

    def answers(rows: DataFrame, w: Column) -> DataFrame:
        voted = best(rows.where("x is null").groupBy(*CELL, "value").agg(F.sum(w).alias("score")))
        return voted.unionByName(means(rows, w)) if numeric else voted

    answer = answers(held, F.lit(1.0))
    for _ in range(iters):
        judged = held.join(answer.select(*CELL, F.col("value").alias("_a")), list(CELL))
        loss = (F.col("value") != F.col("_a")).cast("double")
        if numeric:
            gap = F.pow(F.col("x") - F.col("_a").cast("double"), F.lit(2.0))
            judged = judged.join(spread.select(*CELL, "_v"), list(CELL), "left")
            loss = F.when(F.col("x").isNull(), loss).when(F.col("_v") > 0, gap / F.col("_v")).otherwise(0.0)
        lost = judged.groupBy("source_id").agg(F.sum(loss).alias("loss"))
        sources = settle(size.join(lost, "source_id").select("source_id", (F.col("q") / (F.col("loss") + 1e-6)).alias("w")), "interval-sources")
        answer = answers(held.join(sources, "source_id"), F.col("w"))
    return answer


def claim_graph_propagation(claims: DataFrame, seeds: DataFrame, iters: int = 20, gain: float = 1.0, rival: float = 1.0) -> DataFrame:
    """Scores of facts spread through sources that agree and against rivals; a source's clique is its mean."""
    held = settle(supports(claims), "graph-supports")
    truth = seeds.select(*CELL, F.col("value").alias("truth"))
    facts = held.select(*CELL, "value").distinct().join(truth, list(CELL), "left")
    clamp = F.when(F.col("truth").isNull(), F.lit(None).cast("double")).when(F.col("value") == F.col("truth"), 1.0).otherwise(-1.0)
    facts = settle(facts.select(*CELL, "value", clamp.alias("clamp")), "graph-facts")
    state = facts.select("*", F.coalesce("clamp", F.lit(0.0)).alias("f"))
    for _ in range(iters):
        per_source = held.join(state.select(*CELL, "value", "f"), [*CELL, "value"]).groupBy("source_id").agg(F.avg("f").alias("mean"))
        pull = held.join(per_source, "source_id").groupBy(*CELL, "value").agg(F.sum("mean").alias("pull"))
        cell = Window.partitionBy(*CELL)
        up = F.greatest(F.col("f"), F.lit(0.0))
        rivals = state.withColumn("rivals", F.sum(up).over(cell) - up).join(pull, [*CELL, "value"])
        moved = F.tanh(F.lit(gain) * F.col("pull") - F.lit(rival) * F.col("rivals"))
        state = settle(rivals.select(*CELL, "value", "clamp", F.coalesce("clamp", moved).alias("f")), "graph-state")
    # Supporters break what propagation leaves equal.
    size = held.groupBy(*CELL, "value").agg(F.count(F.lit(1)).alias("n"))
    return best(state.join(size, [*CELL, "value"]).select(*CELL, "value", ((F.col("f") + 1) / 2 + F.col("n") * 1e-6).alias("score")))


def discriminative_gradient(held: DataFrame, p: DataFrame, target: DataFrame) -> DataFrame:
    """(source_id, gradient): observed less expected support of each source over the target cells.

    target is (entity_id, attr, value, t), the weight of each candidate as truth.
    """
    both = p.select(*CELL, "value", "p").join(target.select(*CELL, "value", "t"), [*CELL, "value"])
    return held.join(both, [*CELL, "value"]).groupBy("source_id").agg(F.sum(F.col("t") - F.col("p")).alias("gradient"))


def discriminative_source_model(claims: DataFrame, seeds: DataFrame, mode: str = "auto", l2: float = 0.01, iters: int = 30, rate: float = 4.0) -> DataFrame:
    """Log-linear weights of sources: by gradient on seeds ('erm'), or with posteriors of all cells as soft truth ('em')."""
    held = settle(supports(claims), "source-model-supports")
    truth = seeds.select(*CELL, F.col("value").alias("truth"))
    if mode == "auto":
        labelled = held.join(truth, list(CELL), "left").groupBy("source_id").agg(F.sum(F.col("truth").isNotNull().cast("long")).alias("n")).agg(F.median("n")).first()[0]
        mode = "erm" if (labelled or 0) >= 10 else "em"
    if mode not in ("erm", "em"):
        raise ValueError("mode must be 'auto', 'erm' or 'em'")
    sources = held.groupBy("source_id").agg(F.count(F.lit(1)).alias("claims")).withColumn("w", F.lit(1.0))
    on = settle(held.join(truth, list(CELL)), "source-model-seeds") if mode == "erm" else held.join(truth, list(CELL), "left")
    n = on.groupBy("source_id").agg(F.count(F.lit(1)).alias("n"))
    sources = settle(sources.join(n, "source_id", "left"), "source-model-weights")
    for _ in range(iters):
        p = posterior(_scores(on if mode == "erm" else held, sources, F.col("w")))
        t = p.join(truth, list(CELL), "left")
        soft = F.when(F.col("truth").isNotNull(), (F.col("value") == F.col("truth")).cast("double")).otherwise(F.pow(F.col("p"), F.lit(2.0)))
        norm = Window.partitionBy(*CELL)
        target = t.withColumn("_t", soft).withColumn("t", F.col("_t") / F.greatest(F.sum("_t").over(norm), F.lit(1e-12)))
        g = discriminative_gradient(held if mode == "em" else on.drop("truth"), p, target)
        step = F.coalesce(F.col("gradient") / F.greatest(F.col("n"), F.lit(1)), F.lit(0.0)) - 2 * l2 * F.col("w")
        sources = settle(sources.join(g, "source_id", "left").select("source_id", "claims", "n", (F.col("w") + rate * step).alias("w")), "source-model-weights")
    return best(posterior(_scores(held, sources, F.col("w"))).select(*CELL, "value", F.col("p").alias("score")))


def rewrite_program(a: str, b: str) -> str:
    """A name for the way from a to b: the runs' formats of a, and each run of b as made from a run of a.

    A run is a copy ($0), a copy in upper, lower or title case (U$0, L$0, T$0), a copy
    without its last k characters ($0<k), or a constant.  So values that change in one
    way share a program, whatever their texts.
    """
    left = runs_python(a)
    texts = [t for _, t in left]
    out = []
    for _, t in runs_python(b):
        if t in texts:
            out.append(f"${texts.index(t)}" if t.isalnum() else f"'{t}'")
            continue
        cased = next((f"{how}${i}" for i, x in enumerate(texts) if x.isalnum() for how, y in (("U", x.upper()), ("L", x.lower()), ("T", x.title())) if y == t), None)
        cut = next((f"${i}<{len(x) - len(t)}" for i, x in enumerate(texts) if t.isalnum() and x.startswith(t)), None)
        out.append(cased or cut or f"'{t}'")
    return "".join(s for s, _ in left) + "=>" + "".join(out)


@F.pandas_udf(T.StringType())
def _program(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([rewrite_program(x, y) for x, y in zip(a, b, strict=True)])


def rewrite_pairs(claims: DataFrame, pairs: str = "top") -> DataFrame:
    """(attr, rare, frequent, program, n_entities): value pairs within cells, the rarer to the more supported.

    'top' pairs each candidate with its cell's best, linear in candidates; 'all'
    pairs it with every candidate before it.
    """
    if pairs not in ("top", "all"):
        raise ValueError("pairs must be 'top' or 'all'")
    cands = candidates(claims)
    before = (cands.where("slot = 0") if pairs == "top" else cands).select(*CELL, F.col("value").alias("frequent"), F.col("slot").alias("_first"))
    both = cands.where("slot > 0").join(before, list(CELL)).where("_first < slot").groupBy("attr", F.col("value").alias("rare"), "frequent").agg(F.count_distinct("entity_id").alias("n_entities"))
    return both.withColumn("program", _program("rare", "frequent"))


def rewrite_then_vote(claims: DataFrame, budget: int = 100, oracle: DataFrame | None = None, least: int = 2, pairs: str = "top") -> tuple[DataFrame, int]:
    """Rewrite values by accepted programs, then vote; and the number of questions asked.

    Programs come in the order of the entities they touch.  A verifier (truth,
    for simulation) is asked for `budget` of them and accepts one if most of its
    pairs lead to a true value; without one, a program of `least` entities is accepted.
    """
    found = settle(rewrite_pairs(claims, pairs), "rewrite-pairs")
    ranked = found.groupBy("attr", "program").agg(F.sum("n_entities").alias("n")).orderBy(F.desc("n"), "attr", "program").limit(budget)
    asked = ranked.count()
    if oracle is None:
        accepted = ranked.where(F.col("n") >= least).select("attr", "program")
    else:
        true = oracle.select("attr", F.col("value").alias("frequent")).distinct().withColumn("ok", F.lit(1))
        wrong = oracle.select("attr", F.col("value").alias("rare")).distinct().withColumn("also", F.lit(1))
        seen = found.join(ranked.select("attr", "program"), ["attr", "program"]).join(true, ["attr", "frequent"], "left").join(wrong, ["attr", "rare"], "left")
        share = F.avg((F.col("ok").isNotNull() & F.col("also").isNull()).cast("double"))
        accepted = seen.groupBy("attr", "program").agg(share.alias("share")).where("share > 0.5").select("attr", "program")
    rewrites = found.join(accepted, ["attr", "program"]).groupBy("attr", F.col("rare").alias("value")).agg(F.max_by("frequent", F.struct("n_entities", "frequent")).alias("to"))
    new = claims.join(rewrites, ["attr", "value"], "left").withColumn("value", F.coalesce("to", "value")).drop("to")
    return majority_vote(new), asked


def simulated_voters(cands: DataFrame, truth: DataFrame, k: int = 3, error: int = 100, seed: int = 0) -> DataFrame:
    """k people pick a candidate for each cell, right but for `error` per mille; (.., value, votes, n_questions)."""
    t = truth.select(*CELL, F.col("value").alias("truth"))
    rows = cands.join(t, list(CELL)).withColumn("voter", F.explode(F.sequence(F.lit(1), F.lit(k))))
    fails = mix("entity_id", "voter", F_ATTR, seed) % 1000 < error
    at = mix("entity_id", "voter", f"{F_ATTR} + 1", seed) % F.col("n_slots")
    picked = rows.where(F.when(fails, F.col("slot") == at).otherwise(F.col("value") == F.col("truth")))
    votes = picked.groupBy(*CELL, "value").agg(F.count(F.lit(1)).alias("votes"))
    w = Window.partitionBy(*CELL).orderBy(F.desc("votes"), F.asc("value"))
    return votes.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*CELL, "value", "votes", F.lit(k).alias("n_questions"))
