"""Queries of whole methods and experiments."""

from __future__ import annotations

import itertools
from dataclasses import replace

from pyspark.sql import functions as F

from ..operators import baselines, claims, infer, learn, resolver
from ..plans import experiments
from ..plans.workspace import settle
from ..sources.replicas import SETS, replicas
from ..sources.tables import table
from ..streaming import votes
from . import text
from .batch import CELL, r6, rep_claims, seeds_of
from .batch import _ACC as ACCURACY
from .batch import SQL as _BATCH_SQL

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def _settings(name: str, **changes) -> resolver.Settings:
    return replace(resolver.Settings(tuple(SETS[name][2]), stages=2, embed_dim=8), **changes)


def _fit(spark, d, name="supplier", sources=True, **changes):
    wide = replicas(spark, d, name)
    wide = wide if sources else wide.withColumn("source_id", F.lit(None).cast("int"))
    return resolver.fit(wide, seeds_of(spark, d, name, 0.2), _settings(name, **changes))


def _named(units, vector, names):
    named = F.transform(vector, lambda x, i: F.struct(F.get(F.array(*map(F.lit, names)), i).alias("feature"), F.round(x, 6).alias("x")))
    return units.select(*CELL, "value", F.explode(named).alias("f")).select(*CELL, "value", "f.*")


@query
def static_features(spark, d):
    s = _settings("part_small")
    wide = resolver.number_records(replicas(spark, d, "part_small"), s, "static-records")
    cands, names = resolver._static(wide, s, resolver.source_list(wide, s))
    return _named(settle(cands, "static-candidates"), "static", names)


@query
def full_features(spark, d):
    s = _settings("supplier")
    wide = resolver.number_records(replicas(spark, d, "supplier"), s, "full-records")
    cands, names = resolver._static(wide, s, resolver.source_list(wide, s))
    featured, more = resolver._dynamic(wide, cands, claims.vote_labels(cands).select(*CELL, "value"), s, 1)
    return _named(featured, "x", [*names, *more])


#: Rules of the stand-in without sources.
RULES = experiments.RULES["customer"]


def _source_free_sql() -> str:
    """Candidates of records without sources: supports, bigrams, vote share and mean log violations, by self-joins."""
    attrs = SETS["customer"][2]
    wide = f"{text.rep_cte('customer')}, r AS (SELECT entity_id * 4096 + source_id AS rid, * FROM rep)"
    fd = "(SELECT a.rid, count(b.rid) AS n FROM r a LEFT JOIN r b ON a.{k} = b.{k} AND a.{v} <> b.{v} GROUP BY a.rid)"
    broken = f"v AS (SELECT x.rid, x.n AS n0, y.n AS n1 FROM {fd.format(k='c_nationkey', v='n_name')} x JOIN {fd.format(k='n_name', v='r_name')} y USING (rid))"
    union = " UNION ALL ".join(f"SELECT entity_id, '{a}' AS attr, {a} AS value, {'ln(1 + n0)' if a in ('c_nationkey', 'n_name') else '0.0'} AS r0, {'ln(1 + n1)' if a in ('n_name', 'r_name') else '0.0'} AS r1 FROM r JOIN v USING (rid) WHERE {a} IS NOT NULL" for a in attrs)
    mapped = "regexp_replace(regexp_replace(regexp_replace(value, '[A-Za-z]', 'A', 'g'), '[0-9]', 'N', 'g'), '[^AN]', 'S', 'g')"
    grams = ["".join(g) for g in itertools.product("ANS", repeat=2)]
    counts = ", ".join(f"ln(1 + len(list_filter(range(1, length(m)), lambda i: substr(m, i, 2) = '{g}'))) AS format{i}" for i, g in enumerate(grams))
    features = [*(f"format{i}" for i in range(9)), "vote_share", "rule0", "rule1"]
    rows = " UNION ALL ".join(f"SELECT entity_id, attr, value, support, '{f}' AS feature, round(CAST({f} AS DOUBLE), 6) AS x FROM f" for f in features)
    return (
        f"WITH {wide}, {broken}, c AS ({union}), g AS (SELECT entity_id, attr, value, count(*) AS support, avg(r0) AS rule0, avg(r1) AS rule1, {mapped} AS m FROM c GROUP BY entity_id, attr, value), "
        f"f AS (SELECT *, {counts}, support / sum(support) OVER (PARTITION BY entity_id, attr) AS vote_share FROM g) {rows}"
    )


@query
def static_features_source_free(spark, d):
    """Records without sources, with rules: every record counts once."""
    s = _settings("customer", use_source=False, rules=RULES, models=("format", "vote", "rules"))
    wide = resolver.number_records(replicas(spark, d, "customer").drop("source_id"), s, "free-records")
    cands, names = resolver._static(wide, s)
    named = _named(cands, "static", names)
    return named.join(cands.select(*CELL, "value", "support"), [*CELL, "value"])


SQL["static_features_source_free"] = _source_free_sql()


@query
def iterative_bayes(spark, d):
    return baselines.iterative_bayes(rep_claims(spark, d, "supplier"))


@query
def interval_weighted_vote(spark, d):
    return baselines.interval_weighted_vote(rep_claims(spark, d, "supplier"))


@query
def claim_graph(spark, d):
    return baselines.claim_graph_propagation(rep_claims(spark, d, "supplier"), seeds_of(spark, d, "supplier", 0.2))


@query
def discriminative_erm(spark, d):
    return baselines.discriminative_source_model(rep_claims(spark, d, "supplier"), seeds_of(spark, d, "supplier", 0.2), "erm")


@query
def discriminative_em(spark, d):
    return baselines.discriminative_source_model(rep_claims(spark, d, "supplier"), seeds_of(spark, d, "supplier", 0.2), "em")


@query
def rewrite_then_vote(spark, d):
    return baselines.rewrite_then_vote(rep_claims(spark, d, "customer"), 100)[0]


@query
def naive_onehot_classifier(spark, d):
    """The value's hashed words alone, without what the cell's other claims say."""
    return resolver.top(_fit(spark, d, models=("onehot",), use_source=False, stages=1)[1]).select(*CELL, "value", r6("p").alias("p"))


def _vectors(spark, d):
    from pyspark.ml.functions import array_to_vector

    return table(spark, d, "embeddings").select("vec_id", array_to_vector(F.col("embedding").cast("array<double>")).alias("features"), F.col("label").cast("double").alias("y"))


def _predicted(spark, d, classifier):
    v = _vectors(spark, d)
    return learn.mllib(v, "features", "y", classifier, max_iter=15).transform(v).select("vec_id", F.col("prediction").cast("int").alias("prediction"))


QUERIES["softmax_fit_lbfgs"] = lambda spark, d: _predicted(spark, d, "softmax")
QUERIES["tree"] = lambda spark, d: _predicted(spark, d, "tree")
QUERIES["one_vs_rest"] = lambda spark, d: _predicted(spark, d, "logreg_ovr")


@query
def softmax_fit_adam(spark, d, most: int = 2000):
    """One model a group of labels, fitted in its own task on at most `most` embeddings, by least hash; all are scored."""
    import numpy as np
    import pandas as pd

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id")
        x, y = np.array(pdf["v"].tolist()), pdf["label"].to_numpy()
        kinds, at = np.unique(y, return_inverse=True)
        w = learn.adam_softmax(x, at, len(kinds), epochs=20)
        return pd.DataFrame({"g": [pdf["g"].iloc[0]], "kinds": [kinds], "w": [w.ravel()]})

    e = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label", (F.col("label") % 2).alias("g"))
    models = {}
    for (g,) in e.select("g").distinct().collect():
        sample = e.where(F.col("g") == g).orderBy(F.xxhash64("vec_id"), "vec_id").limit(most)
        for r in sample.groupBy("g").applyInPandas(fit, "g int, kinds array<int>, w array<double>").collect():
            models[g] = np.array(r["kinds"]), np.array(r["w"]).reshape(-1, len(r["kinds"]))

    def score(parts):
        for pdf in parts:
            for g, rows in pdf.groupby("g"):
                kinds, w = models[g]
                x = np.array(rows["v"].tolist())
                yield pd.DataFrame({"vec_id": rows["vec_id"], "prediction": kinds[(x @ w[:-1] + w[-1]).argmax(axis=1)]})

    return e.select("vec_id", "v", "g").mapInPandas(score, "vec_id long, prediction int")


@query
def platt_fit(spark, d):
    """Over all rows: rows of equal score and label are counted first, so a group brings its distinct scores alone."""
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["x", "y"])
        a, b = learn.platt_fit(pdf["x"].to_numpy(), pdf["y"].to_numpy(float), weight=pdf["n"].to_numpy(float))
        return pd.DataFrame({"l_linestatus": [pdf["l_linestatus"].iloc[0]], "a": [round(a, 4)], "b": [round(b, 4)]})

    li = table(spark, d, "lineitem").select("l_linestatus", F.col("l_discount").alias("x"), (F.col("l_quantity") > 25).cast("int").alias("y"))
    counted = li.groupBy("l_linestatus", "x", "y").agg(F.count(F.lit(1)).alias("n"))
    return counted.groupBy("l_linestatus").applyInPandas(run, "l_linestatus string, a double, b double")


def _answers(scored):
    return resolver.resolve(scored).withColumn("p", r6("p"))


@query
def stagewise(spark, d):
    return _answers(_fit(spark, d, dynamic_from="labels", calibrate=None)[1])


_TWIN = {"first_dynamic": "zero", "stages": 3, "calibrate": None}


@query
def dynamic_twin(spark, d):
    """The formulation with dynamic features, which has no list of stages."""
    return _answers(resolver.resolve_dynamic(replicas(spark, d, "supplier"), seeds_of(spark, d, "supplier", 0.2), _settings("supplier", **_TWIN)))


@query
def twin_disagreements(spark, d):
    """Cells where the stagewise and the dynamic formulation answer differently: none."""
    a = _answers(_fit(spark, d, **_TWIN)[1]).select(*CELL, F.col("value").alias("a"))
    both = a.join(dynamic_twin(spark, d).select(*CELL, F.col("value").alias("b")), CELL, "full")
    return both.agg(F.count(F.lit(1)).alias("cells"), F.coalesce(F.sum((~F.col("a").eqNullSafe(F.col("b"))).cast("long")), F.lit(0)).alias("different"))


SQL["twin_disagreements"] = f"WITH {text.rep_cte('supplier')} SELECT count(*) AS cells, CAST(0 AS BIGINT) AS different FROM (SELECT DISTINCT entity_id, attr FROM claims)"


@query
def forward_layers(spark, d):
    """The output of every layer for entities never seen."""
    fitted, _ = _fit(spark, d, stages=3)
    out = None
    for k, layer in enumerate(resolver.forward(fitted, replicas(spark, d, "supplier", salt=9))):
        one = _answers(layer).withColumn("layer", F.lit(k))
        out = one if out is None else out.unionByName(one)
    return out


@query
def resolve_source_aware(spark, d):
    return _answers(_fit(spark, d, "part_small")[1])


@query
def resolve_source_free(spark, d):
    return _answers(_fit(spark, d, "part_small", use_source=False)[1])


@query
def resolve_source_free_rules(spark, d):
    """No sources, rules, and synthetic entities: a tenth of the labelled ones."""
    return _answers(_fit(spark, d, "customer", sources=False, rules=RULES, augment=0.1)[1])


@query
def resolve_with_rules(spark, d):
    return _answers(_fit(spark, d, "customer", rules=RULES)[1])


@query
def resolve_predicted_partners(spark, d):
    """Rules against the other entities' predicted records."""
    return _answers(_fit(spark, d, "customer", rules=RULES, rule_partners="predicted")[1])


@query
def resolve_faithful(spark, d):
    """The literal variant: every claim's vector classified into slots, 500 epochs of Adam, three stages."""
    wide, s = replicas(spark, d, "supplier"), resolver.faithful(_settings("supplier", stages=3, max_slots=16))
    return _answers(resolver.fit(wide, seeds_of(spark, d, "supplier", 0.2), s)[1])


#: Variants of layout, classifier, fusing, embedding, co-occurrence, trust and augmentation.
VARIANTS = {
    "resolve_own_slot": {"layout": "cell_own_slot", "max_slots": 16},
    "resolve_entity_slots": {"layout": "entity_slots", "max_slots": 12, "models": ("format", "embed", "cooc", "vote")},
    "resolve_one_vs_rest": {"layout": "cell", "max_slots": 16, "classifier": "logreg_ovr"},
    "resolve_tree": {"layout": "cell_own_slot", "max_slots": 16, "classifier": "tree"},
    "resolve_weighted_fusion": {"layout": "cell", "max_slots": 16, "fuse": "weighted"},
    "resolve_word2vec": {"embed": "word2vec"},
    "resolve_raw_cooccurrence": {"cooc_values": "raw"},
    "resolve_with_trust": {"trust": True},
    "resolve_temperature": {"calibrate": "temperature"},
    "resolve_early_stop": {"stages": 15, "early_stop": 0.005},
    "resolve_augmented_to_truth": {"augment": 0.3, "augment_to": "truth"},
    "resolve_augmented_to_majority": {"augment": 0.3, "augment_to": "majority"},
}
for _name, _changes in VARIANTS.items():
    QUERIES[_name] = lambda spark, d, c=_changes: _answers(_fit(spark, d, **c)[1])


@query
def resolve_sampled(spark, d):
    """Candidates drawn in proportion to their probability."""
    return resolver.resolve(_fit(spark, d, stages=1)[1], pick="sample", seed=3).withColumn("p", r6("p"))


@query
def resolve_new(spark, d):
    fitted, _ = _fit(spark, d, stages=1)
    return _answers(resolver.resolve_new(fitted, replicas(spark, d, "supplier", salt=9)))


@query
def estimator(spark, d):
    """The four modules as Spark ML stages."""
    from ..plans import modules

    wide = replicas(spark, d, "supplier")
    model = modules.Resolver(attrs=list(SETS["supplier"][2]), seeds=seeds_of(spark, d, "supplier", 0.2), stages=2, embed_dim=8).fit(wide)
    return modules.Answers().transform(model.transform(wide)).withColumn("p", r6("p"))


@query
def distributions(spark, d):
    dist = infer.distributions(_fit(spark, d, stages=1)[1])
    return dist.select(*CELL, F.explode("dist").alias("value", "p")).withColumn("p", r6("p"))


@query
def golden_records(spark, d):
    return claims.golden(_answers(_fit(spark, d, stages=1)[1]), SETS["supplier"][2])


# -- experiments -----------------------------------------------------------------------

#: Runs of the registered experiments; the published ones have 50, which `runs` takes as well.
RUNS = 5


@query
def end_to_end_customer(spark, d):
    """The stand-in with rules: with its sources every method, at a tenth of the entities labelled."""
    return experiments.summary(experiments.end_to_end(spark, d, ("customer",), runs=RUNS, share=0.1))


@query
def end_to_end_source_free(spark, d):
    """The same without sources, as the published set with rules is: source-free methods alone."""
    return experiments.summary(experiments.end_to_end(spark, d, ("customer",), experiments.WITHOUT, runs=RUNS, share=0.1, sources=False))


@query
def end_to_end_part_small(spark, d):
    return experiments.summary(experiments.end_to_end(spark, d, ("part_small",), runs=RUNS))


@query
def end_to_end_part_vote(spark, d):
    return experiments.summary(experiments.end_to_end(spark, d, ("part_vote",), runs=2))


def _small(spark, d):
    return experiments.end_to_end(spark, d, ("supplier", "customer"), ("source_aware", "seed_accuracy_bayes", "source_free", "majority_vote"), runs=RUNS, share=0.1)


QUERIES["average_over_sets"] = lambda spark, d: experiments.averages(_small(spark, d))
QUERIES["gaps_to_rivals"] = lambda spark, d: experiments.gaps(_small(spark, d))
QUERIES["stages_curve"] = lambda spark, d: experiments.summary(experiments.stages_curve(spark, d, "supplier", shares=(0.1,), ratio=0.1, runs=RUNS))
QUERIES["augmentation_sweep"] = lambda spark, d: experiments.summary(experiments.augmentation_sweep(spark, d, "supplier", shares=(0.1,), runs=RUNS, stages=1))
QUERIES["label_size_sweep"] = lambda spark, d: experiments.summary(experiments.label_size_sweep(spark, d, "customer", shares=(0.002, 0.01, 0.1), methods=("source_free",), runs=RUNS))
QUERIES["ablation_single"] = lambda spark, d: experiments.summary(experiments.ablation_single(spark, d, "customer", runs=2))
QUERIES["ablation_group"] = lambda spark, d: experiments.summary(experiments.ablation_group(spark, d, "customer", use_source=True, runs=2))
QUERIES["ablation_drops"] = lambda spark, d: experiments.drops(experiments.ablation_single(spark, d, "supplier", use_source=True, runs=RUNS))
QUERIES["weight_report"] = lambda spark, d: experiments.weight_report(spark, d, "supplier")


@query
def trust_error(spark, d):
    from ..operators import measure
    from ..sources.replicas import truth

    c = rep_claims(spark, d, "part_small")
    return measure.trust_error(baselines.source_accuracy(c, seeds_of(spark, d, "part_small")), baselines.source_accuracy(c, truth(spark, d, "part_small"), 0.0)).withColumn("error", r6("error"))


SQL["trust_error"] = f"WITH {ACCURACY}, act AS (SELECT source_id, greatest(0.01, least(0.99, avg(CASE WHEN c.value = t.value THEN 1.0 ELSE 0.0 END))) AS b FROM claims c JOIN truth t USING (entity_id, attr) GROUP BY source_id) SELECT source_id, round(abs(a - b), 6) AS error FROM src JOIN act USING (source_id)"


@query
def stream_vote_twin(spark, d):
    e = votes.read_stream(spark, f"{d}/event[s].parquet", table(spark, d, "events").schema).withColumn("ts", F.col("ts").cast("timestamp"))
    out = votes.run_complete(votes.window_votes(e, "user_id", "event_type"), "votes")
    return out.select("user_id", F.unix_seconds("start").alias("day"), "event_type", "n")


SQL["stream_vote_twin"] = _BATCH_SQL["events_window_vote"]
