"""Experiments: methods compared, ablations, and sweeps over stages, labels and augmentation.

The runs of an experiment (one split of the entities each) lie in one table, the
entity ids of the r-th starting at r * claims.RUN, and are fitted together:
every run has its own models and its own source weights, and fifty runs cost the
jobs of one.
"""

from __future__ import annotations

from dataclasses import replace
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.noise import mix
from ..operators import baselines, measure, resolver
from ..operators.claims import RUN, run_of
from ..operators.features import BLOCKS, GROUPS
from ..operators.packed import Packed, Split
from ..operators.packed_rivals import Rivals
from ..sources.replicas import SETS, clean, replicas, truth
from .workspace import settle

CELL = ["entity_id", "attr"]
#: Rules of the stand-ins that have some.
RULES = {"customer": ("not(t1.c_nationkey = t2.c_nationkey and t1.n_name != t2.n_name)", "not(t1.n_name = t2.n_name and t1.r_name != t2.r_name)")}
#: The grids of the published experiments.
STAGES, RATIOS, SHARES = (1, 2, 5, 10, 15), (0.0, 0.05, 0.1, 0.3, 0.5, 0.7, 1.0), (0.05, 0.1)


class Workload:
    """Claims, seeds and test truth of a replica set, once a run; sources=False takes the sources away."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, share: float = 0.05, runs: int = 1, limit: int | None = None, salt: int | None = None, sources: bool = True, like: Workload | None = None):
        self.spark, self.name, self.share, self.runs = spark, name, share, runs
        self.attrs, self.rules = tuple(SETS[name][2]), RULES.get(name, ())
        self._sf_dir, self._limit = sf_dir, limit
        if like is None:
            wide = replicas(spark, sf_dir, name, salt, limit)
            wide = wide if sources else wide.withColumn("source_id", F.lit(None).cast("int"))
            self._one = settle(wide, f"workload-{name}")
        else:  # other shares of the same records
            self._one, self.packed = like._one, like.packed

    def _often(self, df: DataFrame) -> DataFrame:
        return df.withColumn("_run", F.explode(F.sequence(F.lit(0), F.lit(self.runs - 1)))).withColumn("entity_id", F.col("_run").cast("long") * F.lit(RUN) + F.col("entity_id")).drop("_run")

    @cached_property
    def wide(self) -> DataFrame:
        """Records and what is static of them are those of one run, read once a run."""
        return self._often(self._one)

    @cached_property
    def _truth(self) -> tuple[DataFrame, DataFrame]:
        """Cells of known truth, and which entities are seeds."""
        whole = settle(self._often(truth(self.spark, self._sf_dir, self.name, self._limit)), f"truth-{self.name}")
        # The share's entities of least noise in each run, one at least.
        entities = whole.select("entity_id").distinct().withColumn("run", run_of("entity_id"))
        least, of = Window.partitionBy("run").orderBy(mix("entity_id", 0, 55, 1), "entity_id"), Window.partitionBy("run")
        ranked = entities.withColumn("_r", F.row_number().over(least)).withColumn("_n", F.count(F.lit(1)).over(of))
        return whole, settle(ranked.select("entity_id", (F.col("_r") <= F.greatest(F.lit(1), F.round(F.col("_n") * self.share))).alias("seed")), f"split-{self.name}")

    @cached_property
    def seeds(self) -> DataFrame:
        whole, chosen = self._truth
        return settle(whole.join(chosen.where("seed").select("entity_id"), "entity_id").select(*CELL, "value"), f"seeds-{self.name}")

    @cached_property
    def test(self) -> DataFrame:
        whole, chosen = self._truth
        return settle(whole.join(chosen.where("not seed").select("entity_id"), "entity_id").select(*CELL, "value"), f"test-{self.name}")

    @property
    def claims(self) -> DataFrame:
        """Claims as the rivals take them: attributes and sources of one run are strangers to those of another."""
        run = run_of("entity_id")
        long = self.wide.unpivot(["entity_id", "source_id"], list(self.attrs), "attr", "value").where("value is not null")
        return long if self.runs == 1 else long.withColumn("attr", F.concat_ws("#", "attr", run)).withColumn("source_id", F.col("source_id").cast("long") * self.runs + run)

    def _apart(self, df: DataFrame) -> DataFrame:
        return df if self.runs == 1 else df.withColumn("attr", F.concat_ws("#", "attr", run_of("entity_id")))

    def precision(self, answers: DataFrame) -> list[tuple[int, float]]:
        """(run, precision); answers of rivals or of the resolver."""
        plain = answers.withColumn("attr", F.element_at(F.split("attr", "#"), 1))
        judged = measure.judged(plain, self.test).withColumn("run", run_of("entity_id"))
        return sorted((r["run"], r["p"]) for r in judged.groupBy("run").agg(F.avg("right").alias("p")).collect())

    def settings(self, **changes) -> resolver.Settings:
        base = resolver.Settings(self.attrs, stages=3, runs=self.runs, max_slots=12, embed_dim=8, rules=self.rules)
        return replace(base, **changes)

    @cached_property
    def prepared(self) -> resolver.Prepared:
        """Static features of all blocks, for every fit over the workload."""
        return resolver.prepare(self._one, self.settings()).repeated(self.runs)

    @cached_property
    def packed(self) -> Packed:
        """The same in batches, once for all runs."""
        return Packed(self._one, self.settings(), clean(self.spark, self._sf_dir, self.name, self._limit))

    @cached_property
    def split(self) -> Split:
        return self.packed.split(self.share, self.runs, self.settings())

    def fit(self, **changes) -> tuple[resolver.Fitted, list[tuple[int, float]]]:
        """A fit with all its stages' tables, as augmented records need it."""
        s = self.settings(**changes)
        fitted, scored = resolver.fit(self.wide, self.seeds, s, None if s.augment else self.prepared)
        return fitted, self.precision(resolver.resolve(scored))

    def resolve(self, *fits: dict) -> list[list[tuple[int, float]]]:
        """(run, precision) of each of several fits to the same records: all are fitted and answered together."""
        return self.packed.resolve([self.settings(**changes) for changes in fits], self.split, self.runs)


#: Methods that need sources, and those that don't.
WITH_SOURCES = ("source_aware", "seed_accuracy_bayes", "iterative_bayes", "interval_weighted_vote", "claim_graph_propagation", "discriminative_source_model")
WITHOUT = ("source_free", "majority_vote", "rewrite_then_vote")
METHODS = WITH_SOURCES + WITHOUT


def answer(w: Workload, method: str, **changes) -> list[tuple[int, float]]:
    """(run, precision) of a method with its own defaults, as `baselines` and `resolver` have it."""
    if method in ("source_aware", "source_free"):
        return w.fit(use_source=method == "source_aware", **changes)[1]
    c, seeds = w.claims, w._apart(w.seeds)
    run = {
        "majority_vote": lambda: baselines.majority_vote(c),
        "seed_accuracy_bayes": lambda: baselines.seed_accuracy_bayes(c, seeds),
        "iterative_bayes": lambda: baselines.iterative_bayes(c),
        "interval_weighted_vote": lambda: baselines.interval_weighted_vote(c),
        "claim_graph_propagation": lambda: baselines.claim_graph_propagation(c, seeds),
        "discriminative_source_model": lambda: baselines.discriminative_source_model(c, seeds),
        "rewrite_then_vote": lambda: baselines.rewrite_then_vote(c, 100 * w.runs, seeds)[0],
    }
    if method not in run:
        raise ValueError(f"no such method: {method}")
    return w.precision(run[method]())


def answers(w: Workload, methods: tuple[str, ...]) -> list[tuple[str, int, float]]:
    """(method, run, precision) of several methods over packed records; the resolver's fits are made together."""
    fits = [m for m in methods if m in ("source_aware", "source_free")]
    found = dict(zip(fits, w.resolve(*[{"use_source": m == "source_aware"} for m in fits]), strict=True)) if fits else {}
    rivals = tuple(m for m in methods if m not in fits)
    if rivals:
        found |= Rivals(w.packed, w.split, w.runs).precisions(rivals, truth(w.spark, w._sf_dir, w.name, w._limit))
    return [(m, r, p) for m in methods for r, p in found[m]]


COLUMNS = "experiment string, workload string, method string, run int, train_share double, ratio double, stages int, precision double"


def _frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(*r[:3], int(r[3]), *r[4:]) for r in rows], COLUMNS)


def summary(runs: DataFrame) -> DataFrame:
    """Median, mean, variance and standard error over the runs of each point."""
    return measure.run_statistics(runs, by=("experiment", "workload", "method", "train_share", "ratio", "stages"))


def end_to_end(spark: SparkSession, sf_dir: str, names: tuple[str, ...], methods: tuple[str, ...] = METHODS, runs: int = 5, share: float = 0.05, **kw) -> DataFrame:
    """One row a workload, method and run."""
    rows = []
    for name in names:
        w = Workload(spark, sf_dir, name, share, runs, **kw)
        rows += [("end_to_end", name, m, r, share, 0.0, 3, p) for m, r, p in answers(w, methods)]
    return _frame(spark, rows)


def stages_curve(spark: SparkSession, sf_dir: str, name: str, stages: tuple[int, ...] = STAGES, shares: tuple[float, ...] = SHARES, ratio: float = 0.0, runs: int = 5, **kw) -> DataFrame:
    """Precision after the stages asked for, of one fit of the longest."""
    rows = []
    for share in shares:
        w = Workload(spark, sf_dir, name, share, runs, **kw)
        fitted, _ = w.fit(stages=max(stages), use_source=False, augment=ratio)
        rows += [("stages", name, "source_free", r, share, ratio, k, p) for k in stages for r, p in w.precision(resolver.resolve(fitted.history[k - 1]))]
    return _frame(spark, rows)


def augmentation_sweep(spark: SparkSession, sf_dir: str, name: str, ratios: tuple[float, ...] = RATIOS, shares: tuple[float, ...] = SHARES, runs: int = 5, stages: int = 3, **kw) -> DataFrame:
    """Precision against the ratio of synthetic to labelled entities."""
    rows = []
    for share in shares:
        w = Workload(spark, sf_dir, name, share, runs, **kw)
        rows += [("augmentation", name, "source_free", r, share, ratio, stages, p) for ratio in ratios for r, p in w.fit(augment=ratio, use_source=False, stages=stages)[1]]
    return _frame(spark, rows)


def label_size_sweep(spark: SparkSession, sf_dir: str, name: str, shares: tuple[float, ...] = (0.002, 0.01, 0.05, 0.1), methods: tuple[str, ...] = ("source_aware", "source_free"), runs: int = 5, **kw) -> DataFrame:
    """Precision against the share of labelled entities."""
    rows, w = [], None
    for share in shares:
        w = Workload(spark, sf_dir, name, share, runs, like=w, **kw)
        rows += [("labels", name, m, r, share, 0.0, 3, p) for m, r, p in answers(w, methods)]
    return _frame(spark, rows)


def ablation(spark: SparkSession, sf_dir: str, name: str, drops: dict[str, tuple[str, ...]], share: float = 0.1, use_source: bool = False, runs: int = 5, **kw) -> DataFrame:
    """Precision of all blocks, and without each named set of blocks."""
    w = Workload(spark, sf_dir, name, share, runs, **kw)
    found = w.resolve({"use_source": use_source}, *[{"use_source": use_source, "models": tuple(b for b in BLOCKS if b not in v)} for v in drops.values()])
    rows = [("ablation", name, m, r, share, 0.0, 3, p) for m, of in zip(("all", *[f"without_{k}" for k in drops]), found, strict=True) for r, p in of]
    return _frame(spark, rows)


def ablation_single(spark: SparkSession, sf_dir: str, name: str, blocks: tuple[str, ...] | None = None, use_source: bool = False, **kw) -> DataFrame:
    """Every block that the workload has: sources and rules only where there are some."""
    have = [b for b in BLOCKS if (b != "source" or use_source) and (b != "rules" or name in RULES)]
    return ablation(spark, sf_dir, name, {b: (b,) for b in blocks or have}, use_source=use_source, **kw)


def ablation_group(spark: SparkSession, sf_dir: str, name: str, **kw) -> DataFrame:
    return ablation(spark, sf_dir, name, dict(GROUPS), **kw)


def drops(ablated: DataFrame) -> DataFrame:
    """(workload, method, full, ablated, drop): mean precision of all blocks less that without some."""
    mean = ablated.groupBy("workload", "method").agg(F.avg("precision").alias("ablated"))
    full = mean.where("method = 'all'").select("workload", F.col("ablated").alias("full"))
    return mean.where("method <> 'all'").join(full, "workload").withColumn("drop", F.col("full") - F.col("ablated"))


def averages(runs: DataFrame) -> DataFrame:
    """(method, workloads, median, mean): medians and means of the workloads, averaged over them."""
    per = runs.groupBy("workload", "method").agg(F.median("precision").alias("median"), F.avg("precision").alias("mean"))
    return per.groupBy("method").agg(F.count(F.lit(1)).alias("workloads"), F.avg("median").alias("median"), F.avg("mean").alias("mean"))


def gaps(runs: DataFrame) -> DataFrame:
    """(workload, setting, ours, best_rival, points): with sources and without, beside the best rival of that setting."""
    per = runs.groupBy("workload", "method").agg(F.median("precision").alias("precision"))
    out = None
    for ours, rivals in (("source_aware", WITH_SOURCES[1:]), ("source_free", WITHOUT[1:])):
        one = measure.improvement(per.where(F.col("method").isin(ours, *rivals)), ours).withColumn("setting", F.lit(ours))
        out = one if out is None else out.unionByName(one)
    return out.select("workload", "setting", "ours", "best_rival", "points")


def weight_report(spark: SparkSession, sf_dir: str, name: str, **kw) -> DataFrame:
    fitted, _ = Workload(spark, sf_dir, name, 0.1, **kw).fit(stages=2)
    return spark.createDataFrame(resolver.weight_report(fitted), "stage int, attr string, block string, norm double").withColumn("norm", F.round("norm", 6))
