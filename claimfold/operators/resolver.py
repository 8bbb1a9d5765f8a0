"""Stagewise resolution of entities.

In the layout 'candidate' the unit is a candidate: its vector is the mean of its
claims' features, with the sources that back it, and candidates of a cell compete
in a softmax of shared weights.  In the literal layout 'cell' every claim has its own
vector, which is classified into the slots of its entity; the outputs of a cell's
claims are fused, cut to its real slots and renormalised.  Variants: 'cell_own_slot'
adds the slot that the claim itself holds, 'entity_slots' has one vector a cell,
its first slots' vectors side by side.

Stage after stage, features that depend on predictions (co-occurrence with the
predicted values of other attributes, the running value, rules against predicted
partners) are made anew and a new model is fitted; all attributes finish a stage
before any begins the next.  `resolve_dynamic` is the other formulation of the
same: one table whose dynamic part starts at zero and is overwritten in place.

Static features are made once, after one exchange on the entity, and written; a
stage reads them, joins labels on the entity, and writes its predictions.  Models are
fitted on all labelled and weakly labelled entities (`max_train` bounds them only where a
caller says so), and are a few numbers an attribute: a small table that scoring joins.
"""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.noise import mix
from ..plans.rules import parse_rule, rules_on, violations, violations_against
from ..plans.workspace import partitions, release, settle
from . import augment as augmentation
from .baselines import source_accuracy
from .claims import CELL, RUN, run_of, seed_split
from .features import BLOCKS, EXTRA, distance, format_ngrams, hash_embedding, hash_words, mean_vector, word2vec_vectors
from .infer import draw, update_labels
from .learn import adam_softmax, conditional_softmax, gradient_softmax, one_vs_rest, platt_fit, sigmoid_rows, softmax_rows, tree_fit, tree_rows

LAYOUTS = ("candidate", "cell", "cell_own_slot", "entity_slots")


@dataclass(frozen=True)
class Settings:
    attrs: tuple[str, ...]
    use_source: bool = True
    rules: tuple[str, ...] = ()
    #: Partners of a rule: the records as they are, or the other entities' predicted records.
    rule_partners: str = "raw"
    models: tuple[str, ...] = BLOCKS
    layout: str = "candidate"
    stages: int = 3
    #: Stop before `stages` once fewer than this share of answers changed.
    early_stop: float | None = None
    train_on: str = "all"
    weak_weight: float = 0.1
    dynamic_from: str = "model"
    #: Labels that the first stage's dynamic features see: the vote, or none (all zero).
    first_dynamic: str = "vote"
    #: Adds the sources' log-odds on known cells, fitted without the fold that a cell is in.
    trust: bool = False
    folds: int = 3
    l2_grid: tuple[float, ...] = (0.003, 0.01, 0.03, 0.1)
    #: Times the ridge of other features that source weights have: chosen on validation cells, like l2.
    source_ridges: tuple[float, ...] = (1.0, 10.0, 100.0)
    #: Of the slot layouts: softmax by gradient or Adam, one logistic model a slot, a decision tree.
    classifier: str = "softmax"
    epochs: int = 500
    batch: int = 10
    calibrate: str | None = "platt"
    fuse: str = "mean"
    pick: str = "argmax"
    augment: float = 0.0
    augment_to: str = "any"
    embed: str = "hash"
    embed_dim: int = 16
    onehot_dim: int = 256
    dist: str = "l2"
    cooc_values: str = "predicted"
    slot_order: str = "support"
    nulls: str = "drop"
    #: Slots that the slot layouts know; candidates beyond have probability 0 there.  The layout 'candidate' has no such bound.
    max_slots: int = 64
    #: Known entities, and others, of each run that models learn from, chosen by noise; all if None.
    max_train: int | None = None
    #: Sources with weights of their own, those of most claims; the others share one.
    max_sources: int = 2048
    seed: int = 0
    #: Independent repetitions in one table, entity ids of the r-th starting at r * claims.RUN; each has its own models.
    runs: int = 1

    def __post_init__(self):
        choices = {
            "layout": LAYOUTS, "train_on": ("all", "seed"), "rule_partners": ("raw", "predicted"), "dynamic_from": ("model", "labels"), "first_dynamic": ("vote", "zero"),
            "classifier": ("softmax", "softmax_adam", "logreg_ovr", "tree"), "calibrate": ("platt", "temperature", None), "fuse": ("mean", "logmean", "max", "weighted"), "pick": ("argmax", "sample"),
            "augment_to": ("any", "truth", "majority"), "embed": ("hash", "word2vec"), "dist": ("l2", "l1", "cosine"), "cooc_values": ("predicted", "raw"), "slot_order": ("support", "value"), "nulls": ("drop", "as_value"),
        }
        for name, allowed in choices.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")
        if set(self.models) - set(BLOCKS + EXTRA):
            raise ValueError(f"models must be among {BLOCKS + EXTRA}")
        if self.stages < 1 or self.runs < 1:
            raise ValueError("one stage and one run are needed at least")
        if self.layout == "candidate" and self.classifier != "softmax":
            raise ValueError("the layout 'candidate' has a softmax only")


def faithful(s: Settings) -> Settings:
    """The literal variant: every claim's vector, weak labels of full weight, Adam, known labels in features."""
    return replace(s, layout="cell", weak_weight=1.0, classifier="softmax_adam", dynamic_from="labels")


@dataclass
class StageModel:
    """Weights of one stage: by attribute (and run), for named features and for sources."""

    stage: int
    l2: float
    weights: dict[str, list] = field(default_factory=dict)
    means: dict[str, list[float]] = field(default_factory=dict)
    scales: dict[str, list[float]] = field(default_factory=dict)
    platt: dict[str, tuple[float, float]] = field(default_factory=dict)


@dataclass
class Fitted:
    settings: Settings
    sources: list[int]
    names: list[str]
    stages: list[StageModel]
    trust: dict[str, list[float]] = field(default_factory=dict)
    history: list[DataFrame] = field(default_factory=list)

    def save(self, spark: SparkSession, path: str) -> None:
        """Models as one small Parquet row a stage, so that they can be read back anywhere."""
        rows = [(json.dumps(asdict(self.settings)), json.dumps([self.sources, self.trust]), json.dumps(self.names), m.stage, json.dumps(asdict(m))) for m in self.stages]
        spark.createDataFrame(rows, "settings string, sources string, names string, stage int, model string").coalesce(1).write.parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> Fitted:
        rows = sorted(spark.read.parquet(path).collect(), key=lambda r: r["stage"])
        s = {k: tuple(v) if isinstance(v, list) else v for k, v in json.loads(rows[0]["settings"]).items()}
        stages = [StageModel(**json.loads(r["model"])) for r in rows]
        for m in stages:
            m.platt = {a: tuple(ab) for a, ab in m.platt.items()}
        sources, trust = json.loads(rows[0]["sources"])
        return Fitted(Settings(**s), sources, json.loads(rows[0]["names"]), stages, trust)


def model_key(s: Settings) -> Column:
    """Which model a cell has: its attribute's, in its run."""
    return F.col("attr") if s.runs == 1 else F.concat_ws("#", F.col("attr"), run_of("entity_id"))


# -- features --------------------------------------------------------------------


def number_records(wide: DataFrame, s: Settings, name: str) -> DataFrame:
    """(entity_id, record_id, source_id, attributes): each record has a number of its own, fixed as the table is written.

    Records may lack sources, repeat an entity and a source, or repeat altogether.
    """
    missing = {"entity_id", *s.attrs} - set(wide.columns)
    if missing:
        raise ValueError(f"no such column: {sorted(missing)}")
    source = F.col("source_id") if "source_id" in wide.columns else F.lit(None).cast("int")
    values = [F.coalesce(a, F.lit("<null>")).alias(a) if s.nulls == "as_value" else F.col(a) for a in s.attrs]
    return settle(wide.select("entity_id", F.monotonically_increasing_id().alias("record_id"), source.alias("source_id"), *values), name)


def source_list(wide: DataFrame, s: Settings) -> list[int]:
    """Sources that have weights of their own: those of most records, then by number."""
    if not (s.use_source and "source" in s.models):
        return []
    counted = wide.where("source_id is not null").groupBy("source_id").count().orderBy(F.desc("count"), "source_id").limit(s.max_sources)
    return sorted(r["source_id"] for r in counted.collect())


def indexed(wide: DataFrame, sources: list[int]) -> DataFrame:
    """Records with `at`, the place of their source in the list, or the place after it; null without a source or a list."""
    if not sources:
        return wide.withColumn("at", F.lit(None).cast("int"))
    table = wide.sparkSession.createDataFrame([(v, i) for i, v in enumerate(sources)], "source_id long, at int")
    rows = wide.join(F.broadcast(table), wide["source_id"].cast("long") == table["source_id"], "left").drop(table["source_id"])
    return rows.withColumn("at", F.when(F.col("source_id").isNotNull(), F.coalesce("at", F.lit(len(sources)))))


def _rule_counts(wide: DataFrame, s: Settings, golden: DataFrame | None = None) -> tuple[DataFrame, list[str], dict[str, list[str]]]:
    """Records with a column of violations for each rule; their names; and the rules of each attribute."""
    of: dict[str, list[str]] = {a: [] for a in s.attrs}
    if not s.rules or "rules" not in s.models:
        return wide, [], of
    parsed = [parse_rule(t, [*s.attrs, "entity_id", "source_id"], f"rule{i}") for i, t in enumerate(s.rules)]
    rows = wide
    for r in parsed:
        found = violations(wide, r, "record_id") if golden is None else violations_against(wide, golden, r, "record_id", "entity_id")
        rows = rows.join(found.select("record_id", F.col("n").alias(r.rule_id)), "record_id")
        for a in s.attrs:
            if r in rules_on(parsed, a):
                of[a].append(r.rule_id)
    return rows, [r.rule_id for r in parsed], of


def _long(rows: DataFrame, s: Settings, used: list[str], of: dict[str, list[str]], keep: tuple[str, ...]) -> DataFrame:
    """One row a claim, after the one exchange on the entity: columns of `keep`, attr, value, rules (logs of one more than the counts)."""
    cells = [F.struct(F.lit(a).alias("attr"), F.col(a).alias("value"), F.array(*[F.log1p(F.col(r).cast("double")) if r in of[a] else F.lit(0.0) for r in used]).cast("array<double>").alias("rules")) for a in s.attrs]
    return rows.repartition(partitions(rows), "entity_id").select(*keep, F.explode(F.array(*cells)).alias("c")).select(*keep, "c.*").where("value is not null")


def _static(wide: DataFrame, s: Settings, sources: list[int] = ()) -> tuple[DataFrame, list[str]]:
    """(entity_id, attr, value, support, slot, n_slots, static, sources): one row a candidate; sources as (at, claims)."""
    names: list[str] = []
    static_rules = s.rule_partners == "raw"
    rows, used, of = _rule_counts(wide, s) if static_rules else (wide, [], {a: [] for a in s.attrs})
    row_vector = hash_embedding(F.concat_ws(" ", *s.attrs), s.embed_dim) if "neighbour" in s.models else F.array().cast("array<double>")
    long = _long(indexed(rows.withColumn("_q", row_vector), sources), s, used, of, ("entity_id", "record_id", "at", "_q"))
    # Claims of one value and source first, so that what a candidate gathers is one entry a source.
    alike = long.groupBy(*CELL, "value", "at").agg(F.count(F.lit(1)).alias("n"), *[F.sum(F.col("rules")[i]).alias(f"_r{i}") for i in range(len(used))], *([F.sum(F.col("_q")[i]).alias(f"_q{i}") for i in range(s.embed_dim)] if "neighbour" in s.models else []))
    aggs = [F.sum("n").alias("support"), F.sort_array(F.collect_list(F.when(F.col("at").isNotNull(), F.struct("at", "n")))).alias("sources"), *[(F.sum(f"_r{i}") / F.sum("n")).alias(f"_r{i}") for i in range(len(used))]]
    if "neighbour" in s.models:
        aggs += [F.array(*[F.sum(f"_q{i}") / F.sum("n") for i in range(s.embed_dim)]).alias("_qm")]
    cand = alike.groupBy(*CELL, "value").agg(*aggs)
    cell = Window.partitionBy(*CELL)
    order = [F.desc("support"), F.asc("value")] if s.slot_order == "support" else [F.asc("value")]
    cand = cand.withColumn("slot", F.row_number().over(cell.orderBy(*order)) - 1).withColumn("n_slots", F.count(F.lit(1)).over(cell)).withColumn("_n", F.sum("support").over(cell))
    parts: list[Column] = []
    if "format" in s.models:
        grams = format_ngrams(F.col("value"))
        cand = cand.withColumn("_g", grams)
        parts += [F.log1p(F.col("_g")[i].cast("double")) for i in range(9)]
        names += [f"format{i}" for i in range(9)]
    if {"embed", "neighbour"} & set(s.models):
        cand = cand.withColumn("_m", hash_embedding(F.col("value"), s.embed_dim)) if s.embed == "hash" else word2vec_vectors(cand, s.embed_dim, s.seed, "_m")
    if "embed" in s.models:
        cand = cand.withColumn("_mm", mean_vector(F.col("_m"), s.embed_dim, cell))
        parts.append(distance(F.col("_m"), F.col("_mm"), s.dist))
        names.append("embed")
    if "vote" in s.models:
        parts.append(F.col("support") / F.col("_n"))
        names.append("vote_share")
    if "vote_top" in s.models:
        parts.append((F.col("slot") == 0).cast("double"))
        names.append("votetop")
    if used:
        parts += [F.col(f"_r{i}") for i in range(len(used))]
        names += used
    if "neighbour" in s.models:
        cand = cand.withColumn("_j", F.concat("_qm", "_m")).withColumn("_jm", mean_vector(F.col("_j"), 2 * s.embed_dim, cell))
        parts.append(distance(F.col("_j"), F.col("_jm"), s.dist))
        names.append("neighbour")
    if "onehot" in s.models:
        cand = cand.withColumn("_h", hash_words(F.col("value"), s.onehot_dim))
        parts += [F.col("_h")[i] for i in range(s.onehot_dim)]
        names += [f"onehot{i}" for i in range(s.onehot_dim)]
    static = F.array(*parts) if parts else F.array().cast("array<double>")
    return cand.select(*CELL, "value", "support", "slot", "n_slots", static.cast("array<double>").alias("static"), "sources", F.col("_m") if "_m" in cand.columns else F.lit(None).cast("array<double>").alias("_m")), names


def _claim_static(wide: DataFrame, cands: DataFrame, names: list[str], s: Settings, sources: list[int] = ()) -> DataFrame:
    """One row a claim of the slot layouts: its candidate's row, with rules and neighbourhood of its own record instead of means."""
    rows, used, of = _rule_counts(wide, s) if s.rule_partners == "raw" else (wide, [], {a: [] for a in s.attrs})
    near = "neighbour" in names
    row_vector = hash_embedding(F.concat_ws(" ", *s.attrs), s.embed_dim) if near else F.array().cast("array<double>")
    long = _long(indexed(rows.withColumn("_q", row_vector), sources), s, used, of, ("entity_id", "record_id", "at", "_q"))
    claims = long.join(cands, [*CELL, "value"])
    cell = Window.partitionBy(*CELL)
    own = {f"rule{i}": F.col("rules")[i] for i in range(len(used))}
    if near:
        claims = claims.withColumn("_j", F.concat("_q", "_m")).withColumn("_jm", mean_vector(F.col("_j"), 2 * s.embed_dim, cell))
        own["neighbour"] = distance(F.col("_j"), F.col("_jm"), s.dist)
    static = F.array(*[own.get(n, F.col("static")[i]) for i, n in enumerate(names)]) if names else F.col("static")
    source = F.when(F.col("at").isNotNull(), F.array(F.struct("at", F.lit(1).cast("long").alias("n")))).otherwise(F.array().cast("array<struct<at:int,n:bigint>>"))
    return claims.select(*CELL, "record_id", "value", F.lit(1).cast("long").alias("support"), "slot", "n_slots", static.cast("array<double>").alias("static"), source.alias("sources"))


def _cooccurrence(wide: DataFrame, labels: DataFrame, s: Settings) -> DataFrame:
    """(entity_id, attr, value, ratio): for each attribute, the share of its predicted value's records in which the candidate stands."""
    # Labels nested by entity: the only join of a stage is on the entity.
    nested = labels.groupBy("entity_id").agg(F.map_from_entries(F.collect_list(F.struct("attr", "value"))).alias("_said"))
    agree = F.array(*[F.coalesce((F.col(a) == F.col("_said")[a]), F.lit(False)).cast("double") for a in s.attrs])
    rows = wide.join(nested, "entity_id").withColumn("_agree", agree)
    long = rows.select("entity_id", "_agree", F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in s.attrs])).alias("c")).select("entity_id", "_agree", "c.*").where("value is not null")
    sums = F.array(*[F.sum(F.col("_agree")[i]) for i in range(len(s.attrs))])
    pairs, total = long.groupBy(*CELL, "value").agg(sums.alias("_pairs")), rows.groupBy("entity_id").agg(sums.alias("_total"))
    position = F.array_position(F.array(*[F.lit(a) for a in s.attrs]), F.col("attr"))
    ratio = F.transform(F.arrays_zip("_pairs", "_total"), lambda z, i: F.when((z["_total"] > 0) & (i + 1 != position), z["_pairs"] / z["_total"]).otherwise(0.0))
    return pairs.join(total, "entity_id").select(*CELL, "value", ratio.alias("_cooc"))


def _raw_cooccurrence(wide: DataFrame, s: Settings) -> DataFrame:
    """The same over the records' own values, not predicted ones: for a candidate the mean over its records."""
    out = None
    for a in s.attrs:
        ratios = []
        for b in s.attrs:
            pair, alone = Window.partitionBy("entity_id", a, b), Window.partitionBy("entity_id", b)
            known = F.col(a).isNotNull() & F.col(b).isNotNull()
            ratios.append(F.lit(0.0) if a == b else F.coalesce(F.sum(known.cast("double")).over(pair) / F.nullif(F.sum(known.cast("double")).over(alone), F.lit(0.0)), F.lit(0.0)) * known.cast("double"))
        one = wide.where(F.col(a).isNotNull()).select("entity_id", F.lit(a).alias("attr"), F.col(a).alias("value"), F.array(*ratios).alias("_c"))
        one = one.groupBy(*CELL, "value").agg(F.array(*[F.avg(F.col("_c")[i]) for i in range(len(s.attrs))]).alias("_cooc"))
        out = one if out is None else out.union(one)
    return out


def _dynamic(wide: DataFrame, units: DataFrame, labels: DataFrame | None, s: Settings, stage: int, trust: DataFrame | None = None) -> tuple[DataFrame, list[str]]:
    """Candidates (or claims) with `x`: static features, and those that depend on the labels (entity_id, attr, value).

    Without labels the dynamic part is zero.
    """
    names: list[str] = []
    parts = [F.col("static")]
    out = units
    zeros = F.array(*[F.lit(0.0) for _ in s.attrs])
    if trust is not None:
        out = out.join(trust, [*CELL, "value"], "left")
        parts.append(F.array(F.coalesce("_trust", F.lit(0.0))))
        names.append("trust")
    if "cooc" in s.models and len(s.attrs) > 1:
        if s.cooc_values == "raw":
            out = out.join(_raw_cooccurrence(wide, s), [*CELL, "value"], "left")
        elif labels is not None:
            out = out.join(_cooccurrence(wide, labels, s), [*CELL, "value"], "left")
        parts.append(F.coalesce("_cooc", zeros) if "_cooc" in out.columns else zeros)
        names += [f"cooc_{a}" for a in s.attrs]
    if s.rules and "rules" in s.models and s.rule_partners == "predicted":
        count = len(s.rules)
        nothing = F.array(*[F.lit(0.0)] * count)
        if labels is None:
            parts.append(nothing)
        else:
            golden = labels.groupBy("entity_id").pivot("attr", list(s.attrs)).agg(F.first("value"))
            rows, used, of = _rule_counts(wide, s, golden)
            long = _long(rows, s, used, of, ("entity_id", "record_id"))
            by = [*CELL, "value", *(["record_id"] if "record_id" in units.columns else [])]
            found = long.groupBy(*by).agg(F.array(*[F.avg(F.col("rules")[i]) for i in range(count)]).alias("_broken"))
            out = out.join(found, by, "left")
            parts.append(F.coalesce("_broken", nothing))
        names += [f"rule{i}" for i in range(count)]
    if "running" in s.models:
        last = stage > 0 and labels is not None
        slots = s.layout != "candidate"
        if last:
            said = labels.select(*CELL, F.col("value").alias("_last"))
            if slots:  # one flag for each slot
                at = units.select(*CELL, F.col("value").alias("_last"), "slot").distinct().withColumnRenamed("slot", "_at")
                said = said.join(at, [*CELL, "_last"])
            out = out.join(said, list(CELL), "left")
        if slots:
            parts.append(F.transform(F.sequence(F.lit(0), F.lit(s.max_slots - 1)), lambda i: F.coalesce(F.col("_at") == i, F.lit(False)).cast("double") if last else F.lit(0.0)))
            names += [f"running{i}" for i in range(s.max_slots)]
        else:
            parts.append(F.array(F.coalesce(F.col("value") == F.col("_last"), F.lit(False)).cast("double") if last else F.lit(0.0)))
            names.append("running")
    if s.layout == "cell_own_slot":
        parts.append(F.transform(F.sequence(F.lit(0), F.lit(s.max_slots - 1)), lambda i: (F.col("slot") == i).cast("double")))
        names += [f"own{i}" for i in range(s.max_slots)]
    keep = [c for c in ("record_id",) if c in units.columns]
    return out.select(*CELL, *keep, "value", "support", "slot", "n_slots", "sources", F.concat(*parts).alias("x")), names


def _trust_table(wide: DataFrame, seeds: DataFrame, s: Settings) -> tuple[dict[str, list], DataFrame]:
    """Log-odds of each source on known cells of all attributes together; and their sums by candidate.

    Seed entities fall into folds; a seed cell's sum leaves its own fold out, so
    no cell's truth is in its own feature.  Other cells take all seeds.
    """
    said = wide.unpivot(["entity_id", "source_id"], list(s.attrs), "attr", "value").where("value is not null and source_id is not null")
    fold = (mix("abs(entity_id)", 9, 97, s.seed) % s.folds).cast("int")
    known = seeds.withColumn("fold", fold)
    rates = None
    for k in range(-1, s.folds):
        one = source_accuracy(said, known.where(F.col("fold") != k)).select("source_id", F.lit(k).alias("fold"), F.log(F.col("accuracy") / (1 - F.col("accuracy"))).alias("odds"))
        rates = one if rates is None else rates.union(one)
    rates = settle(rates, "resolver-trust")
    folds = seeds.select("entity_id").distinct().withColumn("fold", fold)
    rows = said.join(folds, "entity_id", "left").withColumn("fold", F.coalesce("fold", F.lit(-1)))
    sums = rows.join(rates, ["source_id", "fold"], "left").groupBy(*CELL, "value").agg(F.sum("odds").alias("_trust"))
    last = {str(r["source_id"]): r["odds"] for r in rates.where("fold = -1").orderBy(F.desc(F.abs("odds")), "source_id").limit(100_000).collect()}
    return last, sums


def _trust_of(wide: DataFrame, odds: dict[str, float], s: Settings) -> DataFrame:
    """Sums by candidate, from a fitted table."""
    table = wide.sparkSession.createDataFrame([(int(k), float(v)) for k, v in odds.items()], "_s long, odds double")
    said = wide.unpivot(["entity_id", "source_id"], list(s.attrs), "attr", "value").where("value is not null")
    return said.join(F.broadcast(table), said["source_id"].cast("long") == table["_s"]).groupBy(*CELL, "value").agg(F.sum("odds").alias("_trust"))


# -- training --------------------------------------------------------------------


def _source_block(sources: list, n: int) -> np.ndarray:
    """Claims of each source: one column a source of the list, and one for the others."""
    out = np.zeros((len(sources), n))
    for i, row in enumerate(sources):
        for v in row if row is not None else ():
            if v["at"] < n:
                out[i, v["at"]] += v["n"]
    return out


def _in_cells(z: np.ndarray, group: np.ndarray) -> np.ndarray:
    e = np.exp(z - pd.Series(z).groupby(group).transform("max").to_numpy())
    return e / np.bincount(group, weights=e)[group]


def _calibration(p: np.ndarray, y: np.ndarray, group: np.ndarray, how: str | None) -> tuple[float, float]:
    """(a, b) for logit(p) * a + b: Platt's, or a temperature that validation cells like best; (1, 0) where there is nothing to learn."""
    if how is None or not len(p):
        return 1.0, 0.0
    logit = np.log(np.clip(p, 1e-9, 1 - 1e-9) / np.clip(1 - p, 1e-9, 1))
    if how == "platt":
        # Targets a little inside 0 and 1, as there are few cells: a clean split mustn't mean certainty.
        ones, zeros = y.sum(), (1 - y).sum()
        a, b = platt_fit(logit, np.where(y > 0, (ones + 1) / (ones + 2), 1 / (zeros + 2))) if ones and zeros else (1.0, 0.0)
        return (a, b) if a > 0 else (1.0, 0.0)
    losses = {t: -np.log(np.maximum(_in_cells(t * logit, group)[y > 0], 1e-12)).mean() for t in (0.5, 0.7, 0.85, 1.0, 1.2, 1.5, 2.0)}
    return min(losses, key=losses.get), 0.0


def _candidate_fit(pdf: pd.DataFrame, n_sources: int, s: Settings) -> dict:
    pdf = pdf.sort_values(["entity_id", "slot"]).reset_index(drop=True)
    x = np.array(pdf["x"].tolist(), dtype=float).reshape(len(pdf), -1)
    y = (pdf["value"] == pdf["truth"]).to_numpy(float)
    return candidate_fit(x, _source_block(pdf["sources"].tolist(), n_sources), y, pdf["entity_id"].to_numpy(), pdf["part"].to_numpy(), pdf["weight"].to_numpy(float), s)


def candidate_fit(x: np.ndarray, block: np.ndarray, y: np.ndarray, entity: np.ndarray, part: np.ndarray, weight: np.ndarray, s: Settings) -> dict:
    """Fit on training cells, choose l2 and the sources' share of it on validation cells; rows by entity and slot, block: claims by source."""
    n_sources = block.shape[1]
    mean, scale = x.mean(axis=0), x.std(axis=0)
    scale[scale < 1e-9] = 1.0
    x = np.hstack([(x - mean) / scale, block])
    group = pd.factorize(entity)[0]
    has = np.bincount(group, weights=y)[group] > 0
    valid = (part == "validation") & has
    train = (part != "validation") & has
    weight = weight.copy()
    # Weak labels all say what the vote says: together they weigh `weak_weight` times the seeds, however many they are.
    weak = part == "weak"
    if weak.any() and (train & ~weak).any():
        weight[weak] *= len(np.unique(group[train & ~weak])) / len(np.unique(group[weak]))
    if not train.any():
        return {"w": [0.0] * x.shape[1], "mean": mean.tolist(), "scale": scale.tolist(), "l2": s.l2_grid[0], "a": 1.0, "b": 0.0}
    best = None
    # Sources are many and each is rarely right or wrong on a seed: their weights may be held down more.
    ridges = [l2 * np.concatenate([np.ones(len(mean)), np.full(x.shape[1] - len(mean), r)]) for l2 in s.l2_grid for r in (s.source_ridges if n_sources else (1.0,))]
    taught, w = (x[train], y[train], pd.factorize(group[train])[0], weight[train]), None
    for l2 in ridges if valid.any() else ridges[len(ridges) // 2 :][:1]:
        w = conditional_softmax(*taught, l2, start=w)  # ridges are like their neighbours: a few steps from the last one's weights
        if not valid.any():
            best = (0.0, l2, w)
            break
        p = _in_cells(x[valid] @ w, pd.factorize(group[valid])[0])
        loss = -np.log(np.maximum(p[y[valid] > 0], 1e-12)).mean()
        if best is None or loss < best[0]:
            best = (loss, l2, w)
    _, l2, w = best
    a, b = 1.0, 0.0
    if valid.any():
        g = pd.factorize(group[valid])[0]
        a, b = _calibration(_in_cells(x[valid] @ w, g), y[valid], g, s.calibrate)
        both = train | valid  # with l2 chosen, the validation cells teach too
        w = conditional_softmax(x[both], y[both], pd.factorize(group[both])[0], weight[both], l2, start=w)
    return {"w": w.tolist(), "mean": mean.tolist(), "scale": scale.tolist(), "l2": float(l2[0]), "a": a, "b": b}


def _probabilities(x: np.ndarray, w, classifier: str) -> np.ndarray:
    if classifier == "tree":
        return tree_rows(x, w)
    z = np.hstack([x, np.ones((len(x), 1))]) @ np.array(w)
    return sigmoid_rows(z) if classifier == "logreg_ovr" else softmax_rows(z)


def _slot_fit(pdf: pd.DataFrame, n_sources: int, rho: int, s: Settings) -> dict:
    """The literal form: every vector is classified into the slots of its entity."""
    pdf = pdf.sort_values(["entity_id", "slot"]).reset_index(drop=True)
    x = np.array(pdf["x"].tolist(), dtype=float).reshape(len(pdf), -1)
    mean, scale = x.mean(axis=0), x.std(axis=0)
    scale[scale < 1e-9] = 1.0
    x = np.hstack([(x - mean) / scale, _source_block(pdf["sources"].tolist(), n_sources)])
    y = pdf["truth_slot"].to_numpy()
    weight = pdf["weight"].to_numpy(float)
    known = (y >= 0) & (y < rho)
    valid = known & (pdf["part"] == "validation").to_numpy()
    use = known & (pdf["part"] != "validation").to_numpy()
    if not use.any():
        use = known
    if not use.any():
        w = np.zeros((x.shape[1] + 1, rho))
        return {"w": w.tolist(), "mean": mean.tolist(), "scale": scale.tolist(), "l2": s.l2_grid[1], "a": 1.0, "b": 0.0}
    if s.classifier == "softmax_adam":
        w = adam_softmax(x[use], y[use], rho, weight[use], epochs=s.epochs, batch=s.batch, seed=s.seed)
    elif s.classifier == "logreg_ovr":
        w = one_vs_rest(x[use], y[use], rho, weight[use], l2=s.l2_grid[1])
    elif s.classifier == "tree":
        w = tree_fit(x[use], y[use], rho, weight[use])
    else:
        w = gradient_softmax(x[use], y[use], rho, weight[use], l2=s.l2_grid[1])
    a, b = 1.0, 0.0
    if valid.any() and s.calibrate:
        # What is calibrated is what is answered: the fused probability of each real slot.
        p = _probabilities(x[valid], w, s.classifier)
        cells = pd.factorize(pdf["entity_id"][valid])[0]
        fused = np.stack([np.bincount(cells, weights=p[:, k]) for k in range(rho)], axis=1)
        first = np.unique(cells, return_index=True)[1]
        real = np.arange(rho)[None] < np.minimum(pdf["n_slots"][valid].to_numpy()[first], rho)[:, None]
        fused = np.where(real, fused, 0)
        fused /= np.maximum(fused.sum(axis=1, keepdims=True), 1e-12)
        hot = np.arange(rho)[None] == y[valid][first][:, None]
        a, b = _calibration(fused[real], hot[real].astype(float), np.repeat(np.arange(len(first)), real.sum(axis=1)), s.calibrate)
    return {"w": w if isinstance(w, (dict, list)) else w.tolist(), "mean": mean.tolist(), "scale": scale.tolist(), "l2": s.l2_grid[1], "a": a, "b": b}


def _train(featured: DataFrame, labels: DataFrame, s: Settings, sources: list[int], stage: int, rho: dict[str, int]) -> StageModel:
    """labels: (entity_id, attr, truth, part, weight) for the cells to learn from; rho: the label dimension of each model."""
    n_sources = len(sources) + 1 if sources else 0
    rows = featured.join(labels, list(CELL)).withColumn("model_key", model_key(s))
    rows = rows.withColumn("truth_slot", F.max(F.when(F.col("value") == F.col("truth"), F.col("slot")).otherwise(-1)).over(Window.partitionBy(*CELL)))

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        got = _candidate_fit(pdf, n_sources, s) if s.layout == "candidate" else _slot_fit(pdf, n_sources, rho[key[0]], s)
        return pd.DataFrame({"model_key": [key[0]], "model": [json.dumps(got)]})

    model = StageModel(stage, 0.0)
    for r in rows.groupBy("model_key").applyInPandas(run, "model_key string, model string").collect():  # one row an attribute and run
        got, k = json.loads(r["model"]), r["model_key"]
        model.weights[k], model.means[k], model.scales[k] = got["w"], got["mean"], got["scale"]
        model.platt[k], model.l2 = (got["a"], got["b"]), got["l2"]
    return model


def _calibrated(scored: DataFrame, m: StageModel, s: Settings) -> DataFrame:
    """p after calibration, renormalised within the cell."""
    if all(ab == (1.0, 0.0) for ab in m.platt.values()):
        return scored
    table = F.broadcast(scored.sparkSession.createDataFrame([(k, *ab) for k, ab in m.platt.items()], "_k string, _a double, _b double"))
    p = F.greatest(F.least(F.col("p"), F.lit(1 - 1e-9)), F.lit(1e-9))
    moved = 1 / (1 + F.exp(-(F.coalesce("_a", F.lit(1.0)) * F.log(p / (1 - p)) + F.coalesce("_b", F.lit(0.0)))))
    rows = scored.join(table, model_key(s) == F.col("_k"), "left").withColumn("_p", F.when(F.col("p") > 0, moved).otherwise(0.0))
    total = F.sum("_p").over(Window.partitionBy(*CELL))
    return rows.select(*CELL, "value", "slot", F.when(total > 0, F.col("_p") / total).otherwise(F.col("p")).alias("p"))


def _score(featured: DataFrame, m: StageModel, s: Settings, sources: list[int], accuracy: DataFrame | None = None) -> DataFrame:
    """(entity_id, attr, value, slot, p).  In the layout 'candidate' by native dot products with a joined table of weights."""
    if s.layout != "candidate":
        return _calibrated(_slot_scores(featured, m, s, sources, accuracy), m, s)
    rows = []
    for k, w in m.weights.items():
        n = len(m.means[k])
        scaled = np.array(w[:n]) / np.array(m.scales[k])
        rows.append((k, scaled.tolist(), list(map(float, w[n:])), float(scaled @ np.array(m.means[k]))))
    # One row an attribute and run: as many numbers as features and listed sources.
    table = F.broadcast(featured.sparkSession.createDataFrame(rows, "_k string, _w array<double>, _s array<double>, _c double"))
    joined = featured.join(table, model_key(s) == F.col("_k"), "left")
    dot = F.aggregate(F.zip_with("x", "_w", lambda x, y: x * y), F.lit(0.0), lambda t, v: t + v) - F.col("_c")
    if sources:
        dot = dot + F.aggregate("sources", F.lit(0.0), lambda t, v: t + v["n"] * F.coalesce(F.get("_s", v["at"]), F.lit(0.0)))
    cell = Window.partitionBy(*CELL)
    scored = joined.withColumn("_z", F.coalesce(dot, F.lit(0.0))).withColumn("_e", F.exp(F.col("_z") - F.max("_z").over(cell)))
    return _calibrated(scored.select(*CELL, "value", "slot", (F.col("_e") / F.sum("_e").over(cell)).alias("p")), m, s)


def _slot_scores(featured: DataFrame, m: StageModel, s: Settings, sources: list[int], accuracy: DataFrame | None) -> DataFrame:
    shared = featured.sparkSession.sparkContext.broadcast(m)
    n_sources = len(sources) + 1 if sources else 0

    def run(batches):
        model = shared.value
        for pdf in batches:
            p: list = [None] * len(pdf)
            for k, rows in pdf.groupby("k"):
                if k not in model.weights:
                    continue
                x = (np.array(rows["x"].tolist(), dtype=float).reshape(len(rows), -1) - model.means[k]) / model.scales[k]
                x = np.hstack([x, _source_block(rows["sources"].tolist(), n_sources)])
                for i, d in zip(rows.index, _probabilities(x, model.weights[k], s.classifier), strict=True):
                    p[i] = d.tolist()
            yield pd.DataFrame({"entity_id": pdf["entity_id"], "attr": pdf["attr"], "w": pdf["w"], "dist": p})

    weight = F.lit(1.0)
    rows = featured
    if s.fuse == "weighted" and accuracy is not None:
        rows = rows.join(F.broadcast(accuracy), F.get("sources", F.lit(0))["at"] == accuracy["_at"], "left")
        weight = F.coalesce("_accuracy", F.lit(0.5))
    out = rows.select(*CELL, model_key(s).alias("k"), weight.alias("w"), "x", "sources").mapInPandas(run, "entity_id long, attr string, w double, dist array<double>")
    exploded = out.select(*CELL, "w", F.posexplode("dist").alias("slot", "q"))
    q = F.col("q")
    fused = {"mean": F.avg(q), "max": F.max(q), "logmean": F.exp(F.avg(F.log(F.greatest(q, F.lit(1e-12))))), "weighted": F.sum(q * F.col("w")) / F.sum("w")}[s.fuse]
    cells = exploded.groupBy(*CELL, "slot").agg(fused.alias("_p"))
    own = featured.select(*CELL, F.explode("values").alias("v")).select(*CELL, "v.*") if "values" in featured.columns else featured.select(*CELL, "value", "slot").distinct()
    own = own.join(cells, [*CELL, "slot"], "left").withColumn("_p", F.coalesce("_p", F.lit(0.0)))
    cell = Window.partitionBy(*CELL)
    total = F.sum("_p").over(cell)
    return own.select(*CELL, "value", "slot", F.when(total > 0, F.col("_p") / total).otherwise(1 / F.count(F.lit(1)).over(cell)).alias("p"))


def _side_by_side(featured: DataFrame, width: int, s: Settings) -> DataFrame:
    """The layout 'entity_slots': one row a cell, the vectors of its first max_slots candidates one after another; all values beside it."""
    slots = F.array_sort(F.collect_list(F.when(F.col("slot") < s.max_slots, F.struct("slot", "x"))))
    values = F.array_sort(F.collect_list(F.struct("slot", "value")))
    rows = featured.groupBy(*CELL).agg(slots.alias("_v"), values.alias("values"), F.max("n_slots").alias("n_slots"), F.flatten(F.collect_list("sources")).alias("sources"))
    zero = F.array_repeat(F.lit(0.0), width)
    x = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(s.max_slots - 1)), lambda i: F.coalesce(F.get("_v", i)["x"], zero)))
    return rows.select(*CELL, F.get("values", F.lit(0))["value"].alias("value"), F.lit(1).cast("long").alias("support"), F.lit(0).alias("slot"), "n_slots", "sources", x.alias("x"), "values")


def top(scored: DataFrame) -> DataFrame:
    w = Window.partitionBy(*CELL).orderBy(F.desc("p"), F.asc("slot"))
    return scored.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*CELL, "value", "slot", "p")


def sampled(scored: DataFrame, seed: int = 0) -> DataFrame:
    """One candidate a cell, drawn in proportion to its probability by seeded noise."""
    cell = Window.partitionBy(*CELL).orderBy("slot")
    upto = F.sum("p").over(cell.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    hit = scored.withColumn("_upto", upto).where((F.col("_upto") > draw(seed)) | (F.col("_upto") >= 1 - 1e-9))
    return hit.withColumn("_r", F.row_number().over(cell)).where("_r = 1").select(*CELL, "value", "slot", "p")


# -- the whole -------------------------------------------------------------------


def _label_table(cands: DataFrame, seeds: DataFrame, predicted: DataFrame | None, s: Settings) -> DataFrame:
    """(entity_id, attr, truth, part, weight): seed labels, and weak ones for the other entities; of `max_train` entities each in a run, if there is such a bound."""
    parts = seed_split(seeds.select("entity_id"), 0.8, 0.2, s.seed + 11)
    known = seeds.select(*CELL, F.col("value").alias("truth")).join(parts, "entity_id")

    def some(rows: DataFrame, salt: int) -> DataFrame:
        if s.max_train is None:
            return rows
        by = Window.partitionBy(run_of("entity_id")).orderBy(mix("abs(entity_id)", salt, 91, s.seed), "entity_id")
        distinct = rows.select("entity_id").distinct()
        if s.runs == 1:
            return rows.join(F.broadcast(distinct.orderBy(mix("abs(entity_id)", salt, 91, s.seed), "entity_id").limit(s.max_train)), "entity_id")
        return rows.join(F.broadcast(distinct.withColumn("_r", F.row_number().over(by)).where(F.col("_r") <= s.max_train).select("entity_id")), "entity_id")

    known = some(known, 3).select(*CELL, "truth", F.when(F.col("part") == "validation", "validation").otherwise("train").alias("part"), F.lit(1.0).alias("weight"))
    if s.train_on == "seed" or s.weak_weight <= 0:
        return known
    votes = Window.partitionBy(*CELL).orderBy(F.desc("support"), F.asc("value"))
    first = cands.withColumn("_r", F.row_number().over(votes)).where("_r = 1") if s.slot_order != "support" else cands.where("slot = 0")
    weak = (predicted if predicted is not None else first).select(*CELL, F.col("value").alias("truth")).join(seeds.select("entity_id").distinct(), "entity_id", "left_anti")
    return known.union(some(weak, 5).select(*CELL, "truth", F.lit("weak"), F.lit(float(s.weak_weight))))


@dataclass
class _Tables:
    """What the stages read: records, seeds, candidates, units (candidates or claims), and what is known of sources."""

    wide: DataFrame
    seeds: DataFrame | None
    cands: DataFrame
    units: DataFrame
    names: list[str]
    sources: list[int]
    trust: DataFrame | None = None
    accuracy: DataFrame | None = None
    rho: dict[str, int] = field(default_factory=dict)


def _label_dimension(cands: DataFrame, s: Settings) -> dict[str, int]:
    """The most candidates that a cell of an attribute (and run) has, `max_slots` at most; only the slot layouts ask."""
    if s.layout == "candidate":
        return {}
    rows = cands.groupBy(model_key(s).alias("k")).agg(F.max("n_slots").alias("rho")).collect()  # one row an attribute and run
    return {r["k"]: min(s.max_slots, r["rho"]) for r in rows}


def _tables(wide: DataFrame, seeds: DataFrame | None, s: Settings, sources: list[int] | None, name: str) -> _Tables:
    wide = number_records(wide, s, f"{name}-wide")
    sources = source_list(wide, s) if sources is None else sources
    cands, names = _static(wide, s, sources)
    cands = settle(cands, f"{name}-static")
    units = cands if s.layout in ("candidate", "entity_slots") else settle(_claim_static(wide, cands, names, s, sources), f"{name}-claims")
    return _Tables(wide, seeds, cands, units, names, sources)


def _accuracy(t: _Tables, s: Settings) -> DataFrame | None:
    """(place of a source, its accuracy on seeds), for weighted fusing."""
    if s.fuse != "weighted" or not t.sources or t.seeds is None:
        return None
    said = t.wide.unpivot(["entity_id", "source_id"], list(s.attrs), "attr", "value").where("value is not null and source_id is not null")
    rates = {r["source_id"]: r["accuracy"] for r in source_accuracy(said, t.seeds).where(F.col("source_id").isin(t.sources)).collect()}  # listed sources
    return t.wide.sparkSession.createDataFrame([(i, float(rates.get(v, 0.5))) for i, v in enumerate(t.sources)], "_at int, _accuracy double")


def _first_votes(t: _Tables) -> DataFrame:
    w = Window.partitionBy(*CELL).orderBy(F.desc("support"), F.asc("value"))
    return t.cands.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*CELL, "value")


def _featured(t: _Tables, labels: DataFrame | None, s: Settings, stage: int) -> tuple[DataFrame, list[str]]:
    featured, more = _dynamic(t.wide, t.units, labels, s, stage, t.trust)
    names = [*t.names, *more]
    if s.layout == "entity_slots":
        featured, names = _side_by_side(featured, len(names), s), [f"{n}@{i}" for i in range(s.max_slots) for n in names]
    return featured, names


def _answers(scored: DataFrame, s: Settings, stage: int) -> DataFrame:
    return top(scored) if s.pick == "argmax" else sampled(scored, s.seed + stage)


#: Settings that static features depend on, blocks and sources aside.
_STATIC = ("attrs", "rules", "rule_partners", "layout", "embed", "embed_dim", "onehot_dim", "dist", "slot_order", "nulls", "max_sources", "seed")


@dataclass
class Prepared:
    """Numbered records and static features of all blocks, from which fits of the layout 'candidate' take those they have."""

    settings: Settings
    wide: DataFrame
    cands: DataFrame
    names: list[str]
    sources: list[int]

    def repeated(self, runs: int) -> Prepared:
        """The same records in each of several runs: rules and neighbours are those of one run."""

        def often(df: DataFrame) -> DataFrame:
            rows = df.withColumn("_run", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(runs - 1).cast("long"))))
            if "record_id" in df.columns:
                rows = rows.withColumn("record_id", F.col("record_id") * runs + F.col("_run"))
            return rows.withColumn("entity_id", F.col("_run") * RUN + F.col("entity_id")).drop("_run")

        return self if runs == 1 else replace(self, settings=replace(self.settings, runs=runs), wide=often(self.wide), cands=often(self.cands))

    def shares(self, s: Settings) -> bool:
        """Whether the static features of a fit are among these; its runs aside."""
        same = all(getattr(s, k) == getattr(self.settings, k) for k in _STATIC)
        return same and s.augment == 0 and set(s.models) <= set(self.settings.models) and (self.settings.use_source or not s.use_source)

    def serves(self, s: Settings) -> bool:
        return self.shares(s) and s.runs == self.settings.runs

    def columns(self, s: Settings) -> list[int]:
        """The static features of the blocks that a fit has."""
        block = {"votetop": "vote_top"}
        return [i for i, n in enumerate(self.names) if (b := n.rstrip("0123456789").split("_")[0]) in s.models or block.get(b, "rules" if b == "rule" else b) in s.models]

    def tables(self, seeds: DataFrame, s: Settings) -> _Tables:
        have = self.columns(s)
        sources = self.sources if s.use_source and "source" in s.models else []
        cands = self.cands.withColumn("static", F.array(*[F.col("static")[i] for i in have]).cast("array<double>"))
        if not sources:
            cands = cands.withColumn("sources", F.array().cast(self.cands.schema["sources"].dataType))
        return _Tables(self.wide, seeds, cands, cands, [self.names[i] for i in have], sources)


def prepare(wide: DataFrame, s: Settings) -> Prepared:
    """Static features that several fits over the same records share: with s for its blocks, all of which they may have."""
    if s.layout != "candidate":
        raise ValueError("static features are shared in the layout 'candidate' only")
    s = replace(s, runs=1)
    wide = number_records(wide, s, "prepared-wide")
    sources = source_list(wide, s)
    cands, names = _static(wide, s, sources)
    return Prepared(s, wide, settle(cands, "prepared-static"), names, sources)


def _begin(wide: DataFrame, seeds: DataFrame, s: Settings, prepared: Prepared | None = None) -> tuple[_Tables, Fitted]:
    """Augment, number, and make static features, or take prepared ones; what both formulations start from."""
    values = [a for a in s.attrs if a in wide.columns]
    wide = wide.select("entity_id", *[c for c in ("source_id",) if c in wide.columns], *values)
    seeds = settle(seeds.select(*CELL, "value"), "resolver-seeds")
    if s.augment > 0:
        wide, seeds = augmentation.augment_records(number_records(wide, s, "resolver-given"), seeds, list(s.attrs), s.augment, s.seed, s.augment_to)
        seeds = settle(seeds, "resolver-seeds")
    t = prepared.tables(seeds, s) if prepared is not None and prepared.serves(s) else _tables(wide, seeds, s, None, "resolver")
    out = Fitted(s, t.sources, [], [])
    if s.trust and t.sources:
        out.trust, sums = _trust_table(t.wide, seeds, s)
        t.trust = settle(sums, "resolver-trusted")
    t.accuracy, t.rho = _accuracy(t, s), _label_dimension(t.cands, s)
    return t, out


def _known(seeds: DataFrame, predicted: DataFrame, s: Settings) -> DataFrame:
    """Labels that the next stage's features see.  With dynamic_from='model' no feature of a known entity has seen its truth, at no stage."""
    answers = predicted.select(*CELL, "value")
    return answers if s.dynamic_from == "model" else update_labels(seeds, answers).select(*CELL, "value")


def fit(wide: DataFrame, seeds: DataFrame, s: Settings, prepared: Prepared | None = None) -> tuple[Fitted, DataFrame]:
    """The fitted stages, and (entity_id, attr, value, slot, p) of the last stage for all candidates.

    wide: (entity_id, source_id or none, attributes as strings); seeds: (entity_id,
    attr, value) of known entities.  Without seeds the vote is the label of all cells.
    prepared: what prepare() has made of the same records, in all runs alike.
    """
    t, out = _begin(wide, seeds, s, prepared)
    labels = None if s.first_dynamic == "zero" else _known(t.seeds, _first_votes(t), s)
    predicted = scored = None
    for stage in range(s.stages):
        featured, out.names = _featured(t, labels, s, stage)
        featured = settle(featured, f"resolver-stage{stage}")
        model = _train(featured, _label_table(t.cands, t.seeds, predicted, s), s, t.sources, stage, t.rho)
        out.stages.append(model)
        scored = settle(_score(featured, model, s, t.sources, t.accuracy), f"resolver-scored{stage}")
        release(featured)
        out.history.append(scored)
        now = _answers(scored, s, stage)
        if s.early_stop is not None and predicted is not None:
            both = now.join(predicted.select(*CELL, F.col("value").alias("_before")), list(CELL))
            if (both.agg(F.avg((F.col("value") != F.col("_before")).cast("double"))).first()[0] or 0.0) < s.early_stop:
                break
        predicted, labels = now, _known(t.seeds, now, s)
    return out, scored


def resolve_dynamic(wide: DataFrame, seeds: DataFrame, s: Settings) -> DataFrame:
    """(entity_id, attr, value, slot, p) by the formulation with dynamic features.

    One table holds each unit's static vector and its dynamic vector, zero at
    first.  A round trains on it, predicts, keeps the known labels, and puts the dynamic
    features that follow from the labels in place of the old ones.  There is no
    list of stages; only the last model is left.
    """
    s = replace(s, first_dynamic="zero")
    t, _ = _begin(wide, seeds, s)
    table, _ = _featured(t, None, s, 0)
    table, weak, scored = settle(table, "dynamic-table"), None, None
    for k in range(s.stages):
        model = _train(table, _label_table(t.cands, t.seeds, weak, s), s, t.sources, k, t.rho)
        scored = settle(_score(table, model, s, t.sources, t.accuracy), "dynamic-scored")
        if k + 1 < s.stages:
            weak = _answers(scored, s, k)
            fresh, _ = _featured(t, _known(t.seeds, weak, s), s, k + 1)
            old, table = table, settle(fresh, "dynamic-table")
            release(old)
    return scored


def resolve(scored: DataFrame, seeds: DataFrame | None = None, pick: str = "argmax", seed: int = 0) -> DataFrame:
    """(entity_id, attr, value, p) for every cell; known values stay."""
    answers = (top(scored) if pick == "argmax" else sampled(scored, seed)).where("entity_id >= 0").select(*CELL, "value", "p")
    if seeds is None:
        return answers
    known = seeds.select(*CELL, F.col("value").alias("_seed"))
    return answers.join(known, list(CELL), "left").select(*CELL, F.coalesce("_seed", "value").alias("value"), F.when(F.col("_seed").isNotNull(), 1.0).otherwise(F.col("p")).alias("p"))


def forward(fitted: Fitted, wide: DataFrame) -> list[DataFrame]:
    """The layers' outputs for entities never seen: each stage's scores feed the next one's dynamic features, weights frozen."""
    s = fitted.settings
    t = _tables(wide.select("entity_id", *[c for c in ("source_id",) if c in wide.columns], *s.attrs), None, s, fitted.sources, "resolver-new")
    if fitted.trust:
        t.trust = settle(_trust_of(t.wide, fitted.trust, s), "resolver-new-trusted")
    labels = None if s.first_dynamic == "zero" else _first_votes(t)
    out = []
    for m in fitted.stages:
        featured, _ = _featured(t, labels, s, m.stage)
        out.append(settle(_score(featured, m, s, t.sources, t.accuracy), f"resolver-new{m.stage}"))
        labels = _answers(out[-1], s, m.stage).select(*CELL, "value")
    return out


def resolve_new(fitted: Fitted, wide: DataFrame) -> DataFrame:
    """(entity_id, attr, value, slot, p) for entities never seen: the last layer's output."""
    return forward(fitted, wide)[-1]


def weight_report(fitted: Fitted) -> list[tuple[int, str, str, float]]:
    """(stage, attr, block, norm) of the trained weights of each feature block."""
    rows = []
    for m in fitted.stages:
        for a, w in m.weights.items():
            w = np.abs(np.array(w)).sum(axis=1) if np.ndim(w) == 2 else np.abs(np.array(w))
            blocks: dict[str, float] = {}
            for name, v in zip(fitted.names, w, strict=False):
                block = name.split("@")[0].rstrip("0123456789").split("_")[0]
                blocks[block] = blocks.get(block, 0.0) + float(v) ** 2
            if fitted.sources:
                blocks["source"] = float((w[len(fitted.names) : len(fitted.names) + len(fitted.sources) + 1] ** 2).sum())
            rows += [(m.stage, a, b, v**0.5) for b, v in sorted(blocks.items())]
    return rows
