"""From scores to answers: fusing cells, cutting to real slots, picking."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import mix
from .claims import CELL, F_ATTR


def fuse(cells: DataFrame, how: str = "mean", weight: str | None = None) -> DataFrame:
    """(entity_id, attr, slot, p) from one score a (cell, slot): mean, log mean, max, or weighted mean."""
    p = F.col("p")
    agg = {"mean": F.avg(p), "logmean": F.exp(F.avg(F.log(F.greatest(p, F.lit(1e-12))))), "max": F.max(p), "weighted": F.sum(p * F.col(weight)) / F.sum(weight) if weight else None}.get(how)
    if agg is None:
        raise ValueError("how must be mean, logmean, max, or weighted with a weight")
    return cells.groupBy(*CELL, "slot").agg(agg.alias("p"))


def softmax(scores: Column) -> Column:
    """Softmax of an array, shifted by its largest entry."""
    e = F.transform(scores, lambda x: F.exp(x - F.array_max(scores)))
    return F.transform(e, lambda x: x / F.aggregate(e, F.lit(0.0), lambda s, y: s + y))


def truncate(dist: Column, n_slots: Column) -> Column:
    """The first n_slots entries, renormalised; equal shares where they sum to 0."""
    cut = F.slice(dist, F.lit(1), n_slots)
    total = F.aggregate(cut, F.lit(0.0), lambda s, x: s + x)
    return F.transform(cut, lambda x: F.when(total > 0, x / total).otherwise(1.0 / n_slots))


def pick(dist: Column, how: str = "argmax", draw: Column | None = None) -> Column:
    """The slot of the largest probability, or the one in whose share a draw in [0, 1) falls."""
    if how == "argmax":
        return (F.array_position(dist, F.array_max(dist)) - 1).cast("int")
    if how != "sample" or draw is None:
        raise ValueError("how must be argmax, or sample with a draw")
    upto = F.aggregate(dist, F.struct(F.lit(0.0).alias("sum"), F.lit(0).alias("n")), lambda s, x: F.struct((s["sum"] + x).alias("sum"), (s["n"] + (s["sum"] + x <= draw).cast("int")).alias("n")))
    return F.least(upto["n"], F.size(dist) - 1)


def draw(seed: int = 0) -> Column:
    return (mix("entity_id", 0, F_ATTR, seed) % 1000000) / 1000000.0


def distributions(scored: DataFrame) -> DataFrame:
    """(entity_id, attr, dist): probability of each candidate value."""
    return scored.groupBy(*CELL).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("value", "p")))).alias("dist"))


def update_labels(seeds: DataFrame, predictions: DataFrame) -> DataFrame:
    """Known labels stay; the others are the predictions."""
    known = seeds.select(*CELL, F.col("value").alias("_seed"))
    return predictions.join(known, list(CELL), "full").select(*CELL, F.coalesce("_seed", "value").alias("value"), F.when(F.col("_seed").isNotNull(), "seed").otherwise("model").alias("origin"))
