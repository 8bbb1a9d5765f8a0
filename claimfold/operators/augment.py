"""Synthetic entities by editing values to the formats of others."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..functions.noise import mix
from .claims import CELL, F_ATTR, candidates

#: A run of letters, a run of digits, or any one other character.
RUN = r"[A-Za-z]+|[0-9]+|(?s:.)"


def format_runs(value: Column) -> Column:
    """Runs of a string as (sym, text): L one letter, L+ more, D one digit, D+ more, others themselves."""
    texts = F.regexp_extract_all(value, F.lit(RUN), F.lit(0))

    def sym(t: Column) -> Column:
        return F.when(t.rlike("^[A-Za-z]$"), "L").when(t.rlike("^[A-Za-z]+$"), "L+").when(t.rlike("^[0-9]$"), "D").when(t.rlike("^[0-9]+$"), "D+").otherwise(t)

    return F.transform(texts, lambda t: F.struct(sym(t).alias("sym"), t.alias("text")))


def runs_python(value: str) -> list[tuple[str, str]]:
    def sym(t: str) -> str:
        kind = "L" if re.fullmatch(r"[A-Za-z]+", t) else "D" if re.fullmatch(r"[0-9]+", t) else ""
        return t if not kind else kind if len(t) == 1 else kind + "+"

    return [(sym(t), t) for t in re.findall(RUN, value)]


def common_run_python(a: list[str], b: list[str]) -> tuple[int, int]:
    """(start in a, length) of the longest common piece of two symbol lists: leftmost in a, 0 length if none."""
    best, row = (0, 0), [0] * (len(b) + 1)
    for i, x in enumerate(a):
        row = [0, *(row[j] + 1 if x == y else 0 for j, y in enumerate(b))]
        top = max(row)
        if top > best[1]:
            best = (i + 1 - top, top)
    return best


def edit_python(source: str, target: str) -> str:
    """What of source stands under the longest piece of format that both share; source itself if none."""
    a, b = runs_python(source), runs_python(target)
    start, n = common_run_python([s for s, _ in a], [s for s, _ in b])
    return "".join(t for _, t in a[start : start + n]) if n else source


@F.pandas_udf(T.StringType())
def edit_to_format(source: pd.Series, target: pd.Series) -> pd.Series:
    return pd.Series([edit_python(a, b) if a is not None and b is not None else a for a, b in zip(source, target, strict=True)])


@F.pandas_udf(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("length", T.IntegerType())]))
def common_run(source: pd.Series, target: pd.Series) -> pd.DataFrame:
    rows = [common_run_python([s for s, _ in runs_python(a)], [s for s, _ in runs_python(b)]) for a, b in zip(source, target, strict=True)]
    return pd.DataFrame(rows, columns=["start", "length"])


def _drawn(truth: DataFrame, ratio: float, seed: int) -> DataFrame:
    """(entity_id, _copy, new_id): labelled entities that noise draws, each as often as it is copied."""
    if ratio < 0:
        raise ValueError("the ratio must not be negative")
    times = F.floor(F.lit(ratio)) + (mix("entity_id", 1, 77, seed) % 10000 < round((ratio % 1) * 10000)).cast("int")
    drawn = truth.select("entity_id").distinct().withColumn("_n", times.cast("int")).where("_n > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_n"))))
    return drawn.select("entity_id", "_copy", (-(F.col("entity_id") * 64 + F.col("_copy"))).alias("new_id"))


def _targets(claims: DataFrame, truth: DataFrame, to: str) -> DataFrame:
    """(attr, _at, _target): the claims whose formats may be drawn, numbered within their attribute from 0.

    'any' claim; claims of a known 'truth'; or the 'majority' of each cell.  Numbers
    come from an aggregate of counts a bucket and a prefix sum: no attribute is
    sorted in one task.
    """
    rows = claims.select(*CELL, "value")
    if to == "truth":
        rows = rows.join(truth.select(*CELL, "value"), [*CELL, "value"])
    elif to == "majority":
        rows = candidates(rows).where("slot = 0").select(*CELL, "value")
    elif to != "any":
        raise ValueError("formats are drawn from 'any', 'truth' or 'majority'")
    bucketed = rows.withColumn("_b", F.pmod(F.xxhash64("entity_id", "value"), F.lit(1024)))
    counts = bucketed.groupBy("attr", "_b").agg(F.count(F.lit(1)).alias("_c"))
    starts = counts.withColumn("_start", F.sum("_c").over(Window.partitionBy("attr").orderBy("_b")) - F.col("_c")).drop("_c")
    numbered = bucketed.withColumn("_i", F.row_number().over(Window.partitionBy("attr", "_b").orderBy("entity_id", "value")) - 1).join(starts, ["attr", "_b"])
    return numbered.select("attr", (F.col("_start") + F.col("_i")).alias("_at"), F.col("value").alias("_target"))


def augment_entities(claims: DataFrame, truth: DataFrame, ratio: float = 0.1, seed: int = 0, to: str = "any") -> tuple[DataFrame, DataFrame]:
    """(claims, truth) of synthetic entities with negative ids, about `ratio` times the labelled entities.

    Each copies a labelled entity that noise draws.  Claims of the true value stay;
    each other claim is edited to the format of a claim of the same attribute
    (`_targets`), drawn by its number: drawn numbers meet claims in an equality
    join.  The draw depends on the entity, the attribute, the value and the source,
    so claims that are alike are edited alike, and reruns agree.
    """
    drawn = _drawn(truth, ratio, seed)
    labelled = truth.select(*CELL, F.col("value").alias("_truth"))
    copies = claims.join(drawn, "entity_id").join(labelled, list(CELL), "left").withColumn("_edit", ~F.coalesce(F.col("value") == F.col("_truth"), F.lit(False)))
    numbered = _targets(claims, truth, to)
    size = numbered.groupBy("attr").agg(F.count(F.lit(1)).alias("_size"))  # one row an attribute
    source = "cast(coalesce(source_id, 0) as bigint)" if "source_id" in claims.columns else "cast(0 as bigint)"
    noise = mix("entity_id", f"({source} + ascii(value) * 61 + ascii(reverse(value)) * 7 + length(value) * 1009) % 1000003", f"{F_ATTR} + _copy * 7", seed + 1)
    aimed = copies.where("_edit").join(F.broadcast(size), "attr", "left").withColumn("_at", noise % F.col("_size"))
    edited = aimed.join(numbered, ["attr", "_at"], "left").withColumn("value", edit_to_format("value", "_target"))
    cols = [F.col("new_id").alias("entity_id"), *[F.col(c) for c in claims.columns if c != "entity_id"]]
    synthetic = edited.select(*cols).unionByName(copies.where("not _edit").select(*cols))
    labels = truth.join(drawn, "entity_id").select(F.col("new_id").alias("entity_id"), "attr", "value")
    return synthetic.select(*claims.columns), labels


def augment_records(wide: DataFrame, truth: DataFrame, attrs: list[str], ratio: float, seed: int = 0, to: str = "any") -> tuple[DataFrame, DataFrame]:
    """Records (entity_id, record_id, source_id, attributes) and truth, with those of synthetic entities added.

    A synthetic record has the claims of one record of the copied entity: records
    are told apart by record_id, whether or not they have sources.
    """
    claims = wide.unpivot(["entity_id", "record_id", "source_id"], attrs, "attr", "value").where("value is not null")
    more, labels = augment_entities(claims, truth, ratio, seed, to)
    records = more.groupBy("entity_id", "record_id", "source_id").pivot("attr", attrs).agg(F.first("value"))
    return wide.drop("record_id").unionByName(records.drop("record_id")), truth.unionByName(labels)
