"""From wide records to claims, candidates, slots and labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.noise import mix
from ..sources.tables import canonical

CELL = ("entity_id", "attr")
#: Entity ids of the r-th of several independent runs in one table start at r * RUN.
RUN = 1 << 40


def run_of(entity: str) -> Column:
    """The run of an entity; synthetic entities, whose ids are negative, belong to the run of the one they copy."""
    e = F.col(entity)
    return F.floor(F.when(e < 0, F.floor(-e / 64)).otherwise(e) / RUN).cast("int")


def to_claims(df: DataFrame, entity: str, attrs: list[str], source: str | None = None, record: str | None = None, nulls: str = "drop") -> DataFrame:
    """(entity_id, record_id, source_id, attr, value): one row a cell, no shuffle.

    record_id is the given column or a hash of the row; nulls are dropped, or kept
    as the string '<null>' with nulls='as_value'.
    """
    if nulls not in ("drop", "as_value"):
        raise ValueError("nulls must be 'drop' or 'as_value'")
    missing = {entity, *attrs, *filter(None, (source, record))} - set(df.columns)
    if missing:
        raise ValueError(f"no such column: {sorted(missing)}")
    rid = F.col(record) if record else F.xxhash64(*df.columns)
    cells = [canonical(df, a).alias(f"_v{i}") for i, a in enumerate(attrs)]
    wide = df.select(F.col(entity).alias("entity_id"), rid.alias("record_id"), (F.col(source) if source else F.lit(None).cast("int")).alias("source_id"), *cells)
    wide = wide.toDF("entity_id", "record_id", "source_id", *attrs) if not {"entity_id", "record_id", "source_id"} & set(attrs) else wide
    long = wide.unpivot(["entity_id", "record_id", "source_id"], [c for c in wide.columns[3:]], "attr", "value")
    return long.where("value is not null") if nulls == "drop" else long.withColumn("value", F.coalesce("value", F.lit("<null>")))


def candidates(claims: DataFrame, slot_order: str = "support", max_slots: int | None = None) -> DataFrame:
    """(entity_id, attr, value, support, slot, n_slots): the distinct values of a cell, numbered.

    'support' numbers by claims, then value; 'value' by value.  After one exchange
    on the entity, count and numbering stay in place.
    """
    order = {"support": [F.desc("support"), F.asc("value")], "value": [F.asc("value")]}.get(slot_order)
    if order is None:
        raise ValueError("slot_order must be 'support' or 'value'")
    counted = claims.repartition("entity_id").groupBy("entity_id", "attr", "value").agg(F.count(F.lit(1)).alias("support"))
    cell = Window.partitionBy(*CELL)
    out = counted.withColumn("slot", F.row_number().over(cell.orderBy(*order)) - 1).withColumn("n_slots", F.count(F.lit(1)).over(cell))
    return out if max_slots is None else out.where(F.col("slot") < max_slots)


def label_dimension(cands: DataFrame) -> DataFrame:
    return cands.groupBy("attr").agg(F.max("n_slots").alias("rho"))


def truth_slots(truth: DataFrame, cands: DataFrame) -> DataFrame:
    """(entity_id, attr, value, slot): -1 where nobody claims the truth."""
    return truth.join(cands.select(*CELL, "value", "slot"), [*CELL, "value"], "left").select(*CELL, "value", F.coalesce("slot", F.lit(-1)).alias("slot"))


def one_hot(cands: DataFrame, labels: DataFrame) -> DataFrame:
    """(entity_id, attr, slot, hot) for every slot up to the label dimension; slots that a cell lacks are 0."""
    padded = labels.join(F.broadcast(label_dimension(cands)), "attr").select(*CELL, F.col("slot").alias("at"), F.explode(F.sequence(F.lit(0), F.col("rho").cast("int") - 1)).alias("slot"))
    return padded.select(*CELL, "slot", (F.col("slot") == F.col("at")).cast("int").alias("hot"))


def one_hot_vector(slot: Column, rho: Column | int) -> Column:
    return F.transform(F.sequence(F.lit(0), (rho if isinstance(rho, Column) else F.lit(rho)) - 1), lambda i: F.when(i == slot, 1.0).otherwise(0.0))


def vote_labels(cands: DataFrame, tie: str = "value", seed: int = 0) -> DataFrame:
    """(entity_id, attr, value, slot, support): the majority; ties by value or by seeded noise."""
    if tie == "value":
        return cands.where("slot = 0").select(*CELL, "value", "slot", "support") if "slot" in cands.columns else cands
    noise = mix("entity_id", "slot", F_ATTR, seed)
    w = Window.partitionBy(*CELL).orderBy(F.desc("support"), noise, F.asc("value"))
    return cands.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*CELL, "value", "slot", "support")


#: A number for an attribute's name that every SQL engine has alike.
F_ATTR = "(length(attr) * 31 + ascii(attr))"


def seed_split(entities: DataFrame, train: float, validation: float = 0.1, seed: int = 0) -> DataFrame:
    """(entity_id, part): train, validation or test by integer noise, stable under any partitioning."""
    if not 0 <= train <= 1 or not 0 <= validation <= 1 or train + validation > 1:
        raise ValueError("shares must be within 0 and 1, and together too")
    r = mix("entity_id", 0, 55, seed) % 10000
    a, b = round(train * 10000), round((train + validation) * 10000)
    return entities.select("entity_id").distinct().withColumn("part", F.when(r < a, "train").when(r < b, "validation").otherwise("test"))


def reachable(truth: DataFrame, cands: DataFrame) -> DataFrame:
    """(attr, n, reached): cells whose truth somebody claims."""
    return truth_slots(truth, cands).groupBy("attr").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("slot") >= 0).cast("long")).alias("reached"))


def golden(values: DataFrame, attrs: list[str]) -> DataFrame:
    """One row an entity from (entity_id, attr, value)."""
    return values.groupBy("entity_id").pivot("attr", attrs).agg(F.first("value"))
