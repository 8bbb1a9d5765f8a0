"""Noisy replicas: claims of many sources about a clean table, so that truth is known.

Every source covers some entities; a record errs more the less its source is
trusted.  In burst mode a bad record errs in most attributes at once.  Wrong
values are mostly those of the neighbouring entity, the same for all sources, so
votes can be fooled; others depend on the source, have another format, or miss.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.noise import mix, roll
from ..plans.workspace import partitions
from .tables import canonical, table


@dataclass(frozen=True)
class Spec:
    """Parameters of a replica set; accuracies and coverage are per mille."""

    n_sources: int
    coverage: int
    high: int = 850
    low: int = 350
    mode: str = "burst"
    trusted: int | None = None
    copies: tuple[tuple[int, int], ...] = ()
    salt: int = 0
    limit: int | None = None


#: Keys whose neighbours are found in one sort, and the neighbours of a key.
SPAN, REACH = 4096, 5


def _neighbours(clean: DataFrame, n: int) -> DataFrame:
    """(k, v0 .. v5): each key's row with those of the next keys, after the last one those of the first."""
    rows = clean.select(F.col("k").alias("own"), "v", F.explode(F.expr(f"sequence(k, greatest(k, {n + REACH - 1}), {n})")).alias("k"))
    # A row goes to its span of keys, and to the span before if a key there has it for a neighbour.
    rows = rows.select("*", F.explode(F.array_distinct(F.array(F.floor(F.col("k") / SPAN), F.floor((F.col("k") - REACH) / SPAN)))).alias("b"))
    w = Window.partitionBy("b").orderBy("k")
    near = [F.when(F.lead("k", d).over(w) == F.col("k") + d, F.lead("v", d).over(w)).alias(f"v{d}") for d in range(1, REACH + 1)]
    return rows.select("b", "own", "k", F.col("v").alias("v0"), *near).where((F.col("k") == F.col("own")) & (F.floor(F.col("k") / SPAN) == F.col("b"))).drop("b", "own")


def make_replicas(base: DataFrame, key: str, attrs: list[str], spec: Spec, keep: tuple[str, ...] | None = None) -> DataFrame:
    """(entity_id, source_id, attrs as strings), a row for each entity that a source covers; of the attributes those in `keep`, if given.

    Keys are 0 .. n - 1.  Neighbours are attached before sources multiply the
    rows, so that no claim is shuffled; the rows of an entity lie together.
    """
    kept = [a for a in attrs if keep is None or a in keep]
    typed = base if spec.limit is None else base.where(F.col(key) < spec.limit)
    clean = typed.select(F.col(key).cast("bigint").alias("k"), F.struct(*[canonical(base, a).alias(a) for a in kept]).alias("v"))
    n = clean.agg(F.count(F.lit(1))).first()[0]
    near = _neighbours(clean, max(n, 1))
    # The base is small where the claims are many: it is spread before sources multiply it.
    rows = near.repartition(partitions(near), "k").withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(spec.n_sources - 1))))
    rows = rows.where(roll("k", "s", 97, spec.salt) < spec.coverage)
    voice = F.col("s")
    for child, parent in spec.copies:
        voice = F.when((F.col("s") == child) & (roll("k", parent, 97, spec.salt) < spec.coverage), F.lit(parent)).otherwise(voice)
    rows = rows.withColumn("z", voice).withColumn("acc", F.expr(f"{spec.high} - (({spec.high - spec.low} * z) div {max(spec.n_sources - 1, 1)})"))
    other = F.when(F.col("z") % 5 == 0, F.col("v1"))
    for d in range(1, 5):
        other = other.when(F.col("z") % 5 == d, F.col(f"v{d + 1}"))
    rows = rows.withColumn("other", other)
    if spec.mode == "burst":
        rows = rows.withColumn("limit", F.when(roll("k", "z", 50, spec.salt) >= F.col("acc"), 850).otherwise(50))
    out = []
    for j, a in enumerate(attrs, start=1):
        if a not in kept:
            continue
        m = mix("k", "z", j, spec.salt)
        wrong = m % 1000 < F.col("limit") if spec.mode == "burst" else m % 1000 >= F.col("acc")
        if spec.trusted is not None:
            wrong &= F.col("z") != spec.trusted
        kind = F.floor(m / 1000) % 6
        v = F.col(f"v0.{a}")
        edit = (F.upper(v), F.substring(v, F.lit(1), F.greatest(F.length(v) - 2, F.lit(1))), F.replace(v, F.lit(" "), F.lit("-")))[j % 3]
        out.append(F.when(~wrong, v).when(kind <= 2, F.col(f"v1.{a}")).when(kind == 3, F.col(f"other.{a}")).when(kind == 4, edit).alias(a))
    return rows.select(F.col("k").alias("entity_id"), F.col("s").alias("source_id"), *out)


def customer_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    wide = nation.join(region, nation["n_regionkey"] == region["r_regionkey"]).select("n_nationkey", "n_name", "r_name")
    customer = table(spark, sf_dir, "customer")
    return customer.join(F.broadcast(wide), customer["c_nationkey"] == wide["n_nationkey"]).select("c_custkey", "c_name", "c_mktsegment", "c_nationkey", "n_name", "r_name", "c_acctbal")


def orders_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return o.join(c, o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "o_orderstatus", "o_orderpriority", "o_orderdate", "o_totalprice", "o_custkey", "c_mktsegment")


def part_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "part")
    return p.select(
        "p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice", F.split_part("p_name", F.lit(" "), F.lit(1)).alias("colour"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("noun"),
        F.split_part("p_brand", F.lit("#"), F.lit(2)).alias("brand_no"), F.expr("cast(p_size div 10 as string)").alias("size_band"), F.expr("cast(cast(p_retailprice as bigint) div 50 as string)").alias("price_band"),
    )


def supplier_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "supplier")


#: name: (base, key, attributes, parameters).  The stand-ins for the five data sets, and a tiny one.
SETS = {
    "orders": (orders_base, "o_orderkey", ["o_orderstatus", "o_orderpriority", "o_orderdate", "o_totalprice", "o_custkey", "c_mktsegment"], Spec(37, 670, high=600, low=0)),
    "part": (part_base, "p_partkey", ["p_name", "p_brand", "p_type", "p_size", "p_retailprice", "colour", "noun", "brand_no", "size_band", "price_band"], Spec(55, 1000, high=450, low=50, trusted=0)),
    "part_vote": (part_base, "p_partkey", ["p_name", "p_brand", "p_type", "p_size", "p_retailprice", "colour", "noun", "brand_no"], Spec(55, 1000, high=600, low=100, salt=7)),
    "part_small": (part_base, "p_partkey", ["p_name", "p_brand", "p_type", "p_size"], Spec(11, 900, high=700, low=300)),
    "customer": (customer_base, "c_custkey", ["c_name", "c_mktsegment", "c_nationkey", "n_name", "r_name", "c_acctbal"], Spec(12, 580, high=700, low=250)),
    "supplier": (supplier_base, "s_suppkey", ["s_name", "s_nationkey", "s_acctbal"], Spec(11, 800, high=700, low=350)),
}


def replicas(spark: SparkSession, sf_dir: str, name: str, salt: int | None = None, limit: int | None = None, keep: tuple[str, ...] | None = None) -> DataFrame:
    """The set over the whole table; over the keys below a limit in tests; of the attributes those in `keep`, if given."""
    base, key, attrs, spec = SETS[name]
    spec = replace(spec, salt=spec.salt if salt is None else salt, limit=limit)
    return make_replicas(base(spark, sf_dir), key, attrs, spec, keep)


def clean(spark: SparkSession, sf_dir: str, name: str, limit: int | None = None) -> DataFrame:
    """(entity_id, attributes as strings) of the clean table."""
    base, key, attrs, _ = SETS[name]
    df = base(spark, sf_dir)
    rows = df if limit is None else df.where(F.col(key) < limit)
    return rows.select(F.col(key).cast("bigint").alias("entity_id"), *[canonical(df, a).alias(a) for a in attrs])


def truth(spark: SparkSession, sf_dir: str, name: str, limit: int | None = None) -> DataFrame:
    """(entity_id, attr, value) of the clean table."""
    return clean(spark, sf_dir, name, limit).unpivot(["entity_id"], SETS[name][2], "attr", "value")
