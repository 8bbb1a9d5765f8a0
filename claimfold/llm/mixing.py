"""Mixing sources to target weights by pivotal dependent rounding, in DataFrame functions only.

Every document of a source should appear target / source_size times.  The whole
part of that is certain; the fractions are rounded together: two fractions meet,
mass moves from one to the other at random until one is 0 or 1, and the other
goes on.  Sums of fractions never change, so a source's words stay close to its
target when fractions of like sizes meet, and when what is left last is small.
Documents are therefore numbered in blocks by size class, the largest first; each
block folds its fractions to one residual, and residuals of neighbouring blocks
fold in a tree of FAN branches a level.  Random
numbers are hashes of the ids that meet, so reruns agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import fresh, settle

WEIGHTS, MOST_TIMES, FAN = (5, 2, 1), 3, 32
#: Rows of the table of (source, size class) up to which it is broadcast; beyond, the join is salted.
BROADCAST_ROWS, SALTS = 100_000, 64
#: Rows of one id are numbered apart in so many classes of their texts.
PARTS = 4096


def word_count(text: Column | str) -> Column:
    """Maximal runs outside ASCII white space; 0 for null."""
    trimmed = F.trim(F.col(text) if isinstance(text, str) else text, F.lit(" \t\n\x0b\x0c\r"))
    return F.when(F.coalesce(trimmed, F.lit("")) == "", F.lit(0)).otherwise(F.size(F.split(trimmed, r"[\x20\x09-\x0D]+"))).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST_TIMES) -> DataFrame:
    """(source, source_size, target) from (source, source_size).

    Weights go to the sources by code point, null last, over and over.  A target
    above `most` times its source is cut there and the excess goes to the others
    by weight, until none is above: the fixed point is one level l with target =
    min(most * size, l * weight), found by one pass over the sources in the order
    in which they reach their bound.  These windows hold one row a source.
    """
    rank = F.row_number().over(Window.orderBy(F.asc_nulls_last("source"))) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (rank % len(weights) + 1).cast("int"))
    ranked = sizes.withColumn("weight", weight).withColumn("bound", F.lit(float(most)) * F.col("source_size")).withColumn("ratio", F.col("bound") / F.col("weight"))
    order = Window.orderBy("ratio", F.asc_nulls_last("source"))
    whole = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (F.sum(F.col("source_size").cast("double")).over(whole) - F.coalesce(F.sum("bound").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))) / F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing))
    levelled = ranked.withColumn("level", level)
    cut = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "level"))).over(whole)["level"]
    return levelled.select("source", "source_size", F.when(F.col("source_size") == 0, 0.0).otherwise(F.least("bound", F.coalesce(cut, F.lit(0.0)) * F.col("weight"))).alias("target"))


def _uniform(*parts: Column) -> Column:
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 53)).cast("double") / F.lit(float(1 << 53))


def fold(units: Column, seed: int) -> Column:
    """Fold an array of (size, id, dup, p) to (id, dup, p, size, done): the residual and what is decided."""
    done = "array<struct<id:bigint,dup:bigint,take:int>>"
    start = F.struct(F.element_at(units, 1)["size"].alias("size"), F.element_at(units, 1)["id"].alias("id"), F.element_at(units, 1)["dup"].alias("dup"), F.element_at(units, 1)["p"].alias("p"), F.array().cast(done).alias("done"))

    def meet(a: Column, b: Column) -> Column:
        both = a["p"] + b["p"]
        u = _uniform(F.lit(seed), a["id"], a["dup"], b["id"], b["dup"])
        low = both < F.lit(1 - 1e-12)
        # Below 1 one side takes all mass and the other gets 0; else one gets 1 and the other the rest.
        a_stays = F.when(low, u * both < a["p"]).otherwise(u * (F.lit(2.0) - both) >= F.lit(1.0) - b["p"])
        rest = F.when(low, both).otherwise(F.greatest(both - 1, F.lit(0.0)))
        take = F.when(low, 0).otherwise(1)
        pick = lambda c: F.when(a_stays, a[c]).otherwise(b[c])
        drop = lambda c: F.when(a_stays, b[c]).otherwise(a[c])
        return F.struct(pick("size").alias("size"), pick("id").alias("id"), pick("dup").alias("dup"), rest.alias("p"), F.concat(a["done"], F.array(F.struct(drop("id").alias("id"), drop("dup").alias("dup"), take.alias("take")))).cast(done).alias("done"))

    return F.aggregate(F.slice(units, F.lit(2), F.size(units)), start, meet)


def round_together(units: DataFrame, seed: int = 0) -> DataFrame:
    """(id, dup, take 0/1) for (source, number, size, id, dup, p), 0 < p < 1.

    number is the block of a unit within its source, 0 to n - 1.
    """
    most = units.agg(F.max("number")).first()[0]
    if most is None:
        return units.select("id", "dup", F.lit(0).alias("take"))
    decided, level = None, units.select("source", "number", "size", "id", "dup", "p")
    while True:
        folded = level.groupBy("source", "number").agg(F.sort_array(F.collect_list(F.struct("size", "id", "dup", "p")), asc=False).alias("units")).select("source", "number", fold(F.col("units"), seed).alias("f"))
        folded = settle(folded.select("source", "number", "f.*"), "mixing-level")
        done = folded.select(F.explode("done").alias("d")).select("d.*")
        decided = done if decided is None else decided.union(done)
        if most == 0:
            return decided.union(folded.select("id", "dup", (_uniform(F.lit(seed + 1), F.col("id"), F.col("dup")) < F.col("p")).cast("int")))
        most //= FAN
        level = folded.select("source", F.floor(F.col("number") / FAN).cast("long").alias("number"), "size", "id", "dup", "p")


def _numbered(docs: DataFrame, id: str, text: str, source: str) -> tuple[DataFrame, dict[str, str]]:
    """docs with an id as a number, source, size and dup, under names that clash with none; and these names.

    dup tells rows that share an id apart: a number within the id and one of PARTS
    hashes of the text, so rows without an id don't meet in one task.  Rows equal in all of
    this are interchangeable.
    """
    names = {c: fresh(docs, f"_mix_{c}") for c in ("id", "source", "size", "part", "print", "dup")}
    n = names
    out = docs.withColumns({n["id"]: F.col(f"`{id}`").cast("long"), n["source"]: F.col(f"`{source}`").cast("string"), n["size"]: word_count(F.col(f"`{text}`")), n["print"]: F.xxhash64(F.col(f"`{text}`"))})
    out = out.withColumn(n["part"], F.pmod(F.col(n["print"]), F.lit(PARTS)))
    number = F.row_number().over(Window.partitionBy(n["id"], n["part"]).orderBy(n["source"], n["size"], n["print"]))
    return out.withColumn(n["dup"], F.col(n["part"]) * F.lit(1 << 32) + number), names


def mix(docs: DataFrame, id: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[int, ...] = WEIGHTS, most: int = MOST_TIMES, seed: int = 0) -> DataFrame:
    """(id, dup, source, size, source_size, target, copies, taken) for every row of docs.

    taken = copies * size.  dup tells rows that share an id apart.  Documents
    without words take nothing; an empty table gives no rows.  Null sources are
    one source, null ids are ids like others; ties are settled by hashes of id and dup.
    """
    rows, n = _numbered(docs, id, text, source)
    slim = settle(rows.select(*[F.col(n[c]).alias(c) for c in ("id", "dup", "source", "size")]), "mixing-sizes")
    aimed = targets(slim.groupBy("source").agg(F.sum("size").alias("source_size")), weights, most)
    # Size classes: two to a doubling.  Blocks of FAN documents or so, numbered by class within the source.
    classed = slim.withColumn("class", F.when(F.col("size") > 0, F.floor(2 * F.log2(F.col("size").cast("double")))).otherwise(-1).cast("int"))
    cells = classed.groupBy("source", "class").agg(F.count(F.lit(1)).alias("n")).withColumn("blocks", F.ceil(F.col("n") / FAN).cast("long"))
    before = F.sum("blocks").over(Window.partitionBy("source").orderBy(F.desc("class")).rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("blocks")
    a, c = aimed.alias("a"), cells.withColumn("before", before).alias("c")
    cells = settle(c.join(a, F.expr("a.source <=> c.source")).select("c.source", "class", "blocks", "before", "source_size", "target"), "mixing-cells")
    if cells.count() <= BROADCAST_ROWS:
        c, d = F.broadcast(cells).alias("c"), classed.alias("d")
        joined = d.join(c, F.expr("d.source <=> c.source and d.class = c.class"))
    else:
        c = cells.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))).alias("c")
        d = classed.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int")).alias("d")
        joined = d.join(c, F.expr("d.source <=> c.source and d.class = c.class and d.salt = c.salt"))
    share = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(most)))).otherwise(0.0)
    share = joined.select("d.id", "dup", "d.source", "size", "source_size", "target", share.alias("share"), (F.col("before") + F.pmod(F.xxhash64(F.lit(seed), "d.id", "dup"), F.col("blocks"))).alias("number"))
    share = share.withColumn("whole", F.floor(F.col("share") + 1e-12)).withColumn("p", F.col("share") - F.col("whole"))
    open_ = "size > 0 and p > 1e-12"
    took = round_together(share.where(open_), seed).alias("t")
    s = share.alias("s")
    out = s.join(took, F.expr("s.id <=> t.id and s.dup = t.dup"), "left")
    copies = F.when(F.col("size") > 0, F.col("whole") + F.coalesce("take", F.lit(0))).otherwise(0).cast("long")
    return out.select(F.col("s.id").alias(id), "s.dup", "s.source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))


def sample(docs: DataFrame, id: str = "doc_id", text: str = "text", source: str = "source", weights: tuple[int, ...] = WEIGHTS, most: int = MOST_TIMES, seed: int = 0) -> DataFrame:
    """The rows of docs as the mix takes them: each as often as its copies, all columns as they are."""
    chosen = mix(docs, id, text, source, weights, most, seed)
    rows, n = _numbered(docs, id, text, source)
    taken = chosen.where("copies > 0").select(F.col(id).alias("i"), F.col("dup").alias("d"), F.col("copies").cast("int").alias("c")).alias("taken")
    joined = rows.alias("rows").join(taken, F.expr(f"rows.`{n['id']}` <=> taken.i and rows.`{n['dup']}` = taken.d"))
    return joined.select(*[F.col(f"rows.`{c}`") for c in docs.columns], F.explode(F.sequence(F.lit(1), F.col("taken.c"))).alias(fresh(docs, "_time"))).select(*[F.col(f"`{c}`") for c in docs.columns])
