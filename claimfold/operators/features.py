"""Features of claims at attribute, record and database level; native expressions throughout."""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .claims import CELL

BLOCKS = ("format", "running", "embed", "cooc", "vote", "source", "rules", "neighbour")
#: Asked for by name alone: the naive classifier has nothing else.
EXTRA = ("onehot", "vote_top")
GROUPS = {"attribute": ("format", "running", "embed"), "record": ("cooc", "vote"), "database": ("source", "rules", "neighbour")}


def once(value: Column, f) -> Column:
    """f of a value that is evaluated once however often f names it."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


# -- attribute level -----------------------------------------------------------


def format_map(value: Column, strict_space: bool = False) -> Column:
    """Letters to A, digits to N, the rest to S (only blanks, and others dropped, with strict_space)."""
    mapped = F.regexp_replace(F.regexp_replace(value, r"\p{L}", "A"), r"\p{Nd}", "N")
    if strict_space:
        return F.regexp_replace(F.regexp_replace(mapped, r"[^AN ]", ""), " ", "S")
    return F.regexp_replace(mapped, r"(?s)[^AN]", "S")


def format_ngrams(value: Column, n: int = 2, strict_space: bool = False) -> Column:
    """Counts of all 3 ** n strings of n symbols, in alphabetical order; a look-ahead counts those that overlap."""
    counts = lambda m: F.array(*[F.regexp_count(m, F.lit(f"(?={''.join(g)})")) for g in itertools.product("ANS", repeat=n)])
    return once(format_map(value, strict_space), counts)


def hash_embedding(value: Column, dim: int = 32) -> Column:
    """Character trigrams and tokens of a value, hashed with signs to `dim` numbers of length 1.

    A piece becomes one character that tells its place and sign, and characters are
    counted by string functions, which are compiled where functions over arrays are not.
    """
    if not 1 <= dim <= 64:
        raise ValueError("dim must be from 1 to 64")
    padded = F.concat(F.lit("^"), F.lower(value), F.lit("$"))
    grams = F.concat(F.transform(F.sequence(F.lit(1), F.greatest(F.length(padded) - 2, F.lit(1))), lambda i: F.substring(padded, i, F.lit(3))), F.filter(F.split(F.lower(value), r"[^\p{L}\p{Nd}]+"), lambda t: t != ""))
    codes = F.array_join(F.transform(grams, lambda g: F.char(F.lit(64) + F.pmod(F.xxhash64(g), F.lit(2 * dim)))), "")
    count = lambda v, c: F.length(v) - F.length(F.replace(v, F.lit(chr(64 + c))))
    raw = once(codes, lambda v: F.array(*[(count(v, i) - count(v, i + dim)).cast("double") for i in range(dim)]))
    normed = once(raw, lambda v: F.struct(v.alias("v"), F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x)).alias("n")))
    return once(normed, lambda r: F.transform(r["v"], lambda x: F.when(r["n"] > 0, x / r["n"]).otherwise(0.0)))


def hash_words(value: Column, dim: int = 256) -> Column:
    """Counts of a value's words, in lower case, hashed to `dim` places."""
    words = F.filter(F.split(F.lower(value), r"[^\p{L}\p{Nd}]+"), lambda t: t != "")
    places = F.transform(words, lambda t: F.pmod(F.xxhash64(t), F.lit(dim)))
    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.size(F.filter(places, lambda p: p == i)).cast("double"))


def distance(a: Column, b: Column, kind: str = "l2") -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    if kind == "l2":
        return F.sqrt(F.aggregate(F.zip_with(a, b, lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v))
    if kind == "l1":
        return F.aggregate(F.zip_with(a, b, lambda p, q: F.abs(p - q)), F.lit(0.0), lambda s, v: s + v)
    if kind == "cosine":
        return 1 - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))
    raise ValueError("distance must be l2, l1 or cosine")


def mean_vector(vector: Column, dim: int, over: object | None = None) -> Column:
    """Mean of an array column, as an aggregate or over a window."""
    parts = [F.avg(vector[i]) for i in range(dim)]
    return F.array(*[p.over(over) if over is not None else p for p in parts])


def distance_to_mean(df: DataFrame, keys: list[str], vector: str, dim: int, kind: str = "l2", out: str = "distance") -> DataFrame:
    """Distance of each row's vector to the mean of its group: the group's means are aggregated, then joined."""
    means = df.groupBy(*keys).agg(mean_vector(F.col(vector), dim).alias("_mean"))
    return df.join(means, keys).withColumn(out, distance(F.col(vector), F.col("_mean"), kind)).drop("_mean")


def embed_distance(cells: DataFrame, dim: int = 32, kind: str = "l2") -> DataFrame:
    """Distance of each candidate's embedding to the mean of its cell's (entity, attribute) candidates."""
    return distance_to_mean(cells.withColumn("_e", hash_embedding(F.col("value"), dim)), list(CELL), "_e", dim, kind, "embed").drop("_e")


def word2vec_vectors(cells: DataFrame, dim: int = 16, seed: int = 1, out: str = "vector", sample: int = 100_000) -> DataFrame:
    """Rows with vectors that Word2Vec learns over the character pairs of at most `sample` distinct values, those of the least hashes."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    pairs = F.transform(F.sequence(F.lit(1), F.greatest(F.length("value") - 1, F.lit(1))), lambda i: F.substring(F.col("value"), i, F.lit(2)))
    known = cells.select("value").distinct().orderBy(F.xxhash64("value"), "value").limit(sample)
    model = Word2Vec(vectorSize=dim, minCount=1, seed=seed, maxIter=1, numPartitions=1, inputCol="_w", outputCol="_v").fit(known.select(pairs.alias("_w")))
    return model.transform(cells.withColumn("_w", pairs)).withColumn(out, vector_to_array("_v")).drop("_w", "_v")


def word2vec_distance(cells: DataFrame, dim: int = 16, seed: int = 1, kind: str = "l2") -> DataFrame:
    """The same with embeddings that Word2Vec learns over character pairs of the values."""
    return distance_to_mean(word2vec_vectors(cells, dim, seed, "_e"), list(CELL), "_e", dim, kind, "embed").drop("_e")


def lookup_embedding(df: DataFrame, vectors: DataFrame, on: str) -> DataFrame:
    """Given vectors (on, vector) beside the rows they belong to."""
    return df.join(vectors, on, "left")


def running_flags(cands: DataFrame, labels: DataFrame | None) -> DataFrame:
    """(entity_id, attr, slot, flag): 1 at the slot of the last prediction; all 0 before there is one."""
    base = cands.select(*CELL, "slot")
    if labels is None:
        return base.withColumn("flag", F.lit(0))
    last = labels.select(*CELL, F.col("slot").alias("_last"))
    return base.join(last, list(CELL), "left").withColumn("flag", F.coalesce((F.col("slot") == F.col("_last")).cast("int"), F.lit(0))).drop("_last")


# -- record level --------------------------------------------------------------


def vote_share(claims: DataFrame) -> DataFrame:
    """Share of the cell's claims that have the claim's value; two windows on one exchange."""
    cell = Window.partitionBy(*CELL)
    same = Window.partitionBy(*CELL, "value")
    return claims.withColumn("share", F.count(F.lit(1)).over(same) / F.count(F.lit(1)).over(cell))


def cooccurrence(wide: DataFrame, attrs: list[str], labels: DataFrame | None = None, scope: str = "entity", normalise: bool = True) -> DataFrame:
    """(entity_id, source_id, attr, other, value, ratio): how often a value stands beside another attribute's.

    With labels (entity_id, attr, value) the other attribute's value is the
    predicted one, not the record's.  Ratio: pair count over the count of the
    other value, within the entity or in the whole table; or the pair count.
    """
    if scope not in ("entity", "database"):
        raise ValueError("scope must be 'entity' or 'database'")
    if labels is None:
        both = wide.select("entity_id", "source_id", F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.lit(b).alias("other"), F.col(a).alias("value"), F.col(b).alias("beside")) for a in attrs for b in attrs if a != b])).alias("c")).select("entity_id", "source_id", "c.*")
        key = ["entity_id"] if scope == "entity" else []
        if scope == "entity":
            pair = Window.partitionBy(*key, "attr", "other", "value", "beside")
            alone = Window.partitionBy(*key, "attr", "other", "beside")
            out = both.where("value is not null and beside is not null").withColumn("pairs", F.count(F.lit(1)).over(pair)).withColumn("m", F.count(F.lit(1)).over(alone))
        else:  # whole-table counts may be hot: aggregate with map-side combine, then join
            known = both.where("value is not null and beside is not null")
            pairs = known.groupBy("attr", "other", "value", "beside").agg(F.count(F.lit(1)).alias("pairs"))
            m = pairs.groupBy("attr", "other", "beside").agg(F.sum("pairs").alias("m"))
            out = known.join(pairs.join(m, ["attr", "other", "beside"]), ["attr", "other", "value", "beside"])
        return out.select("entity_id", "source_id", "attr", "other", "value", (F.col("pairs") / F.col("m") if normalise else F.col("pairs")).alias("ratio"))
    # Labels nested by entity: one join, on the entity, and counts of all other attributes side by side.
    said = labels.groupBy("entity_id").agg(*[F.max(F.when(F.col("attr") == b, F.col("value"))).alias(f"_s{i}") for i, b in enumerate(attrs)])
    agree = [F.coalesce(F.col(b) == F.col(f"_s{i}"), F.lit(False)).cast("long").alias(f"_a{i}") for i, b in enumerate(attrs)]
    rows = wide.join(said, "entity_id").select("entity_id", *agree, F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in attrs])).alias("c"))
    pairs = rows.where("c.value is not null").groupBy("entity_id", "c.attr", "c.value").agg(*[F.sum(f"_a{i}").alias(f"_p{i}") for i in range(len(attrs))])
    # The records with a predicted value are those of its own pairs, which its attribute's candidates share out.
    entity = Window.partitionBy("entity_id")
    total = [F.sum(F.when(F.col("attr") == b, F.col(f"_p{i}"))).over(entity).alias(f"_m{i}") for i, b in enumerate(attrs)]
    out = pairs.select("*", *total).select("entity_id", "attr", "value", F.explode(F.array(*[F.struct(F.lit(b).alias("other"), F.col(f"_p{i}").alias("pairs"), F.col(f"_m{i}").alias("m")) for i, b in enumerate(attrs)])).alias("c"))
    ratio = F.col("c.pairs") / F.col("c.m") if normalise else F.col("c.pairs")
    return out.where("c.m > 0 and attr <> c.other").select("entity_id", "attr", "c.other", "value", ratio.alias("ratio"))


# -- database level ------------------------------------------------------------


def source_index(claims: DataFrame, source: str) -> DataFrame:
    """(source, index): a dense number for each source, by name; one row a source."""
    return claims.select(source).distinct().withColumn("index", F.dense_rank().over(Window.orderBy(source)) - 1)


def source_onehot(df: DataFrame, source: str) -> DataFrame:
    """Each row with the index of its source: the sparse form (index, 1) of the one-hot vector."""
    return df.join(F.broadcast(source_index(df, source)), source).withColumn("one", F.lit(1))


def neighbour_distance(df: DataFrame, keys: list[str], row_vector: str, cell_vector: str, dim: int, kind: str = "l2") -> DataFrame:
    """Distance of the joined (row, cell) vector to its group's mean."""
    return distance_to_mean(df.withColumn("_j", F.concat(row_vector, cell_vector)), keys, "_j", dim, kind, "neighbour").drop("_j")
