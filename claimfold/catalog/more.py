"""Queries of the natural workloads, of numeric answers and of the remaining measures, each with SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators import baselines, claims, infer, measure
from ..sources.replicas import truth
from ..sources.tables import table
from . import text
from .batch import CELL, r6, rep_claims, weather_wide
from .batch import _BEST as BEST
from .batch import _C as CUSTOMER
from .batch import _SUP as SUPPLIER
from .batch import _WEATHER as WEATHER

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str):
    def add(f):
        QUERIES[f.__name__], SQL[f.__name__] = f, sql
        return f

    return add


# -- natural workloads -------------------------------------------------------------------

#: Attributes of line items as claims about a part, and the same as SQL strings.
LINE = {
    "l_returnflag": "l_returnflag", "l_linestatus": "l_linestatus", "l_quantity": "CAST(CAST(l_quantity AS DECIMAL(18,2)) AS VARCHAR)", "l_discount": "CAST(CAST(l_discount AS DECIMAL(18,2)) AS VARCHAR)",
    "l_tax": "CAST(CAST(l_tax AS DECIMAL(18,2)) AS VARCHAR)", "l_linenumber": "CAST(l_linenumber AS VARCHAR)", "ship_year": "CAST(year(l_shipdate) AS VARCHAR)", "ship_month": "CAST(month(l_shipdate) AS VARCHAR)",
}
_LINE = " UNION ALL ".join(f"SELECT l_partkey AS entity_id, CAST(l_suppkey AS INTEGER) AS source_id, '{a}' AS attr, {e} AS value FROM lineitem" for a, e in LINE.items())
_AGREE = "SELECT t.attr, count(*) AS n, round(avg(CASE WHEN t.value = a.value THEN 1.0 ELSE 0.0 END), 6) AS precision FROM {t} t JOIN {a} a ON a.entity_id = t.entity_id AND a.attr = t.attr WHERE t.slot = 0 GROUP BY t.attr"


def lineitem_claims(spark, d):
    li = table(spark, d, "lineitem").withColumns({"ship_year": F.year("l_shipdate"), "ship_month": F.month("l_shipdate"), "_s": F.col("l_suppkey").cast("int")})
    return claims.to_claims(li, "l_partkey", list(LINE), "_s").select("entity_id", "source_id", "attr", "value")


@query(f"WITH claims AS ({_LINE}), {text.cand_cte()}, few AS (SELECT * FROM claims WHERE source_id < 5), {text.cand_cte('few', 'truth')} " + _AGREE.format(t="truth", a="(SELECT * FROM cand WHERE slot = 0)"))
def lineitem_natural_precision(spark, d):
    """Line items as they are: the vote of all suppliers against that of five named ones."""
    c = lineitem_claims(spark, d)
    known = claims.vote_labels(claims.candidates(c.where("source_id < 5")))
    return measure.precision(baselines.majority_vote(c), known, by=("attr",)).withColumn("precision", r6("precision"))


_W = f"w AS ({WEATHER}), claims AS (SELECT entity_id, source_id, 'event_type' AS attr, event_type AS value FROM w UNION ALL SELECT entity_id, source_id, 'band', band FROM w UNION ALL SELECT entity_id, source_id, 'hour', hour FROM w)"


@query(f"WITH {_W}, {text.cand_cte()}, any_ AS (SELECT entity_id, attr, max(value) AS value FROM claims GROUP BY ALL) " + _AGREE.format(t="cand", a="any_"))
def weather_heuristic_precision(spark, d):
    """Events as they are: the greatest value against the vote of all sources."""
    c = weather_wide(spark, d).unpivot(["entity_id", "source_id"], ["event_type", "band", "hour"], "attr", "value")
    known = claims.vote_labels(claims.candidates(c))
    return measure.precision(baselines.heuristic(c, "max"), known, by=("attr",)).withColumn("precision", r6("precision"))


_WORDS = "regexp_extract_all(lower({c}), '[a-z0-9]+')"


@query(
    f"WITH b AS (SELECT item_id, {_WORDS.format(c='text')} AS w FROM benchmark), bw AS (SELECT item_id, array_to_string(w[p:p + 12], ' ') AS k FROM (SELECT item_id, w, unnest(range(1, len(w) - 11)) AS p FROM b WHERE len(w) >= 13)), "
    f"d AS (SELECT doc_id, {_WORDS.format(c='text')} AS w FROM documents), dw AS (SELECT DISTINCT doc_id, array_to_string(w[p:p + 12], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS p FROM d WHERE len(w) >= 13)) "
    "SELECT item_id, count(DISTINCT doc_id) AS documents, count(DISTINCT k) AS windows FROM bw JOIN dw USING (k) GROUP BY item_id"
)
def benchmark_passages(spark, d):
    """Windows of 13 words of each benchmark item that documents hold word by word."""

    def windows(df, id):
        words = F.regexp_extract_all(F.lower("text"), F.lit("[a-z0-9]+"), F.lit(0))
        rows = df.select(id, words.alias("w")).where(F.size("w") >= 13)
        return rows.select(id, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 12), lambda p: F.array_join(F.slice("w", p, F.lit(13)), " ")))).alias("k"))

    both = windows(table(spark, d, "benchmark"), "item_id").join(windows(table(spark, d, "documents"), "doc_id"), "k")
    return both.groupBy("item_id").agg(F.count_distinct("doc_id").alias("documents"), F.count_distinct("k").alias("windows"))


# -- numeric answers ---------------------------------------------------------------------


@query(
    f"WITH {CUSTOMER}, num AS (SELECT *, CASE WHEN attr = 'c_acctbal' THEN CAST(value AS DOUBLE) END AS x FROM claims), {text.cand_cte()}, "
    "m AS (SELECT entity_id, attr, CAST(CAST(avg(x) AS DECIMAL(38,6)) AS DOUBLE) AS m, var_pop(x) AS v FROM num WHERE x IS NOT NULL GROUP BY ALL), "
    "lost AS (SELECT c.source_id, count(*) AS n, sum(CASE WHEN c.x IS NULL THEN (CASE WHEN c.value <> t.value THEN 1.0 ELSE 0.0 END) WHEN m.v > 0 THEN (c.x - m.m) * (c.x - m.m) / m.v ELSE 0.0 END) AS loss FROM num c LEFT JOIN cand t ON t.entity_id = c.entity_id AND t.attr = c.attr AND t.slot = 0 LEFT JOIN m ON m.entity_id = c.entity_id AND m.attr = c.attr GROUP BY c.source_id), "
    "w AS (SELECT source_id, n * power(1 - 2 / (9.0 * n) - 1.959963984540054 * sqrt(2 / (9.0 * n)), 3) / (loss + 1e-6) AS w FROM lost) "
    "SELECT entity_id, attr, round(sum(x * w) / sum(w), 2) AS mean FROM num JOIN w USING (source_id) WHERE x IS NOT NULL GROUP BY entity_id, attr"
)
def interval_weighted_mean(spark, d):
    """Weighted means of a numeric attribute after one round, its losses being squared distances."""
    out = baselines.interval_weighted_vote(rep_claims(spark, d, "customer"), iters=1, exact=False, numeric=("c_acctbal",))
    return out.where("attr = 'c_acctbal'").select(*CELL, F.round(F.col("value").cast("double"), 2).alias("mean"))


# -- measures ----------------------------------------------------------------------------

_SHARES = f"{SUPPLIER}, pr AS (SELECT entity_id, attr, value, slot, support / sum(support) OVER (PARTITION BY entity_id, attr) AS p FROM cand), y AS (SELECT pr.*, CASE WHEN pr.value = t.value THEN 1.0 ELSE 0.0 END AS y FROM pr JOIN truth t ON t.entity_id = pr.entity_id AND t.attr = pr.attr)"


def _shares(spark, d):
    c = claims.candidates(rep_claims(spark, d, "supplier"))
    return c.withColumn("p", F.col("support") / F.sum("support").over(Window.partitionBy(*CELL)))


@query(f"WITH {_SHARES}, b AS (SELECT CAST(least(floor(p * 10), 9) AS INTEGER) AS bin, count(*) AS n, avg(p) AS confidence, avg(y) AS accuracy FROM y GROUP BY 1) SELECT round(sum(n * abs(confidence - accuracy)) / sum(n), 6) AS ece FROM b")
def calibration_error(spark, d):
    return measure.calibration_error(measure.calibration(_shares(spark, d), truth(spark, d, "supplier"))).withColumn("ece", r6("ece"))


@query(f"WITH {_SHARES} SELECT entity_id, attr, value, round(p, 6) AS p FROM pr")
def vote_distributions(spark, d):
    """The distribution over a cell's values, from vote shares."""
    return infer.distributions(_shares(spark, d)).select(*CELL, F.explode("dist").alias("value", "p")).withColumn("p", r6("p"))


@query(
    f"WITH {CUSTOMER}, {text.cand_cte()}, a AS (SELECT c.attr AS workload, 'vote' AS method, avg(CASE WHEN c.value = t.value THEN 1.0 ELSE 0.0 END) AS p FROM cand c JOIN truth t USING (entity_id, attr) WHERE slot = 0 GROUP BY 1 "
    "UNION ALL SELECT c.attr, 'min', avg(CASE WHEN c.value = t.value THEN 1.0 ELSE 0.0 END) FROM (SELECT entity_id, attr, min(value) AS value FROM claims GROUP BY ALL) c JOIN truth t USING (entity_id, attr) GROUP BY 1 "
    "UNION ALL SELECT c.attr, 'max', avg(CASE WHEN c.value = t.value THEN 1.0 ELSE 0.0 END) FROM (SELECT entity_id, attr, max(value) AS value FROM claims GROUP BY ALL) c JOIN truth t USING (entity_id, attr) GROUP BY 1) "
    "SELECT workload, round(max(CASE WHEN method = 'vote' THEN p END), 6) AS ours, round(max(CASE WHEN method <> 'vote' THEN p END), 6) AS best_rival, round(100 * (max(CASE WHEN method = 'vote' THEN p END) - max(CASE WHEN method <> 'vote' THEN p END)), 6) AS points FROM a GROUP BY workload"
)
def improvement_points(spark, d):
    """Points of the vote over the better of two heuristics, by attribute."""
    c, t = rep_claims(spark, d, "customer"), truth(spark, d, "customer")
    rows = None
    for name, got in (("vote", baselines.majority_vote(c)), ("min", baselines.heuristic(c, "min")), ("max", baselines.heuristic(c, "max"))):
        one = measure.precision(got, t, by=("attr",)).select(F.col("attr").alias("workload"), F.lit(name).alias("method"), "precision")
        rows = one if rows is None else rows.unionByName(one)
    return measure.improvement(rows, "vote").select("workload", *[r6(x).alias(x) for x in ("ours", "best_rival", "points")])


@query(f"WITH {SUPPLIER}, sc AS (SELECT entity_id, attr, value, CAST(support AS DOUBLE) AS score FROM cand) " + BEST.format(score="score", src="sc"))
def best_scores(spark, d):
    return baselines.best(claims.candidates(rep_claims(spark, d, "supplier")).select(*CELL, "value", F.col("support").cast("double").alias("score")))
