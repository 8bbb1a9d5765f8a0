"""Denial constraints: parsed, validated, and planned by their shape.

A rule is not(p1 and p2 and ...) over tuples t1, t2, ...; the result is, for each
record, with how many other records (or combinations) it breaks the rule.
Equality with one inequality becomes a difference of two counts, pure order
becomes counting inversions; only rules with an equality key are joined, so no
plan is a cross product.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

#: Rows that a task of an order rule gets, of as many whole blocks as fit.
GROUP_ROWS = 500_000

_OPS = ("!=", "<=", ">=", "=", "<", ">")
_TERM = re.compile(r"\s*(?:(t\d+)\.(\w+)|('(?:[^']|'')*')|(-?\d+(?:\.\d+)?))\s*")
_FLIP = {"=": "=", "!=": "!=", "<": ">", ">": "<", "<=": ">=", ">=": "<="}


class RuleError(ValueError):
    pass


@dataclass(frozen=True)
class Term:
    """An attribute of a tuple, or a constant."""

    tuple: int = 0
    column: str = ""
    constant: object = None


@dataclass(frozen=True)
class Predicate:
    left: Term
    op: str
    right: Term


@dataclass(frozen=True)
class Rule:
    rule_id: str
    predicates: tuple[Predicate, ...]
    tuples: int

    def columns(self) -> set[str]:
        return {t.column for p in self.predicates for t in (p.left, p.right) if t.tuple}


def _term(text: str) -> Term:
    m = _TERM.fullmatch(text)
    if not m:
        raise RuleError(f"no attribute and no constant: {text!r}")
    if m[1]:
        return Term(int(m[1][1:]), m[2])
    return Term(constant=m[3][1:-1].replace("''", "'") if m[3] else float(m[4]) if "." in m[4] else int(m[4]))


def parse_rule(text: str, columns: list[str] | None = None, rule_id: str = "") -> Rule:
    """Read not(t1.a = t2.a and ...); columns, if given, are those that may occur."""
    m = re.fullmatch(r"\s*not\s*\((.*)\)\s*", text, re.S | re.I)
    if not m:
        raise RuleError("a rule has the form not(p and p and ...)")
    found = []
    for part in re.split(r"\s+and\s+(?=(?:[^']*'[^']*')*[^']*$)", m[1], flags=re.I):
        cut = re.match(r"((?:[^'!=<>]|'(?:[^']|'')*')+)(!=|<=|>=|=|<|>)(.+)$", part, re.S)
        if not cut:
            raise RuleError(f"no comparison: {part!r}")
        left, op, right = _term(cut[1]), cut[2], _term(cut[3])
        if not left.tuple and not right.tuple:
            raise RuleError(f"a comparison of two constants: {part!r}")
        if not left.tuple:
            left, op, right = right, _FLIP[op], left
        found.append(Predicate(left, op, right))
    used = {t.tuple for p in found for t in (p.left, p.right) if t.tuple}
    n = max(used)
    if used != set(range(1, n + 1)):
        raise RuleError("tuples must be numbered from t1 without gaps")
    unknown = {t.column for p in found for t in (p.left, p.right) if t.tuple} - set(columns or [])
    if columns is not None and unknown:
        raise RuleError(f"no such column: {sorted(unknown)}")
    return Rule(rule_id or text, tuple(found), n)


def rules_on(rules: list[Rule], column: str) -> list[Rule]:
    return [r for r in rules if column in r.columns()]


def rules_frame(spark, rules: list[Rule]) -> DataFrame:
    show = lambda t: f"t{t.tuple}.{t.column}" if t.tuple else repr(t.constant)
    rows = [(r.rule_id, r.tuples, [(show(p.left), p.op, show(p.right)) for p in r.predicates]) for r in rules]
    return spark.createDataFrame(rows, "rule_id string, tuple_vars int, predicates array<struct<left:string,op:string,right:string>>")


def _compare(a: Column, op: str, b: Column) -> Column:
    return {"=": a == b, "!=": a != b, "<": a < b, ">": a > b, "<=": a <= b, ">=": a >= b}[op]


def _holds(p: Predicate, of: dict[int, str]) -> Column:
    side = lambda t: F.col(f"{of[t.tuple]}{t.column}") if t.tuple else F.lit(t.constant)
    return _compare(side(p.left), p.op, side(p.right))


def violations(df: DataFrame, rule: Rule, id: str, small_blocks: bool = False) -> DataFrame:
    """(id, n): for every record, the partners (or tuples of partners) with which it breaks the rule.

    A comparison with null holds never.  Rules of two or more tuples need an
    equality between them, or must be of pure order (one comparison either way);
    others are refused, not nested.  With small_blocks the records of equal keys
    are few (those of an entity, say): counts of equal keys are made where they lie.
    """
    unknown = rule.columns() - set(df.columns)
    if unknown:
        raise RuleError(f"no such column: {sorted(unknown)}")
    need = df.select(id, *sorted(rule.columns() - {id}))
    if rule.tuples == 1:
        bad = F.lit(True)
        for p in rule.predicates:
            bad &= _holds(p, {1: ""})
        return need.select(id, F.coalesce(bad, F.lit(False)).cast("long").alias("n"))
    if rule.tuples == 2:
        shape = _shape(rule)
        if shape:
            kind, *rest = shape
            if kind == "fd" and small_blocks:
                return _fd(need, rule, id, *rest, in_place=True)
            return {"fd": _fd, "dominance": _dominance, "inversion": _inversion}[kind](need, rule, id, *rest)
    return _joined(need, rule, id)


def violations_against(df: DataFrame, partners: DataFrame, rule: Rule, id: str, own: str) -> DataFrame:
    """(id, n): for every record, the rows of `partners` (one an entity) with which it breaks the rule; its own entity's row aside.

    `own` names the entity in both.  Rules of one tuple ask the record alone; of two tuples those with an
    equality between them are taken, equalities and one inequality as a difference of counts; others are refused.
    """
    if rule.tuples == 1:
        return violations(df, rule, id)
    if rule.tuples != 2:
        raise RuleError("partners that are predicted are for rules of one or two tuples")
    columns = sorted(rule.columns() - {id, own})
    keys, _, _ = _split(rule)
    if not keys:
        raise RuleError("no equality links the tuples: the plan would be a cross product")
    need = df.select(id, own, *columns)
    shape = _shape(rule)
    if shape and shape[0] == "fd" and not shape[3] and not shape[4] and own not in rule.columns():
        on, column = shape[1], shape[2]
        known = F.col(column).isNotNull()
        for k in on:
            known &= F.col(k).isNotNull()
        by_value = partners.where(known).groupBy(*on, column).agg(F.count(F.lit(1)).alias("_v"))
        by_key = by_value.groupBy(*on).agg(F.sum("_v").alias("_k"))
        mine = partners.where(known).select(own, *[F.col(c).alias(f"_own_{c}") for c in [*on, column]])
        rows = need.join(by_value, [*on, column], "left").join(by_key, on, "left").join(mine, own, "left")
        same = F.col(f"_own_{column}") != F.col(column)
        for k in on:
            same &= F.col(f"_own_{k}") == F.col(k)
        n = F.coalesce("_k", F.lit(0)) - F.coalesce("_v", F.lit(0)) - F.coalesce(same.cast("long"), F.lit(0))
        return rows.select(id, F.when(known, n).otherwise(0).cast("long").alias("n"))
    a, b = need.toDF(*[f"a_{c}" for c in need.columns]), partners.select(own, *columns).toDF(f"b_{own}", *[f"b_{c}" for c in columns])
    first, second = F.lit(True), F.lit(True)
    for p in rule.predicates:
        first &= _holds(p, {1: "a_", 2: "b_"})
        second &= _holds(p, {1: "b_", 2: "a_"})
    on = F.col(f"a_{own}") != F.col(f"b_{own}")
    for k in keys:
        on &= F.col(f"a_{k.left.column}") == F.col(f"b_{k.left.column}")
    counted = a.join(b, on & (first | second)).groupBy(F.col(f"a_{id}").alias(id)).agg(F.count(F.lit(1)).alias("n"))
    return need.select(id).join(counted, id, "left").select(id, F.coalesce("n", F.lit(0)).alias("n"))


def _split(rule: Rule):
    """Equalities of one column across, conditions on single tuples, the rest."""
    keys, single, rest = [], [], []
    for p in rule.predicates:
        if p.right.tuple and p.left.tuple != p.right.tuple:
            (keys if p.op == "=" and p.left.column == p.right.column else rest).append(p)
        else:
            single.append(p)
    return keys, single, rest


def _shape(rule: Rule):
    keys, single, rest = _split(rule)
    crossed = [p if p.left.tuple == 1 else Predicate(p.right, _FLIP[p.op], p.left) for p in rest]
    same = all(p.left.column == p.right.column for p in crossed)
    one = {(p.left.column, p.op, p.right.constant) for p in single if p.left.tuple == 1}
    two = {(p.left.column, p.op, p.right.constant) for p in single if p.left.tuple == 2}
    if keys and len(rest) == 1 and same and rest[0].op == "!=" and (one == two or not one or not two) and not any(p.right.tuple for p in single):
        return "fd", [p.left.column for p in keys], rest[0].left.column, sorted(one, key=str), sorted(two, key=str)
    if len(rest) == 2 and same and not single and all(p.op in "<>" for p in crossed):
        ops = [p.op for p in crossed]
        columns = [p.left.column for p in crossed]
        return ("dominance" if keys else "inversion"), [p.left.column for p in keys], columns, ops
    return None


def _fd(df: DataFrame, rule: Rule, id: str, keys: list[str], column: str, one: list, two: list, in_place: bool = False) -> DataFrame:
    """Partners of equal keys and another value: count(keys) - count(keys, column); no self-join.  In place: by windows, with no exchange if rows of equal keys lie together."""

    def side(conditions) -> Column:
        out = F.lit(True)
        for c, op, k in conditions:
            out &= _compare(F.col(c), op, F.lit(k))
        return F.coalesce(out, F.lit(False))

    known = F.col(column).isNotNull()
    for k in keys:
        known &= F.col(k).isNotNull()
    rows = df.withColumn("_a", side(one) & known).withColumn("_b", side(two) & known)
    if in_place:
        of = {"v": Window.partitionBy(*keys, column), "k": Window.partitionBy(*keys)}
        counted = rows.select("*", *[F.sum(F.col(f"_{x}").cast("long")).over(w).alias(f"_{c}{x}") for c, w in of.items() for x in "ab"])
    else:
        by_value = rows.where("_a or _b").groupBy(*keys, column).agg(F.sum(F.col("_a").cast("long")).alias("_va"), F.sum(F.col("_b").cast("long")).alias("_vb"))
        by_key = by_value.groupBy(*keys).agg(F.sum("_va").alias("_ka"), F.sum("_vb").alias("_kb"))
        counted = rows.join(by_value.join(by_key, keys), [*keys, column], "left")  # the rows move once
    # A record is t1 beside the t2s of its key, and t2 beside the t1s; both at once count a partner once.
    as_one, as_two = F.col("_kb") - F.col("_vb"), F.col("_ka") - F.col("_va")
    symmetric = not one and not two or set(one) == set(two)
    n = F.when(F.col("_a"), as_one).otherwise(0) if symmetric else F.when(F.col("_a") & F.col("_b"), F.greatest(as_one, as_two)).when(F.col("_a"), as_one).when(F.col("_b"), as_two).otherwise(0)
    return counted.select(id, F.coalesce(n, F.lit(0)).cast("long").alias("n"))


def _count_below(x: np.ndarray, y: np.ndarray, block: np.ndarray | None = None) -> np.ndarray:
    """For each point, how many of its block have a smaller x and a smaller y.

    In the order of (block, x, falling y) these are the earlier points of a smaller
    rank, where ranks fall with the block; they are counted level by level of the
    places' bits: each right half looks at the left half beside it.
    """
    n = len(x)
    block = np.zeros(n, dtype=np.int64) if block is None else block
    order = np.lexsort((-y, x, block))
    place = np.empty(n, dtype=np.int64)
    place[order] = np.arange(n)
    by_rank = place[np.lexsort((-place, y, -block))]  # of equal ranks the later place first: it isn't smaller
    below, out = np.zeros(n, dtype=np.int64), np.empty(n, dtype=np.int64)
    for level in range(max(n - 1, 0).bit_length()):
        pair = by_rank >> (level + 1)
        at = by_rank[np.argsort(pair, kind="stable")]
        left = 1 - (at >> level & 1)
        seen = np.cumsum(left) - ((at >> (level + 1)) << level)  # the pairs before have whole left halves
        below[at] += np.where(left == 1, 0, seen)
    out[order] = below
    return out


def _number(df: DataFrame, c: str) -> Column:
    kind = df.schema[c].dataType
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        return F.unix_micros(F.col(c).cast("timestamp")).cast("double")
    if not isinstance(kind, T.NumericType):
        raise RuleError(f"order rules need numbers or times: {c}")
    return F.col(c).cast("double")


def _known(df: DataFrame, columns: list[str]) -> Column:
    """Rows that can break a rule of order: no null and no NaN in the columns."""
    out = F.lit(True)
    for c in columns:
        out &= F.col(c).isNotNull()
        if isinstance(df.schema[c].dataType, (T.DoubleType, T.FloatType)):
            out &= ~F.isnan(c)
    return out


def _dominance(df: DataFrame, rule: Rule, id: str, keys: list[str], columns: list[str], ops: list[str]) -> DataFrame:
    """Two order comparisons within blocks of equal keys; a task counts many blocks at once.  Records that share an id have a row each."""
    rows = df.select(F.col(id).cast("long").alias("_id"), *[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], _number(df, columns[0]).alias("_x"), _number(df, columns[1]).alias("_y"))
    sx, sy = (1 if ops[0] == "<" else -1), (1 if ops[1] == "<" else -1)

    names = [f"_k{i}" for i in range(len(keys))]

    def count(t: pa.Table) -> pa.Table:
        known = t.column("_known").to_numpy()
        n, whole = np.zeros(len(known), dtype=np.int64), t.filter(pa.array(known))
        x, y = whole.column("_x").to_numpy() * sx, whole.column("_y").to_numpy() * sy
        block = np.zeros(len(x), dtype=np.int64)
        for k in names:
            code = whole.column(k).combine_chunks().dictionary_encode()
            code = code.combine_chunks() if isinstance(code, pa.ChunkedArray) else code
            block = np.unique(block * (len(code.dictionary) + 1) + code.indices.to_numpy(), return_inverse=True)[1]
        n[known] = _count_below(x, y, block) + _count_below(-x, -y, block)
        return pa.table({"_id": t.column("_id"), "n": pa.array(n)})

    groups = max(1, -(-rows.count() // GROUP_ROWS))
    # Records that break nothing go along, spread by their ids: a join back on the id would pair those that share one.
    marked = rows.withColumn("_known", _known(rows, [*names, "_x", "_y"]))
    dealt = marked.withColumn("_group", F.pmod(F.when(F.col("_known"), F.xxhash64(*names)).otherwise(F.xxhash64("_id")), F.lit(groups)))
    return dealt.groupBy("_group").applyInArrow(count, "_id long, n long").select(F.col("_id").alias(id), "n")


def _inversion(df: DataFrame, rule: Rule, id: str, keys: list[str], columns: list[str], ops: list[str], blocks: int = 64) -> DataFrame:
    """Two order comparisons over the whole table: pairs within a range of x point by point, pairs of ranges by counts.

    x is cut into ranges at quantiles, and so is y.  Records of other x ranges
    and other y ranges are counted from a small table; those of another x range
    but the same y range, and of the same x range, meet in their range's task.
    """
    rows = df.select(F.col(id).cast("long").alias("_id"), (_number(df, columns[0]) * (1 if ops[0] == "<" else -1)).alias("_x"), (_number(df, columns[1]) * (1 if ops[1] == "<" else -1)).alias("_y"))
    known = _known(rows, ["_x", "_y"])
    whole = rows.where(known)
    cuts = whole.select(F.percentile_approx("_x", [i / blocks for i in range(1, blocks)], 10000).alias("x"), F.percentile_approx("_y", [i / blocks for i in range(1, blocks)], 10000).alias("y")).first()
    cut = lambda c, at: F.size(F.filter(F.array(*[F.lit(float(v)) for v in sorted(set(at or []))]), lambda v: v < c)) if at else F.lit(0)
    ranged = whole.withColumn("_bx", cut(F.col("_x"), cuts["x"])).withColumn("_by", cut(F.col("_y"), cuts["y"]))
    cells = ranged.groupBy("_bx", "_by").count()
    a, b = cells.alias("a"), F.broadcast(cells).alias("b")  # blocks ** 2 rows at most
    far = a.join(b, F.expr("(b._bx < a._bx and b._by < a._by) or (b._bx > a._bx and b._by > a._by)"), "left").groupBy("a._bx", "a._by").agg(F.coalesce(F.sum("b.count"), F.lit(0)).alias("far"))

    def count(only_other: str | None):
        def run(t: pa.Table) -> pa.Table:
            x, y = t.column("_x").to_numpy(), t.column("_y").to_numpy()
            n = _count_below(x, y) + _count_below(-x, -y)
            if only_other:  # leave out what the other grouping counts
                block = t.column(only_other).to_numpy().astype(np.int64)
                n -= _count_below(x, y, block) + _count_below(-x, -y, block)
            return pa.table({"_id": t.column("_id"), "_x": t.column("_x"), "_y": t.column("_y"), "n": pa.array(n), "m": pa.array(np.zeros(len(n), dtype=np.int64))})

        return run

    schema = "_id long, _x double, _y double, n long, m long"

    same_x = ranged.groupBy("_bx").applyInArrow(count(None), schema)
    same_y = ranged.groupBy("_by").applyInArrow(count("_bx"), schema)
    far = ranged.join(F.broadcast(far), ["_bx", "_by"]).select("_id", "_x", "_y", F.col("far").alias("n"), F.lit(1).cast("long").alias("m"))
    # Records that share an id and a place have the same count, and a row each.
    total = same_x.union(same_y).union(far).groupBy("_id", "_x", "_y").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))
    each = total.select("_id", F.explode(F.expr("array_repeat(n div m, cast(m as int))")).alias("n"))
    return each.union(rows.where(~known).select("_id", F.lit(0).cast("long"))).select(F.col("_id").alias(id), "n")


def _joined(df: DataFrame, rule: Rule, id: str) -> DataFrame:
    """Chains of equi-joins in the order of the tuples; each record counts the sets of records that it is in.

    Records that are equal in the rule's columns can stand for each other: classes of them are joined,
    and a set of classes has as many sets of records as members can be drawn from its classes.
    """
    columns = sorted(rule.columns())
    classes = df.groupBy(*columns).agg(F.count(F.lit(1)).alias("_n"))
    side = lambda k: classes.toDF(*[f"t{k}_{c}" for c in classes.columns])
    joined, bound = side(1), {1}
    todo = list(rule.predicates)
    while len(bound) < rule.tuples:
        nxt = next((k for k in range(1, rule.tuples + 1) if k not in bound and any(p.op == "=" and {p.left.tuple, p.right.tuple} & bound and k in (p.left.tuple, p.right.tuple) for p in todo)), None)
        if nxt is None:
            raise RuleError("no equality links the tuples: the plan would be a cross product")
        bound.add(nxt)
        of = {k: f"t{k}_" for k in bound}
        ready = [p for p in todo if {t.tuple for t in (p.left, p.right) if t.tuple} <= bound]
        on = F.lit(True)
        for p in ready:
            on &= _holds(p, of)
        joined = joined.join(side(nxt), on)
        todo = [p for p in todo if p not in ready]
    member = lambda k: F.struct(*[F.col(f"t{k}_{c}").alias(c) for c in classes.columns])
    sets = joined.select(F.sort_array(F.array(*[member(k) for k in range(1, rule.tuples + 1)])).alias("_set")).distinct()
    # Ways to draw each class's members, one after another: a class of n has n - r left when r are drawn.
    ways, each = F.lit(1).cast("long"), [F.get("_set", F.lit(i)) for i in range(rule.tuples)]
    for i, m in enumerate(each):
        drawn = F.lit(0).cast("long")
        for other in each[:i]:
            drawn += other.eqNullSafe(m).cast("long")
        ways = F.call_function("div", ways * (m["_n"] - drawn), drawn + 1)
    drawn = sets.withColumn("_ways", ways).where("_ways > 0")
    shares = drawn.select("_ways", "_set", F.explode(F.array_distinct("_set")).alias("_m")).withColumn("_times", F.size(F.filter("_set", lambda x: x.eqNullSafe(F.col("_m")))))
    counted = shares.groupBy(*[F.col("_m")[c].alias(f"_{c}") for c in columns]).agg(F.sum(F.expr("_ways * _times div _m._n")).alias("n"))
    on = F.lit(True)
    for c in columns:
        on &= F.col(c).eqNullSafe(F.col(f"_{c}"))
    return df.join(counted, on, "left").select(id, F.coalesce("n", F.lit(0)).alias("n"))


def violation_summary(df: DataFrame, rules: list[Rule], id: str) -> DataFrame:
    """(rule_id, n_violations, n_dirty, n_clean) for each rule."""
    out = None
    for r in rules:
        one = violations(df, r, id).agg(F.sum("n").alias("n_violations"), F.sum((F.col("n") > 0).cast("long")).alias("n_dirty"), F.sum((F.col("n") == 0).cast("long")).alias("n_clean")).select(F.lit(r.rule_id).alias("rule_id"), "*")
        out = one if out is None else out.union(one)
    return out
