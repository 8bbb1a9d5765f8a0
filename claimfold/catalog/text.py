"""SQL text shared by the oracles: replicas, votes, seeds."""

from __future__ import annotations

from ..functions.noise import mix_sql
from ..sources.replicas import SETS

#: (entity key, its table expression, attributes as SQL strings) of each replica set.
_BASE = {
    "orders": ("o_orderkey", "orders JOIN customer ON o_custkey = c_custkey", {"o_orderstatus": "o_orderstatus", "o_orderpriority": "o_orderpriority", "o_orderdate": "strftime(o_orderdate, '%Y-%m-%d')", "o_totalprice": "CAST(CAST(o_totalprice AS DECIMAL(18,2)) AS VARCHAR)", "o_custkey": "CAST(o_custkey AS VARCHAR)", "c_mktsegment": "c_mktsegment"}),
    "part": ("p_partkey", "part", {"p_name": "p_name", "p_brand": "p_brand", "p_type": "p_type", "p_size": "CAST(p_size AS VARCHAR)", "p_retailprice": "CAST(CAST(p_retailprice AS DECIMAL(18,2)) AS VARCHAR)", "colour": "split_part(p_name, ' ', 1)", "noun": "split_part(p_name, ' ', 2)", "brand_no": "split_part(p_brand, '#', 2)", "size_band": "CAST(p_size // 10 AS VARCHAR)", "price_band": "CAST(CAST(floor(p_retailprice) AS BIGINT) // 50 AS VARCHAR)"}),
    "customer": ("c_custkey", "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey", {"c_name": "c_name", "c_mktsegment": "c_mktsegment", "c_nationkey": "CAST(c_nationkey AS VARCHAR)", "n_name": "n_name", "r_name": "r_name", "c_acctbal": "CAST(CAST(c_acctbal AS DECIMAL(18,2)) AS VARCHAR)"}),
    "supplier": ("s_suppkey", "supplier", {"s_name": "s_name", "s_nationkey": "CAST(s_nationkey AS VARCHAR)", "s_acctbal": "CAST(CAST(s_acctbal AS DECIMAL(18,2)) AS VARCHAR)"}),
}
_BASE["part_small"] = _BASE["part_vote"] = _BASE["part"]


def roll_sql(k: str, s: str | int, j: str | int, salt: int = 0) -> str:
    return f"({mix_sql(k, s, j, salt)} % 1000)"


def base_cte(name: str, prefix: str = "") -> str:
    key, tables, exprs = _BASE[name]
    cols = ", ".join(f"{exprs[a]} AS {a}" for a in SETS[name][2])
    return f"{prefix}base AS MATERIALIZED (SELECT CAST({key} AS BIGINT) AS k, {cols} FROM {tables}), {prefix}size AS (SELECT count(*) AS n FROM {prefix}base)"


def rep_cte(name: str, prefix: str = "", salt: int | None = None) -> str:
    """CTEs `base`, `rep` (wide), `claims` (long) and `truth`."""
    _, _, attrs, spec = SETS[name]
    salt = spec.salt if salt is None else salt
    p = prefix
    acc = f"({spec.high} - (({spec.high - spec.low} * s) // {max(spec.n_sources - 1, 1)}))"
    cols = []
    for j, a in enumerate(attrs, start=1):
        edit = (f"upper(b.{a})", f"substr(b.{a}, 1, greatest(length(b.{a}) - 2, 1))", f"replace(b.{a}, ' ', '-')")[j % 3]
        wrong = f"m{j} % 1000 < (CASE WHEN bad THEN 850 ELSE 50 END)"
        if spec.trusted is not None:
            wrong = f"({wrong} AND r.s <> {spec.trusted})"
        cols.append(f"CASE WHEN NOT ({wrong}) THEN b.{a} WHEN (m{j} // 1000) % 6 <= 2 THEN x.{a} WHEN (m{j} // 1000) % 6 = 3 THEN y.{a} WHEN (m{j} // 1000) % 6 = 4 THEN {edit} END AS {a}")
    mixes = ", ".join(f"{mix_sql('k', 's', j, salt)} AS m{j}" for j in range(1, len(attrs) + 1))
    union = " UNION ALL ".join(f"SELECT entity_id, source_id, '{a}' AS attr, {a} AS value FROM {p}rep WHERE {a} IS NOT NULL" for a in attrs)
    truths = " UNION ALL ".join(f"SELECT k AS entity_id, '{a}' AS attr, {a} AS value FROM {p}base" for a in attrs)
    return (
        f"{base_cte(name, p)}, {p}raw AS MATERIALIZED (SELECT k, s, (k + 1) % (SELECT n FROM {p}size) AS xk, (k + 1 + s % 5) % (SELECT n FROM {p}size) AS yk, {roll_sql('k', 's', 50, salt)} >= {acc} AS bad, {mixes} FROM {p}base, (SELECT CAST(unnest(range({spec.n_sources})) AS BIGINT) AS s) q WHERE {roll_sql('k', 's', 97, salt)} < {spec.coverage}), "
        f"{p}rep AS MATERIALIZED (SELECT r.k AS entity_id, CAST(r.s AS INTEGER) AS source_id, {', '.join(cols)} FROM {p}raw r JOIN {p}base b ON b.k = r.k JOIN {p}base x ON x.k = r.xk JOIN {p}base y ON y.k = r.yk), "
        f"{p}claims AS ({union}), {p}truth AS ({truths})"
    )


def cand_cte(claims: str = "claims", name: str = "cand") -> str:
    return f"{name} AS (SELECT entity_id, attr, value, count(*) AS support, row_number() OVER (PARTITION BY entity_id, attr ORDER BY count(*) DESC, value) - 1 AS slot, count(*) OVER (PARTITION BY entity_id, attr) AS n_slots FROM {claims} GROUP BY entity_id, attr, value)"


def part_sql(k: str, train: int, validation: int = 1000, seed: int = 0) -> str:
    m = f"({mix_sql(k, 0, 55, seed)} % 10000)"
    return f"CASE WHEN {m} < {train} THEN 'train' WHEN {m} < {train + validation} THEN 'validation' ELSE 'test' END"


def seeds_cte(train: int = 1000) -> str:
    return f"seeds AS (SELECT * FROM truth WHERE {part_sql('entity_id', train)} = 'train')"


LINE_ATTRS = ("l_returnflag", "l_linestatus", "l_discount", "l_linenumber")


def line_cte() -> str:
    union = " UNION ALL ".join(f"SELECT l_partkey AS entity_id, CAST(l_suppkey AS INTEGER) AS source_id, '{a}' AS attr, {'CAST(CAST(l_discount AS DECIMAL(18,2)) AS VARCHAR)' if a == 'l_discount' else f'CAST({a} AS VARCHAR)'} AS value FROM lineitem" for a in LINE_ATTRS)
    return f"claims AS ({union})"
