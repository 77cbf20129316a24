"""Registered queries with their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import rng
from ..plans import counts

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

#: Decimals that measures and coordinates are compared to.
DIGITS = 8


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return add


def rounded(c: Column | str, digits: int = DIGITS) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, digits)


def flat(points: DataFrame, n: int, keys: list[str], arrays: dict[str, str]) -> DataFrame:
    """Array columns as rounded scalar columns: ``arrays`` maps a column to its prefix."""
    axes = [rounded(F.element_at(a, d)).alias(f"{p}{d}") for d in range(1, n + 1) for a, p in arrays.items()]
    return points.select(*keys, *axes)


def tree_sql(count: int, n: int, avoid_odd: bool = True, mode: str = "fixed", seed: int = 0, lo: list[str] | None = None, hi: list[str] | None = None, name: str = "strata", source: str = "") -> str:
    """Recursive CTEs ending in ``name(stratum_id, lo1, hi1, ...)``; ``lo``/``hi`` are SQL expressions over ``source``."""
    dims = range(1, n + 1)
    lo, hi = lo or ["0.0"] * n, hi or ["1.0"] * n
    sides = [f"(hi{d} - lo{d})" for d in dims]
    longest = f"(greatest({', '.join(sides)}) * (1 - {counts.TIE!r}))"
    share = counts.smaller_share_sql("cnt", avoid_odd)
    if mode == "fixed":
        axis = "CASE " + " ".join(f"WHEN {s} >= {longest} THEN {d}" for d, s in zip(dims, sides)) + " END"
    else:
        share = f"(CASE WHEN {rng.uniform_sql(seed, 'swap', 'off', 'cnt')} < 0.5 THEN {share} ELSE cnt - {share} END)"
        ties = "list_filter([" + ", ".join(f"CASE WHEN {s} >= {longest} THEN {d} END" for d, s in zip(dims, sides)) + "], lambda t: t IS NOT NULL)"
        axis = f"{ties}[CAST(floor({rng.uniform_sql(seed, 'axis', 'off', 'cnt')} * len({ties})) AS INTEGER) + 1]"
    cut = "CASE axis " + " ".join(f"WHEN {d} THEN lo{d} + (hi{d} - lo{d}) * CAST(share AS DOUBLE) / CAST(cnt AS DOUBLE)" for d in dims) + " END"
    columns = ", ".join(f"lo{d}, hi{d}" for d in dims)
    start = ", ".join(f"CAST({a} AS DOUBLE), CAST({b} AS DOUBLE)" for a, b in zip(lo, hi))
    moved = ", ".join(f"CASE WHEN side = 1 AND axis = {d} THEN cut ELSE lo{d} END, CASE WHEN side = 0 AND axis = {d} THEN cut ELSE hi{d} END" for d in dims)
    return f"""{name}_tree(off, cnt, {columns}) AS (
        SELECT CAST(0 AS BIGINT), CAST({count} AS BIGINT), {start} {f'FROM {source}' if source else ''}
        UNION ALL
        SELECT CASE side WHEN 0 THEN off ELSE off + share END, CASE side WHEN 0 THEN share ELSE cnt - share END, {moved}
        FROM (SELECT *, {cut} AS cut FROM (SELECT *, {axis} AS axis FROM (SELECT *, {share} AS share FROM {name}_tree WHERE cnt > 1))),
             (VALUES (0), (1)) v(side)
    ), {name} AS (SELECT off AS stratum_id, {columns} FROM {name}_tree WHERE cnt = 1)"""


def rounded_sql(columns: list[str], digits: int = DIGITS) -> str:
    return ", ".join(f"round({c}, {digits}) AS {c}" for c in columns)


def box_columns(n: int) -> list[str]:
    return [f"{s}{d}" for d in range(1, n + 1) for s in ("lo", "hi")]


def product_sql(terms: list[str]) -> str:
    return " * ".join(f"({t})" for t in terms)
