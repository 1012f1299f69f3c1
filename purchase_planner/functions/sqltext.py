"""The measures as Spark SQL text, for users who stay in SQL: each function returns a SELECT over named tables or views.

The text aggregates in two combinable steps, as the DataFrame measures do; no join of the sides is ever built.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import SparkSession

from .measures import FD


def _names(columns: Sequence[str]) -> str:
    return ", ".join(f"`{c}`" for c in columns)


def _xlog(x: str) -> str:
    return f"IF({x} > 0, {x} * log2({x}), 0D)"


def fd_quality_sql(source: str, fd: FD) -> str:
    """quality: the share of rows in the largest class of their left side."""
    sizes = f"SELECT {_names(fd.lhs)}, count(*) AS c FROM {source} GROUP BY {_names(fd.lhs)}, `{fd.rhs}`"
    return f"SELECT sum(m) / sum(n) AS quality FROM (SELECT max(c) AS m, sum(c) AS n FROM ({sizes}) GROUP BY {_names(fd.lhs)})"


def informativeness_sql(left: str, right: str, join: Sequence[str]) -> str:
    """ji and join_rows of two tables on `join`, from key counts; a null in any part of a key matches nothing."""
    keys = _names(join)
    tagged = f"SELECT {keys}, 1 AS l, 0 AS r FROM {left} UNION ALL SELECT {keys}, 0, 1 FROM {right}"
    no_key = " OR ".join(f"`{k}` IS NULL" for k in join)
    per = f"SELECT CAST(sum(l) AS DOUBLE) AS l, CAST(sum(r) AS DOUBLE) AS r, first({no_key}) AS no_key FROM ({tagged}) GROUP BY {keys}"
    alone_l, alone_r, both = "NOT no_key AND r = 0", "NOT no_key AND l = 0", "NOT no_key AND l > 0 AND r > 0"
    total = lambda of, when: f"coalesce(sum({of}) FILTER (WHERE {when}), 0D)"
    sums = f"SELECT {total('l', alone_l)} AS al, {total('r', alone_r)} AS ar, {total('l + r', 'no_key')} AS np, {total('l * r', both)} AS mt, {total(_xlog('l'), alone_l)} AS xl, {total(_xlog('r'), alone_r)} AS xr, {total(_xlog('(l * r)'), both)} AS xm FROM ({per})"
    rest = f"{_xlog('(ar + np)')} + {_xlog('(al + np)')} - xl - xr - 2 * {_xlog('np')}"
    entropy = f"{_xlog('(al + ar + np + mt)')} - xm - xl - xr - {_xlog('np')}"
    return f"SELECT IF(h > 1e-12, greatest(0D, least(1D, rest / h)), 0D) AS ji, mt AS join_rows FROM (SELECT {rest} AS rest, {entropy} AS h, mt FROM ({sums}))"


def correlation_sql(source: str, x: Sequence[str], y: Sequence[str]) -> str:
    """corr of categorical attributes: H(x) + H(y) - H(x, y), by grouping sets over one read."""
    all_of = list(dict.fromkeys([*x, *y]))
    bit = {c: 1 << (len(all_of) - 1 - i) for i, c in enumerate(all_of)}
    absent = lambda s: sum(b for c, b in bit.items() if c not in s)
    sets = ", ".join(f"({_names(s)})" for s in ([*x], [*y], all_of))
    counts = f"SELECT grouping_id() AS g, CAST(count(*) AS DOUBLE) AS c FROM {source} GROUP BY GROUPING SETS ({sets})"
    entropies = f"SELECT g, log2(sum(c)) - sum(c * log2(c)) / sum(c) AS h FROM ({counts}) GROUP BY g"
    return f"SELECT sum(CASE g WHEN {absent(x)} THEN h WHEN {absent(y)} THEN h ELSE -h END) AS corr FROM ({entropies})"


def create_view(spark: SparkSession, name: str, text: str) -> None:
    """A temporary view of one of the texts; it is evaluated when it is read."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY VIEW `{name}` AS {text}")
