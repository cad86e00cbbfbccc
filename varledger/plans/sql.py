"""DuckDB SQL fragments that the oracle queries share."""

from __future__ import annotations

from ..functions.rules import CENSUS, SCALE_LEVEL, Gates

CODES = ", ".join(str(s) for s in CENSUS.sentinels)


def union_cells(table: str, columns: list[str], by: str = "") -> str:
    """Long cells (by..., col, v) of numeric columns of a table."""
    lead = f"{by}, " if by else ""
    return " UNION ALL ".join(f"SELECT {lead}'{c}' AS col, CAST({c} AS DOUBLE) AS v FROM {table}" for c in columns)


def stats(cells: str, keys: list[str], rules: Gates = CENSUS, prefix: str = "") -> str:
    """CTEs that end in {prefix}cls: statistics and class for each key."""
    k = ", ".join(keys)
    on = " AND ".join(f"a.{x} IS NOT DISTINCT FROM b.{x}" for x in keys)
    p = prefix
    ak = ", ".join(f"a.{x}" for x in keys)
    core = f"v NOT IN ({CODES}) AND v >= {rules.core_low} AND v <= {rules.core_high}"
    eligible = f"all_integer AND nd <= {rules.support_cap} AND core_n > 0" if rules.strip else "FALSE"
    count = "all_integer AND vmin >= 0"
    if rules.count_skew is not None:
        count += f" AND coalesce(skew, 0) >= {rules.count_skew}"
    if rules.count_distinct is not None:
        count += f" AND nd > {rules.count_distinct}"
    if rules.count_max is not None:
        count += f" AND vmax < {rules.count_max:.0f}"
    unit = "n_unit = nonnull"
    if rules.unit_distinct is None:
        units = f"WHEN {unit} THEN 'proportion'"
    else:
        units = f"WHEN {unit} AND nd > {rules.unit_distinct} THEN 'proportion' WHEN {unit} THEN 'ordinal'"
    return f"""
{p}cells AS ({cells}),
{p}mom AS (
    SELECT {k}, count(*) AS n, count(v) AS nonnull, min(v) AS vmin, max(v) AS vmax, count(*) FILTER (v < 0) AS n_negative,
           count(*) FILTER (v >= 0 AND v <= 1) AS n_unit, coalesce(bool_and(v = floor(v)), FALSE) AS all_integer,
           avg(v) AS mean, var_pop(v) AS variance
    FROM {p}cells GROUP BY {k}
),
{p}third AS (
    SELECT {ak}, CASE WHEN avg(pow(a.v - b.mean, 2)) > 0
           THEN avg(pow(a.v - b.mean, 3)) / pow(avg(pow(a.v - b.mean, 2)), 1.5) END AS skew
    FROM {p}cells a JOIN {p}mom b ON {on} GROUP BY {ak}
),
{p}vals AS (SELECT {k}, v, count(*) AS c FROM {p}cells WHERE v IS NOT NULL GROUP BY {k}, v),
{p}sup AS (
    SELECT {k}, count(*) AS nd_all, count(*) FILTER ({core}) AS core_n, min(v) FILTER ({core}) AS core_min,
           max(v) FILTER ({core}) AS core_max
    FROM {p}vals GROUP BY {k}
),
{p}st AS (
    SELECT a.*, b.skew, coalesce(core_n, 0) AS core_n, core_min, core_max,
           least(coalesce(nd_all, 0), {rules.support_cap + 1}) AS nd
    FROM {p}mom a JOIN {p}third b ON {on}
    LEFT JOIN (SELECT {', '.join(f'{x} AS s_{x}' for x in keys)}, nd_all, core_n, core_min, core_max FROM {p}sup) s
      ON {" AND ".join(f"a.{x} IS NOT DISTINCT FROM s.s_{x}" for x in keys)}
),
{p}cls AS (
    SELECT *, ({eligible}) AS eligible,
      CASE WHEN nonnull = 0 THEN 'categorical'
           WHEN ({eligible}) AND core_n <= {rules.binary_distinct} THEN 'binary'
           WHEN ({eligible}) AND core_min >= 0 AND core_max <= {rules.ordinal_max} AND core_n <= {rules.ordinal_distinct} THEN 'ordinal'
           WHEN nd <= {rules.binary_distinct} THEN 'binary'
           WHEN all_integer AND vmin >= 0 AND vmax <= {rules.ordinal_max} AND nd <= {rules.ordinal_distinct} THEN 'ordinal'
           WHEN {count} THEN 'count'
           {units}
           WHEN vmin >= 0 AND coalesce(skew, 0) >= {rules.heavy_skew} THEN 'heavy-tailed'
           ELSE 'continuous' END AS class
    FROM {p}st
)"""


def scale(cls: str = "class") -> str:
    return "CASE " + " ".join(f"WHEN {cls} = '{k}' THEN '{v}'" for k, v in SCALE_LEVEL.items()) + " END"


SHOWN = """CAST(n AS BIGINT) AS n, CAST(nonnull AS BIGINT) AS nonnull, CAST(nd AS BIGINT) AS n_distinct, vmin, vmax,
CAST(n_negative AS BIGINT) AS n_negative, CAST(n_unit AS BIGINT) AS n_unit, all_integer,
CASE WHEN round(mean, 4) = 0 THEN 0.0 ELSE round(mean, 4) END AS mean, CASE WHEN round(skew, 3) = 0 THEN 0.0 ELSE round(skew, 3) END AS skew, class"""
