"""Queries of profiling, classification, audit and lineage."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.rules import CENSUS, HARDENED, PILOT
from ..operators import audit, classify, evidence, lineage
from ..sources.tables import ORDER_QUANTITIES_SQL, PRIORITY_SQL, order_quantities, priority_codes, table
from . import sql

NUMERIC = {
    "region": ["r_regionkey"],
    "nation": ["n_nationkey", "n_regionkey"],
    "customer": ["c_custkey", "c_nationkey", "c_acctbal"],
    "supplier": ["s_suppkey", "s_nationkey", "s_acctbal"],
    "part": ["p_partkey", "p_size", "p_retailprice"],
    "orders": ["o_orderkey", "o_custkey", "o_totalprice"],
    "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax"],
    "events": ["event_id", "user_id", "value"],
    "documents": ["doc_id", "n_chars"],
    "labels": ["doc_id", "quality", "toxic"],
    "pages": ["page_id"],
    "benchmark": ["item_id"],
    "conversations": ["conv_id", "turn"],
    "embeddings": ["vec_id", "label"],
}


def shown(profiles: DataFrame, *keys: str) -> DataFrame:
    return profiles.select(
        *keys, "n", "nonnull", "n_distinct", "vmin", "vmax", "n_negative", "n_unit", "all_integer",
        _rounded("mean", 4), _rounded("skew", 3), "class",
    )


def _rounded(c: str, digits: int):
    """Rounded, with one zero."""
    x = F.round(c, digits)
    return F.when(x == 0, 0.0).otherwise(x).alias(c)


def _profile(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        profiles = evidence.profile_columns(table(spark, sf_dir, name), NUMERIC[name])
        return shown(classify.classified(profiles).withColumnRenamed("column", "col"), "col")

    return run


def _profile_sql(name: str) -> str:
    return f"WITH {sql.stats(sql.union_cells(name, NUMERIC[name]), ['col'])} SELECT col, {sql.SHOWN} FROM cls"


def profile_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every column of every table, strings and timestamps included."""
    out = None
    for name in NUMERIC:
        df = table(spark, sf_dir, name)
        flat = [f.name for f in df.schema.fields if not isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType))]
        one = classify.classified(evidence.profile_columns(df, flat)).select(
            F.lit(name).alias("table_name"), "column", "class", classify.declared_datatype().alias("datatype"),
            classify.scale_level().alias("scale"),
        )
        out = one if out is None else out.unionByName(one)
    return out.groupBy("table_name", "class", "scale").agg(F.count("*").alias("n_columns"))


def _profile_all_sql() -> str:
    numeric = " UNION ALL ".join(f"SELECT '{t}' AS table_name, col, v FROM ({sql.union_cells(t, c)})" for t, c in NUMERIC.items())
    others = {"region": 1, "nation": 1, "customer": 2, "supplier": 1, "part": 3, "orders": 3, "lineitem": 3, "events": 3,
              "documents": 3, "pages": 2, "benchmark": 1, "conversations": 2}
    rest = " UNION ALL ".join(f"SELECT '{t}' AS table_name, 'categorical' AS class, {n} AS k" for t, n in others.items())
    return f"""WITH {sql.stats(numeric, ['table_name', 'col'])},
counted AS (SELECT table_name, class, count(*) AS k FROM cls GROUP BY table_name, class UNION ALL {rest})
SELECT table_name, class, {sql.scale()} AS scale, CAST(sum(k) AS BIGINT) AS n_columns FROM counted GROUP BY table_name, class"""


def scope_event_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same variable in the full scope and in each slice, in one scan."""
    ev = table(spark, sf_dir, "events").select("event_type", F.col("value").alias("value"))
    cells = ev.select(F.explode(F.array(F.lit("full"), "event_type")).alias("scope"), "value")
    return shown(classify.classified(evidence.profile_cells(cells, ["scope"])), "scope")


SCOPE_SQL = f"""WITH {sql.stats("SELECT 'full' AS scope, value AS v FROM events UNION ALL SELECT event_type, value FROM events", ['scope'])}
SELECT scope, {sql.SHOWN} FROM cls"""


def lang_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("lang", "source", F.col("n_chars").cast("double").alias("value"))
    return shown(classify.classified(evidence.profile_cells(docs, ["lang", "source"])), "lang", "source")


LANG_SOURCE_SQL = f"""WITH {sql.stats("SELECT lang, source, CAST(n_chars AS DOUBLE) AS v FROM documents", ['lang', 'source'])}
SELECT lang, source, {sql.SHOWN} FROM cls"""


def distinct_estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketched against exact distinct counts: within three standard errors?"""
    li, rsd = table(spark, sf_dir, "lineitem"), 0.05
    exact = li.agg(F.array(*[F.struct(F.lit(c).alias("column"), F.countDistinct(c).alias("n_distinct")) for c in NUMERIC["lineitem"]]).alias("a")).select(F.inline("a"))
    near = F.abs(F.col("estimate") - F.col("n_distinct")) <= 3 * rsd * F.col("n_distinct")
    return evidence.distinct_estimates(li, NUMERIC["lineitem"], rsd=rsd).join(exact, "column").select(F.col("column").alias("col"), "n_distinct", near.alias("near"))


DISTINCT_SQL = " UNION ALL ".join(f"SELECT '{c}' AS col, count(DISTINCT {c}) AS n_distinct, TRUE AS near FROM lineitem" for c in NUMERIC["lineitem"])

def lexical_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Datatypes of columns that are all text, as a delimited file gives them."""
    text = table(spark, sf_dir, "orders").select(
        F.col("o_orderkey").cast("string").alias("key"), F.col("o_totalprice").cast("string").alias("price"), F.col("o_orderstatus").alias("status"),
        (F.col("o_totalprice") > 100000).cast("string").alias("large"), F.date_format("o_orderdate", "yyyy-MM-dd").alias("day"),
        F.when(F.col("o_orderkey") % 2 == 0, F.substring("o_orderpriority", 1, 1)).alias("digit"),
    )
    return evidence.type_flags(text).select(F.col("column").alias("col"), "xsd_datatype")


def _types_sql() -> str:
    parts = {
        "key": "CAST(o_orderkey AS VARCHAR)", "price": "CAST(o_totalprice AS VARCHAR)", "status": "o_orderstatus", "large": "CAST(o_totalprice > 100000 AS VARCHAR)",
        "day": "strftime(o_orderdate, '%Y-%m-%d')", "digit": "CASE WHEN o_orderkey % 2 = 0 THEN substring(o_orderpriority, 1, 1) END",
    }
    return " UNION ALL ".join(
        f"""SELECT '{c}' AS col, CASE WHEN bool_and(regexp_full_match(x, '[+-]?[0-9]+')) THEN 'Integer' WHEN bool_and(TRY_CAST(x AS DOUBLE) IS NOT NULL) THEN 'Double'
WHEN bool_and(lower(x) IN ('true', 'false')) THEN 'Boolean' WHEN bool_and(regexp_full_match(x, '[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}')) THEN 'Date' ELSE 'String' END AS xsd_datatype FROM (SELECT {e} AS x FROM orders) WHERE x IS NOT NULL"""
        for c, e in parts.items()
    )


KINDS = ("customer", "supplier", "part", "orders", "nation")


def structural_kinds(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in KINDS:
        df = table(spark, sf_dir, name)
        p = evidence.profile_columns(df, df.columns).join(evidence.distinct_estimates(df, df.columns, rsd=0.02), "column")
        one = p.select(F.lit(name).alias("table_name"), F.col("column").alias("col"), classify.structural_kind().alias("kind"))
        out = one if out is None else out.unionByName(one)
    return out


#: (table, column): text columns, integral columns and others, by the schema.
_COLUMNS = {
    "customer": ("c_custkey c_nationkey", "c_name c_mktsegment", "c_acctbal"), "supplier": ("s_suppkey s_nationkey", "s_name", "s_acctbal"),
    "part": ("p_partkey p_size", "p_name p_brand p_type", "p_retailprice"), "orders": ("o_orderkey o_custkey", "o_orderstatus o_orderdate o_orderpriority", "o_totalprice"),
    "nation": ("n_nationkey n_regionkey", "n_name", ""),
}
KINDS_SQL = " UNION ALL ".join(
    f"""SELECT '{t}' AS table_name, '{c}' AS col, CASE WHEN {coded} AND count(*) > 25 AND count(DISTINCT {c}) >= 0.8 * count(*) THEN 'identifier' WHEN count(DISTINCT {c}) <= 25 THEN 'dimension' ELSE '{rest}' END AS kind FROM {t}"""
    for t, groups in _COLUMNS.items() for (coded, rest), names in zip((("TRUE", "measure"), ("TRUE", "attribute"), ("FALSE", "measure")), groups, strict=True) for c in names.split()
)


def small_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact value counts of the columns whose support is complete."""
    p = evidence.profile_columns(table(spark, sf_dir, "lineitem"), NUMERIC["lineitem"])
    return p.where("complete").select(F.col("column").alias("col"), F.explode("support").alias("s")).select(
        "col", F.col("s.value").alias("v"), F.col("s.count").alias("n")
    )


SUPPORT_SQL = f"""WITH c AS (SELECT col, v, count(*) AS n FROM ({sql.union_cells('lineitem', NUMERIC['lineitem'])}) GROUP BY col, v)
SELECT col, v, n FROM c WHERE col IN (SELECT col FROM c GROUP BY col HAVING count(*) <= 25)"""


# -- derived columns of five kinds ---------------------------------------


def _five_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = order_quantities(spark, sf_dir)
    digit = F.substring("o_orderpriority", 1, 1).cast("double")
    parts = [
        orders.select(F.lit("bulk_units").alias("col"), F.col("bulk_units").cast("double").alias("value")),
        orders.select(F.lit("bulk_share").alias("col"), F.col("bulk_share").alias("value")),
        table(spark, sf_dir, "labels").select(F.lit("toxic").alias("col"), F.col("toxic").cast("double").alias("value")),
        table(spark, sf_dir, "orders").select(F.lit("priority_digit").alias("col"), digit.alias("value")),
        table(spark, sf_dir, "events").select(F.lit("value_squared").alias("col"), (F.col("value") * F.col("value")).alias("value")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


FIVE_CELLS_SQL = f"""SELECT 'bulk_units' AS col, CAST(bulk_units AS DOUBLE) AS v FROM ({ORDER_QUANTITIES_SQL})
UNION ALL SELECT 'bulk_share', bulk_share FROM ({ORDER_QUANTITIES_SQL})
UNION ALL SELECT 'toxic', CAST(toxic AS DOUBLE) FROM labels
UNION ALL SELECT 'priority_digit', CAST(substring(o_orderpriority, 1, 1) AS DOUBLE) FROM orders
UNION ALL SELECT 'value_squared', value * value FROM events"""


def five_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Datatype, scale and class side by side, and as one document: the datatype
    cannot tell what the class tells."""
    p = classify.classified(evidence.profile_cells(_five_cells(spark, sf_dir), ["col"]))
    kind = F.when(F.col("all_integer"), "Integer").otherwise("Double")
    return classify.described(p, name="col", datatype=kind).withColumnRenamed("name", "col")


FIVE_SQL = f"""WITH {sql.stats(FIVE_CELLS_SQL, ['col'])}, d AS (SELECT col, CASE WHEN all_integer THEN 'Integer' ELSE 'Double' END AS datatype, {sql.scale()} AS scale, class FROM cls)
SELECT *, '{{"name":"' || col || '","datatype":"' || datatype || '","scale":"' || scale || '","class":"' || class || '"}}' AS description FROM d"""


def transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes under the pilot, hardened and final rules over one evidence."""
    p = evidence.profile_cells(_five_cells(spark, sf_dir).unionByName(_table_cells(spark, sf_dir)), ["col"])
    a, b, c = (classify.classified(p, rules=r).select("col", F.col("class").alias(n)) for r, n in ((PILOT, "pilot"), (HARDENED, "hardened"), (CENSUS, "final")))
    return a.join(b, "col").join(c, "col").groupBy("pilot", "hardened", "final").agg(F.count("*").alias("n_columns"))


def _table_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in ("lineitem", "documents", "events"):
        cols = NUMERIC[name]
        cells = table(spark, sf_dir, name).select(*[F.col(c).cast("double").alias(c) for c in cols]).unpivot([], cols, "col", "value")
        out = cells if out is None else out.unionByName(cells)
    return out


def _transitions_sql() -> str:
    cells = FIVE_CELLS_SQL + "".join(" UNION ALL " + sql.union_cells(t, NUMERIC[t]) for t in ("lineitem", "documents", "events"))
    return f"""WITH {sql.stats(cells, ['col'], PILOT, 'p_')}, {sql.stats(cells, ['col'], HARDENED, 'h_')}, {sql.stats(cells, ['col'], CENSUS, 'f_')}
SELECT p.class AS pilot, h.class AS hardened, f.class AS final, count(*) AS n_columns
FROM p_cls p JOIN h_cls h ON p.col = h.col JOIN f_cls f ON p.col = f.col GROUP BY p.class, h.class, f.class"""


# -- literal cases ---------------------------------------------------------

#: (case, values): supports with a known outcome.
CASES = {
    "three_values": [0, 50, 100],
    "species_like": [2, 3, 3, 4, 4, 4, 5, 5, 6, 7, 9, 11],
    "two_counts": [3, 7, 3, 3],
    "rating_with_codes": [1, 2, 3, 4, 5, 98, 99],
    "negatives": [-1, 0, 1],
    "declared_negatives": [-1, -1, 0, 1],
    "undeclared_pair": [-1, 1],
    "zero_and_code": [0, 99],
    "declared_rating": [1, 2, 3, 4, 5, 99],
    "half_declared_rating": [1, 2, 3, 4, 5, 98, 99],
    "overflow_declared": [*range(30), 99, 99, 99],
    "coarse_share": [0, 0.25, 0.5, 0.75, 1],
    "rescaled_rating": [0, 1 / 8, 2 / 8, 3 / 8, 4 / 8, 5 / 8, 6 / 8, 7 / 8, 1],
    "fine_share": [i / 40 for i in range(41)],
    "percentage": [i * 2.4 for i in range(42)] + [100],
    "constant": [4, 4, 4],
    "empty_core": [100, 200, 300, 400, 500],
    "small_long_tail": [0] * 9 + [1] * 6 + [2] * 3 + [3, 4, 6, 14],
    "large_count": [i * i * i for i in range(40)],
    "over_magnitude": [i * i * i for i in range(40)] + [2_000_000],
    "valid_99_100": list(range(90, 120)),
    "all_missing": [None, None],
}


def _case_rows() -> list[tuple[str, float | None]]:
    return [(c, None if v is None else float(v)) for c, values in CASES.items() for v in values]


#: What a codebook says of some cases: (case, value).
DECLARED = [("declared_negatives", -1), ("declared_rating", 99), ("half_declared_rating", 99), ("overflow_declared", 99), ("fine_share", 7)]


def regression_cases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document holds the column of one case, by the length of its text."""
    held = table(spark, sf_dir, "documents").select("doc_id", (F.coalesce(F.length("text"), F.lit(0)) % len(CASES)).alias("i"))
    names = list(CASES)
    values = spark.createDataFrame([(names.index(c), c, v) for c, v in _case_rows()], "i int, case_name string, value double")
    codes = spark.createDataFrame([(names.index(c), c, float(v), "codebook") for c, v in DECLARED], "i int, case_name string, value double, evidence_id string")
    cells, said = (held.join(F.broadcast(rows), "i").drop("i") for rows in (values, codes))
    keys = ["doc_id", "case_name"]
    p = audit.audited(evidence.profile_cells(cells, keys), said, keys, cells=cells)
    return p.select("doc_id", "case_name", "class", "audit_class", F.size("stripped").alias("n_stripped"), "overflow", "dropped_rows")


_CASE_VALUES = ", ".join(f"({list(CASES).index(c)}, '{c}', {'NULL' if v is None else repr(v)})" for c, v in _case_rows())
#: The audit from its definition: the class of the values as they are, against
#: the class that the sentinel step leads to.
PLAIN = replace(CENSUS, strip=False)
_BY_CORE = "coalesce(f.eligible, FALSE) AND (f.core_n <= 2 OR (f.core_min >= 0 AND f.core_max <= 12 AND f.core_n <= 12))"
_GONE = f"(v IN ({sql.CODES}) OR v < -90 OR v > 90)"
_CASE_KEYS = ["doc_id", "case_name"]
CASES_SQL = f"""WITH src AS (SELECT doc_id, c AS case_name, CAST(x AS DOUBLE) AS v FROM documents JOIN (VALUES {_CASE_VALUES}) t(i, c, x) ON i = coalesce(length(text), 0) % {len(CASES)}), said(c, x) AS (VALUES {", ".join(f"('{c}', {v})" for c, v in DECLARED)}),
{sql.stats("SELECT * FROM src", _CASE_KEYS)}, {sql.stats("SELECT * FROM src", _CASE_KEYS, PLAIN, 'q_')},
open AS (SELECT doc_id, case_name, count(DISTINCT v) AS n FROM src LEFT JOIN said ON c = case_name AND x = v WHERE {_GONE} AND c IS NULL GROUP BY 1, 2),
gone AS (SELECT doc_id, case_name, count(*) AS n FROM src JOIN said ON c = case_name AND x = v GROUP BY 1, 2)
SELECT f.doc_id, f.case_name, f.class, CAST(CASE WHEN {_BY_CORE} THEN f.nd - f.core_n ELSE 0 END AS INTEGER) AS n_stripped,
  CASE WHEN f.nd <= 1 OR ({_BY_CORE} AND coalesce(open.n, 0) > 0 AND q.class <> f.class) THEN 'unresolved' ELSE f.class END AS audit_class,
  f.nd > 25 AS overflow, CAST(coalesce(gone.n, 0) AS BIGINT) AS dropped_rows
FROM cls f JOIN q_cls q ON q.doc_id = f.doc_id AND q.case_name = f.case_name LEFT JOIN open ON open.doc_id = f.doc_id AND open.case_name = f.case_name
LEFT JOIN gone ON gone.doc_id = f.doc_id AND gone.case_name = f.case_name"""


def counterexample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A column whose values lie outside the core range leaves two values or
    fewer there: quantity to the sixth power, per part."""
    cells = table(spark, sf_dir, "lineitem").select("l_partkey", F.pow("l_quantity", F.lit(6.0)).alias("value"))
    p = audit.audited(evidence.profile_cells(cells, ["l_partkey"]), None, ["l_partkey"])
    return p.groupBy("class", "audit_class").agg(F.count("*").alias("n"))


_SIXTH = "SELECT l_partkey, pow(l_quantity, 6.0) AS v FROM lineitem"
COUNTER_SQL = f"""WITH {sql.stats(_SIXTH, ['l_partkey'])}, {sql.stats(_SIXTH, ['l_partkey'], PLAIN, 'q_')}
SELECT f.class, CASE WHEN f.nd <= 1 OR ({_BY_CORE} AND f.nd > f.core_n AND q.class <> f.class) THEN 'unresolved' ELSE f.class END AS audit_class, count(*) AS n
FROM cls f JOIN q_cls q ON q.l_partkey = f.l_partkey GROUP BY 1, 2"""


def hints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Failure modes that the gates cannot see, as hints beside the class."""
    share = table(spark, sf_dir, "events").groupBy("user_id").agg(
        (100 * F.avg((F.col("event_type") == "purchase").cast("double"))).alias("value")
    )
    lines = order_quantities(spark, sf_dir).select(F.lit("lines_per_order").alias("col"), F.col("lines").cast("double").alias("value"))
    li = table(spark, sf_dir, "lineitem")
    cells = share.select(F.lit("purchase_pct").alias("col"), "value").unionByName(lines)
    for c in ("l_discount", "l_tax"):
        cells = cells.unionByName(li.select(F.lit(c).alias("col"), F.col(c).alias("value")))
    p = audit.failure_hints(classify.classified(evidence.profile_cells(cells, ["col"])))
    return p.select("col", "class", "hint")


HINTS_SQL = f"""WITH {sql.stats(f'''SELECT 'purchase_pct' AS col, 100 * avg(CASE WHEN event_type = 'purchase' THEN 1.0 ELSE 0.0 END) AS v FROM events GROUP BY user_id
UNION ALL SELECT 'lines_per_order', CAST(lines AS DOUBLE) FROM ({ORDER_QUANTITIES_SQL})
UNION ALL SELECT 'l_discount', l_discount FROM lineitem UNION ALL SELECT 'l_tax', l_tax FROM lineitem''', ['col'])},
gaps AS (SELECT col, max(g) - min(g) < 1e-9 AND count(g) > 1 AS even FROM
  (SELECT col, v - lag(v) OVER (PARTITION BY col ORDER BY v) AS g FROM vals) GROUP BY col)
SELECT col, class, CASE WHEN class = 'continuous' AND vmin >= 0 AND vmax BETWEEN 99 AND 100 AND n_unit <> nonnull THEN 'percent_scale'
  WHEN class = 'ordinal' AND n_unit = nonnull AND nd > 2 AND nd <= 25 AND even THEN 'evenly_spaced_share'
  WHEN class = 'ordinal' AND n_unit = nonnull AND nd > 2 THEN 'coarse_share'
  WHEN class IN ('continuous', 'ordinal') AND all_integer AND vmin >= 0 AND nd > 4 AND nd <= 25 AND abs(coalesce(skew, 0)) < 1 THEN 'symmetric_small_count'
  ELSE 'none' END AS hint FROM cls JOIN gaps USING (col)"""


def _audit(declared: bool):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        said = None
        if declared:
            said = spark.createDataFrame(
                [("priority", 99.0, "codebook-1"), ("priority", -9.0, "codebook-2")], "col string, value double, evidence_id string"
            )
        p = audit.audited(evidence.profile_cells(priority_codes(spark, sf_dir), ["col"]), said, ["col"])
        return p.select("col", "class", "audit_class", "dropped_rows", F.size("would_strip").alias("n_would_strip"))

    return run


def _audit_sql(declared: bool) -> str:
    verdict = "class" if declared else "'unresolved'"
    dropped = "(SELECT count(*) FROM cells WHERE v IN (99, -9))" if declared else "0"
    return f"""WITH {sql.stats(PRIORITY_SQL, ['col'])} SELECT col, class, {verdict} AS audit_class,
CAST({dropped} AS BIGINT) AS dropped_rows, CAST(nd - core_n AS INTEGER) AS n_would_strip FROM cls"""


def net_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    step = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    li = table(spark, sf_dir, "lineitem").select("l_extendedprice", "l_discount")
    df, _ = lineage.derive(li, "net_price", "product", ["l_extendedprice", "l_discount"], step)
    return lineage.verify(df, "net_price", step)


def difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    step = F.col("bulk_units") - F.col("total_quantity")
    df, _ = lineage.derive(order_quantities(spark, sf_dir), "rest", "difference", ["bulk_units", "total_quantity"], step)
    return lineage.verify(df, "rest", step)


def embeddings_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arrays become child variables, one for each position."""
    cells = table(spark, sf_dir, "embeddings").select(F.posexplode("embedding").alias("position", "x")).select(
        "position", F.col("x").cast("double").alias("value")
    )
    p = classify.classified(evidence.profile_cells(cells, ["position"]))
    return p.groupBy("class").agg(F.count("*").alias("n_positions"), F.sum("nonnull").alias("n_values"))


EMBEDDINGS_SQL = f"""WITH {sql.stats("SELECT generate_subscripts(embedding, 1) AS position, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings", ['position'])}
SELECT class, count(*) AS n_positions, CAST(sum(nonnull) AS BIGINT) AS n_values FROM cls GROUP BY class"""


def props_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = table(spark, sf_dir, "events").select(F.from_json("props", "k long").alias("p")).select(
        F.lit("props.k").alias("col"), F.col("p.k").cast("double").alias("value")
    )
    return shown(classify.classified(evidence.profile_cells(ev, ["col"])), "col")


PROPS_SQL = f"""WITH {sql.stats("SELECT 'props.k' AS col, CAST(json_extract(props, '$.k') AS DOUBLE) AS v FROM events", ['col'])}
SELECT col, {sql.SHOWN} FROM cls"""


def queries():
    return {
        **{f"profile_{t}": _profile(t) for t in ("lineitem", "documents", "orders", "events")},
        "profile_all": profile_all,
        "profile_by_scope_event_type": scope_event_type,
        "corpus_profile_by_lang_source": lang_source,
        "distinct_estimates": distinct_estimates,
        "structural_kinds": structural_kinds,
        "lexical_types": lexical_types,
        "small_support_complete": small_support,
        "five_column_comparison": five_columns,
        "class_transitions": transitions,
        "regression_cases": regression_cases,
        "sentinel_counterexample": counterexample,
        "failure_mode_hints": hints,
        "audit_priority_undeclared": _audit(False),
        "audit_priority_declared": _audit(True),
        "lineage_net_price": net_price,
        "lineage_difference": difference,
        "array_profile_embeddings": embeddings_profile,
        "json_profile_props": props_profile,
    }


def oracle_sql():
    return {
        **{f"profile_{t}": _profile_sql(t) for t in ("lineitem", "documents", "orders", "events")},
        "profile_all": _profile_all_sql(),
        "profile_by_scope_event_type": SCOPE_SQL,
        "corpus_profile_by_lang_source": LANG_SOURCE_SQL,
        "distinct_estimates": DISTINCT_SQL,
        "structural_kinds": KINDS_SQL,
        "lexical_types": _types_sql(),
        "small_support_complete": SUPPORT_SQL,
        "five_column_comparison": FIVE_SQL,
        "class_transitions": _transitions_sql(),
        "regression_cases": CASES_SQL,
        "sentinel_counterexample": COUNTER_SQL,
        "failure_mode_hints": HINTS_SQL,
        "audit_priority_undeclared": _audit_sql(False),
        "audit_priority_declared": _audit_sql(True),
        "lineage_net_price": "SELECT 'net_price' AS derived_variable, count(*) AS n_rows, CAST(0 AS BIGINT) AS n_mismatch, count(*) FILTER (l_extendedprice * (1 - l_discount) < 0) AS n_negative FROM lineitem",
        "lineage_difference": f"SELECT 'rest' AS derived_variable, count(*) AS n_rows, CAST(0 AS BIGINT) AS n_mismatch, count(*) FILTER (bulk_units - total_quantity < 0) AS n_negative FROM ({ORDER_QUANTITIES_SQL})",
        "array_profile_embeddings": EMBEDDINGS_SQL,
        "json_profile_props": PROPS_SQL,
    }
