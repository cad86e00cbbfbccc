"""Refits, measures and the batch twins of the streaming profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import ledger, lineage, measures, refit
from ..sources import archive
from ..sources.tables import ORDER_QUANTITIES_SQL, order_quantities, table
from ..streaming import ingest
from . import sql
from .archive import LINKS_SQL, Census


def _refit(frame, y: str, x: str, domain: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = frame(spark, sf_dir)
        fit = refit.ols(df, y, [x])
        c = fit["coefficients"]
        return refit.violation_share(df, y, [x], fit, domain).select(
            "n", F.round(F.lit(c[x]), 6).alias("slope"), F.round(F.lit(c["intercept"]), 5).alias("intercept"), F.round("share", 8).alias("share")
        )

    return run


def _refit_sql(frame: str, y: str, x: str, domain: str) -> str:
    bad = "f < -1e-6" if domain == "count" else "f < -1e-6 OR f > 1 + 1e-6"
    return f"""WITH d AS ({frame}), m AS (SELECT regr_slope({y}, {x}) AS b, regr_intercept({y}, {x}) AS a FROM d),
v AS (SELECT a + b * {x} AS f, a, b FROM d, m)
SELECT count(*) AS n, round(any_value(b), 6) AS slope, round(any_value(a), 5) AS intercept,
round(avg(CASE WHEN {bad} THEN 1.0 ELSE 0.0 END), 8) AS share FROM v"""


def _words(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "documents")
    return t.select(
        F.col("n_chars").cast("double").alias("n_chars"), (F.length("text") - F.length(F.replace("text", F.lit(" "), F.lit("")))).cast("double").alias("words"),
        (F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit("")))).cast("double").alias("newlines"), (F.col("n_chars") / 10000.0).alias("size"),
    )


WORDS_SQL = "SELECT CAST(n_chars AS DOUBLE) AS n_chars, CAST(length(text) - length(replace(text, ' ', '')) AS DOUBLE) AS words FROM documents"


def _glm(frame, y: str, x: str, family: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Whether the estimates solve the family's score equations, by a pass of
        its own over the rows, and whether the errors are positive."""
        rows = refit.complete(frame(spark, sf_dir), [y, x])
        fit = refit.glm(rows, y, [x], family=family)
        c = fit["coefficients"]
        eta = F.lit(c["intercept"]) + F.lit(c[x]) * F.col(x)
        mu = 1 / (1 + F.exp(-eta)) if family == "fraclogit" else F.exp(eta)
        weight = 1 / (1 + F.lit(fit["dispersion"]) * mu) if family == "negbin" else F.lit(1.0)
        off = weight * (F.col(y) - mu)
        scale = F.sum(F.abs(F.col(y))) + 1
        got = rows.agg(F.count("*").alias("n"), (F.abs(F.sum(off)) / scale).alias("intercept"), (F.abs(F.sum(off * F.col(x))) / scale).alias(x)).first()
        out = [(family, t, got.n, bool(got[t] < 1e-6), bool(fit["errors"][t] > 0)) for t in ("intercept", x)]
        return spark.createDataFrame(out, "family string, term string, n long, solved boolean, error_positive boolean")

    return run


def _glm_sql(table_: str, x: str, family: str) -> str:
    return f"SELECT '{family}' AS family, term, (SELECT count(*) FROM {table_}) AS n, TRUE AS solved, TRUE AS error_positive FROM (VALUES ('intercept'), ('{x}')) v(term)"


def refit_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least squares of a logged response, which is a variable of its own with a
    checked step from the raw one, and raises no alert as a raw count would."""
    raw = table(spark, sf_dir, "documents").select(F.col("n_chars").cast("double").alias("n_chars"), (F.length("text") - F.length(F.replace("text", F.lit(" "), F.lit("")))).cast("double").alias("words"))
    step = F.log("n_chars")
    df, _ = lineage.derive(raw, "ln_n_chars", "log", ["n_chars"], step)
    fit = refit.ols(df, "ln_n_chars", ["words"])
    c = fit["coefficients"]
    return lineage.verify(df, "ln_n_chars", step).select(
        "derived_variable", "n_mismatch", F.lit(fit["n"]).cast("long").alias("n"), F.round(F.lit(c["words"]), 8).alias("slope"), F.round(F.lit(c["intercept"]), 5).alias("intercept")
    )


LOG_OLS_SQL = """SELECT 'ln_n_chars' AS derived_variable, CAST(0 AS BIGINT) AS n_mismatch, count(*) AS n, round(regr_slope(y, words), 8) AS slope, round(regr_intercept(y, words), 5) AS intercept
FROM (SELECT ln(n_chars) AS y, CAST(length(text) - length(replace(text, ' ', '')) AS DOUBLE) AS words FROM documents)"""


def refit_within(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed effects as a transform: price on quantity within supplier."""
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_quantity", "l_extendedprice")
    fit = refit.ols(refit.within(li, ["l_extendedprice", "l_quantity"], ["l_suppkey"]), "l_extendedprice", ["l_quantity"])
    return spark.createDataFrame([(fit["n"], round(fit["coefficients"]["l_quantity"], 4))], "n long, slope double")


WITHIN_SQL = """SELECT count(*) AS n, round(regr_slope(y, x), 4) AS slope FROM (SELECT l_extendedprice - avg(l_extendedprice) OVER (PARTITION BY l_suppkey) AS y,
l_quantity - avg(l_quantity) OVER (PARTITION BY l_suppkey) AS x FROM lineitem)"""


#: Fits on one 0/1 term, of which group means give every coefficient.
GROUPED = ("poisson", "quasipoisson", "negbin", "fraclogit")


def _grouped_glm(family: str):
    y = "bulk_share" if family == "fraclogit" else "bulk_units"

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        o = order_quantities(spark, sf_dir).select("bulk_units", "bulk_share", (F.col("lines") > 4).cast("double").alias("many"))
        fit = refit.glm(o, y, ["many"], family=family)
        c = fit["coefficients"]
        rows = [(family, fit["n"], round(c["intercept"], 5), round(c["many"], 5))]
        out = spark.createDataFrame(rows, "family string, n long, intercept double, slope double")
        if family == "quasipoisson":
            out = out.withColumn("dispersion", F.round(F.lit(fit["dispersion"]), 4))
        return out

    return run


def _grouped_sql(family: str) -> str:
    y, link = ("bulk_share", "ln({m} / (1 - {m}))") if family == "fraclogit" else ("bulk_units", "ln({m})")
    a, b = link.format(m="m0"), link.format(m="m1")
    more = ", round(p / (n - 2), 4) AS dispersion" if family == "quasipoisson" else ""
    return f"""WITH o AS (SELECT CAST({y} AS DOUBLE) AS y, lines > 4 AS g FROM ({ORDER_QUANTITIES_SQL})), m AS (SELECT avg(y) FILTER (NOT g) AS m0, avg(y) FILTER (g) AS m1, count(*) AS n FROM o),
q AS (SELECT sum(pow(y - CASE WHEN g THEN m1 ELSE m0 END, 2) / CASE WHEN g THEN m1 ELSE m0 END) AS p FROM o, m)
SELECT '{family}' AS family, n, round({a}, 5) AS intercept, round({b} - {a}, 5) AS slope{more} FROM m, q"""


def _scaled_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = order_quantities(spark, sf_dir)
    return o.select("bulk_units", "bulk_share", (F.col("total_quantity") / 100).alias("total_100"), (F.col("mean_quantity") / 10).alias("mean_10"))


def _part_fits(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem")
    q = F.col("l_quantity")
    wide = li.select(F.col("l_partkey").alias("deposit_id"), (q / 50).alias("qty_share"), F.when(q >= 45, q).otherwise(0.0).alias("bulk"), F.col("l_extendedprice").alias("price"))
    share = refit.grouped(wide, ["deposit_id"], "qty_share", "price", domain="proportion").withColumn("outcome", F.lit("qty_share"))
    bulk = refit.grouped(wide, ["deposit_id"], "bulk", "price", domain="count").withColumn("outcome", F.lit("bulk"))
    return share.unionByName(bulk)


def refit_per_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-term fits of all parts in one aggregate and one join."""
    return _part_fits(spark, sf_dir).select("deposit_id", "outcome", "n", "n_outside")


_PART = """WITH d AS (SELECT l_partkey AS deposit_id, 'qty_share' AS outcome, l_quantity / 50 AS y, l_extendedprice AS x FROM lineitem
UNION ALL SELECT l_partkey, 'bulk', CASE WHEN l_quantity >= 45 THEN l_quantity ELSE 0 END, l_extendedprice FROM lineitem),
m AS (SELECT deposit_id, outcome, count(*) AS n, regr_slope(y, x) AS b, regr_intercept(y, x) AS a FROM d GROUP BY deposit_id, outcome HAVING count(*) >= 30),
s AS (SELECT m.deposit_id, m.outcome, m.n, count(*) FILTER (a + b * x < -1e-6 OR (m.outcome = 'qty_share' AND a + b * x > 1 + 1e-6)) AS n_outside
FROM d JOIN m USING (deposit_id, outcome) GROUP BY m.deposit_id, m.outcome, m.n)"""


# -- refits of the census flags --------------------------------------------


def _planned(census: Census) -> tuple[DataFrame, DataFrame]:
    """Clear flag records, and the fits planned for them."""
    clear = census.flags.where("tier = 'clear'")
    return clear, census.saved("refit-plan", lambda: refit.plan(clear, census.links.where("family = 'linear'"), census.profiles))


def refit_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, specs = _planned(Census(spark, sf_dir))
    return specs.groupBy("deposit_id", "estimator", "outcome", F.array_join("design", " ").alias("design"), "data_file").agg(
        F.count("*").alias("n_fits"), F.max("n_rows").alias("n_rows")
    )


def _fits(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    census = Census(spark, sf_dir)
    clear, specs = _planned(census)
    return clear, census.saved("refits", lambda: refit.fit_all(specs, archive.wide(spark, sf_dir)))


def refit_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fuller record of every attempted fit, with its file's checksum."""
    _, fits = _fits(spark, sf_dir)
    marks = ledger.file_checksums(archive.cells(spark, sf_dir)).withColumnRenamed("file_id", "data_file")
    return fits.join(marks, ["deposit_id", "data_file"]).select(
        "deposit_id", "estimator", "outcome", "data_file", "formula", "status", "n", "k", "n_outside",
        F.length("file_checksum").alias("checksum_length"), F.lit("complete cases").alias("row_scope"),
    )


def refit_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clear records by class: how many there are, how many a refit reaches, and
    the violations of their worst refits."""
    clear, fits = _fits(spark, sf_dir)
    keys = ["deposit_id", "estimator", "outcome"]
    summary = clear.select(*keys, "class").join(refit.summarise(fits, keys), keys, "left")
    n = summary.groupBy("class").agg(F.count("*").alias("n_records"), F.sum(F.coalesce("n_fits", F.lit(0))).alias("n_fits"))
    return n.join(refit.report(summary, by=["class"]), "class")


FITS_SQL = f"""{LINKS_SQL}, clear AS (SELECT * FROM flags WHERE tier = 'clear'),
spec AS (SELECT l.deposit_id, l.estimator, l.response AS outcome, c.class, l.place, l.design FROM links l JOIN clear c ON c.deposit_id = l.deposit_id AND c.estimator = l.estimator AND c.outcome = l.response
  WHERE l.plain AND l.family = 'linear' AND l.data_file = 'data-1' QUALIFY row_number() OVER (PARTITION BY l.deposit_id, l.estimator, l.response ORDER BY l.place) <= 8),
d AS (SELECT l_partkey AS deposit_id, l_quantity / 50 AS qty_share, CASE WHEN l_quantity >= 45 THEN l_quantity ELSE 0 END AS bulk, l_extendedprice AS price, l_extendedprice * l_discount AS product, l_linenumber AS line_no FROM lineitem),
r AS (SELECT s.deposit_id, estimator, s.outcome, class, place, design, CASE WHEN s.outcome = 'bulk' THEN bulk ELSE qty_share END AS y, CASE WHEN design = 'price:disc' THEN product ELSE price END AS x, line_no FROM spec s JOIN d USING (deposit_id)),
m AS (SELECT deposit_id, estimator, outcome, place, count(*) AS n, CASE WHEN any_value(design) = 'i.line_no' THEN count(DISTINCT line_no) ELSE 2 END AS k, regr_slope(y, x) AS b, regr_intercept(y, x) AS a FROM r GROUP BY 1, 2, 3, 4),
v AS (SELECT r.*, n, k, CASE WHEN design = 'i.line_no' THEN avg(y) OVER (PARTITION BY r.deposit_id, r.estimator, r.outcome, r.place, line_no) ELSE a + b * x END AS f FROM r JOIN m USING (deposit_id, estimator, outcome, place)),
fits AS (SELECT deposit_id, estimator, outcome, class, place, design, n, k, CASE WHEN n < 30 OR n < 3 * k THEN 'few_rows' ELSE 'fitted' END AS status,
  count(*) FILTER (f < -1e-6 OR (class = 'proportion' AND f > 1 + 1e-6)) AS n_outside FROM v GROUP BY ALL)"""


# -- adjudication and agreement -------------------------------------------


def _verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source")
    return table(spark, sf_dir, "labels").join(docs, "doc_id").withColumn("positive", F.col("quality") == 1)


def precision_by_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.precision(_verdicts(spark, sf_dir), ["lang"])


WILSON = """round((k / n + 3.8414588206941236 / (2 * n) - 1.959963984540054 * sqrt(k / n * (1 - k / n) / n + 3.8414588206941236 / (4.0 * n * n))) / (1 + 3.8414588206941236 / n), 6) AS low,
round((k / n + 3.8414588206941236 / (2 * n) + 1.959963984540054 * sqrt(k / n * (1 - k / n) / n + 3.8414588206941236 / (4.0 * n * n))) / (1 + 3.8414588206941236 / n), 6) AS high"""
WILSON_SQL = "SELECT {by}, n, k, round(k / n, 6) AS share, " + WILSON + """
FROM (SELECT {by}, count(*) AS n, count(*) FILTER (quality = 1) AS k FROM labels JOIN documents USING (doc_id) GROUP BY {by})"""


def precision_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stratum precisions weighted by the sizes of the whole strata."""
    sizes = table(spark, sf_dir, "documents").groupBy("source").agg(F.count("*").alias("weight"))
    strata = _verdicts(spark, sf_dir).groupBy("source").agg(F.count("*").alias("n"), F.count_if("positive").alias("k"))
    return measures.weighted_precision(strata.join(sizes, "source"))


def inverse_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = _verdicts(spark, sf_dir)
    n = v.groupBy("source").agg(F.count("*").alias("n_records"))
    return measures.inverse_record_precision(v.join(n, "source"), ["lang"])


def kappa(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.kappa(table(spark, sf_dir, "labels").withColumn("clean", 1 - F.col("toxic")), "quality", "clean")


def draw(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang")
    return measures.stratified_draw(docs, "lang", "doc_id", 60).select("lang", "doc_id", "draw")


# -- windows ---------------------------------------------------------------


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _shown(p: DataFrame, key: str) -> DataFrame:
    return p.select(F.col("window.start").cast("long").alias("start"), key, "n", "n_distinct", "vmax", "class")


def windowed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown(ingest.windowed_profile(_events(spark, sf_dir), by=["event_type"]), "event_type")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shown(ingest.windowed_profile(_events(spark, sf_dir), by=["event_type"], slide="1 day"), "event_type")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = ingest.session_profile(_events(spark, sf_dir), gap="1 hour")
    return _shown(p, "user_id")


_EPOCH = "CAST(floor(epoch(ts)) AS BIGINT)"
WINDOW_SQL = f"""WITH {sql.stats(f"SELECT {_EPOCH} // 604800 * 604800 AS start, event_type, value AS v FROM events", ['start', 'event_type'])}
SELECT start, event_type, CAST(n AS BIGINT) AS n, CAST(nd AS BIGINT) AS n_distinct, vmax, class FROM cls"""
SLIDING_SQL = f"""WITH {sql.stats(f"SELECT {_EPOCH} // 86400 * 86400 - 86400 * k AS start, event_type, value AS v FROM events, range(0, 7) r(k)", ['start', 'event_type'])}
SELECT start, event_type, CAST(n AS BIGINT) AS n, CAST(nd AS BIGINT) AS n_distinct, vmax, class FROM cls"""
SESSION_SQL = f"""WITH e AS (SELECT user_id, ts, value, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events),
g AS (SELECT user_id, ts, value, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM e),
f AS (SELECT user_id, value AS v, min({_EPOCH}) OVER (PARTITION BY user_id, s) AS start FROM g),
{sql.stats("SELECT user_id, start, v FROM f", ['user_id', 'start'])}
SELECT start, user_id, CAST(n AS BIGINT) AS n, CAST(nd AS BIGINT) AS n_distinct, vmax, class FROM cls"""


def queries():
    return {
        "refit_bulk_units": _refit(order_quantities, "bulk_units", "total_quantity", "count"),
        "refit_bulk_share": _refit(order_quantities, "bulk_share", "mean_quantity", "proportion"),
        "refit_returned_share": _refit(order_quantities, "returned_share", "mean_quantity", "proportion"),
        "refit_chars_words": _refit(_words, "n_chars", "words", "count"),
        "refit_per_part": refit_per_part,
        "refit_plan": refit_plan,
        "refit_records": refit_records,
        "refit_report": refit_report,
        "refit_log_ols": refit_log,
        "refit_within": refit_within,
        **{f"refit_groups_{f}": _grouped_glm(f) for f in GROUPED},
        "refit_poisson": _glm(_words, "newlines", "size", "poisson"),
        "refit_quasipoisson": _glm(_words, "newlines", "size", "quasipoisson"),
        "refit_fraclogit": _glm(_scaled_orders, "bulk_share", "mean_10", "fraclogit"),
        "refit_negbin": _glm(_scaled_orders, "bulk_units", "total_100", "negbin"),
        "precision_by_lang": precision_by_lang,
        "precision_weighted": precision_weighted,
        "precision_inverse_record": inverse_precision,
        "kappa_quality_toxic": kappa,
        "stratified_draw": draw,
        "windowed_profile": windowed,
        "sliding_profile": sliding,
        "session_profile": sessions,
    }


def oracle_sql():
    return {
        "refit_bulk_units": _refit_sql(ORDER_QUANTITIES_SQL, "bulk_units", "total_quantity", "count"),
        "refit_bulk_share": _refit_sql(ORDER_QUANTITIES_SQL, "bulk_share", "mean_quantity", "proportion"),
        "refit_returned_share": _refit_sql(ORDER_QUANTITIES_SQL, "returned_share", "mean_quantity", "proportion"),
        "refit_chars_words": _refit_sql(WORDS_SQL, "n_chars", "words", "count"),
        "refit_per_part": f"{_PART} SELECT deposit_id, outcome, n, n_outside FROM s",
        "refit_plan": f"{FITS_SQL} SELECT deposit_id, estimator, outcome, design, 'data-1' AS data_file, count(*) AS n_fits, CAST(max(n) AS BIGINT) AS n_rows FROM fits GROUP BY ALL",
        "refit_records": f"""{FITS_SQL} SELECT deposit_id, estimator, outcome, 'data-1' AS data_file, outcome || ' ~ ' || design AS formula, status, n, CASE WHEN n >= 30 THEN k END AS k,
CASE WHEN status = 'fitted' THEN n_outside END AS n_outside, 64 AS checksum_length, 'complete cases' AS row_scope FROM fits""",
        "refit_report": f"""{FITS_SQL}, one AS (SELECT deposit_id, estimator, outcome, count(*) AS n_fits, max(n_outside / n) AS share FROM fits WHERE status = 'fitted' GROUP BY 1, 2, 3)
SELECT class, count(*) AS n_records, CAST(coalesce(sum(n_fits), 0) AS BIGINT) AS n_fits, count(share) AS n_fitted, count(*) FILTER (share >= 0.01) AS n_at, count(*) FILTER (share > 0) AS n_any,
round(median(share) FILTER (share >= 0.01), 6) AS median_share, round(max(share) FILTER (share >= 0.01), 6) AS max_share FROM clear LEFT JOIN one USING (deposit_id, estimator, outcome) GROUP BY class""",
        "refit_log_ols": LOG_OLS_SQL,
        "refit_within": WITHIN_SQL,
        "refit_poisson": _glm_sql("documents", "size", "poisson"),
        "refit_quasipoisson": _glm_sql("documents", "size", "quasipoisson"),
        "refit_fraclogit": _glm_sql(f"({ORDER_QUANTITIES_SQL})", "mean_10", "fraclogit"),
        "refit_negbin": _glm_sql(f"({ORDER_QUANTITIES_SQL})", "total_100", "negbin"),
        **{f"refit_groups_{f}": _grouped_sql(f) for f in GROUPED},
        "precision_by_lang": WILSON_SQL.format(by="lang"),
        "precision_weighted": """SELECT round(sum(w * k / n) / sum(w), 6) AS precision, CAST(sum(w) AS BIGINT) AS weight FROM
(SELECT source, count(*) AS n, count(*) FILTER (quality = 1) AS k FROM labels JOIN documents USING (doc_id) GROUP BY source) JOIN (SELECT source, count(*) AS w FROM documents GROUP BY source) USING (source)""",
        "precision_inverse_record": """WITH v AS (SELECT lang, source, quality FROM labels JOIN documents USING (doc_id)), c AS (SELECT source, count(*) AS n FROM v GROUP BY source)
SELECT lang, round(sum(quality / n) / sum(1 / n), 6) AS precision FROM v JOIN c USING (source) GROUP BY lang""",
        "kappa_quality_toxic": """SELECT n, round(po, 6) AS agreement, round((po - pe) / (1 - pe), 6) AS kappa FROM (SELECT n, po, pa * pb + (1 - pa) * (1 - pb) AS pe FROM
(SELECT count(*) AS n, avg(CASE WHEN quality = 1 - toxic THEN 1.0 ELSE 0.0 END) AS po, avg(quality) AS pa, avg(1 - toxic) AS pb FROM labels))""",
        "stratified_draw": """SELECT lang, doc_id, CAST(draw AS INTEGER) AS draw FROM
(SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id) AS draw FROM documents) WHERE draw <= 60""",
        "windowed_profile": WINDOW_SQL,
        "sliding_profile": SLIDING_SQL,
        "session_profile": SESSION_SQL,
    }
