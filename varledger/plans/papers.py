"""Pairing papers with deposits, and the fingerprint of each paired paper.

Extractors A to D replay responses that follow from the case, arm and
extractor; the keyword reader and the two-step baseline read the requests; the
code layer repeats the census links.  The SQL derives every answer from keys.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import classify, fingerprint
from ..operators.joins import grown
from ..sources import archive
from ..sources.store import stored
from ..sources.tables import table
from . import sql
from .archive import KEYS, Census

ARMS = ("text+metadata", "text+metadata+code")
EXTRACTORS = ("A", "B", "C", "D")


def _labels(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([("qty_share", "ordered share of the limit"), ("bulk", "units in bulk")], "name string, label string")


def _sheets(census: Census) -> DataFrame:
    """Sheets over all files: the harvest cap does not bind this layer."""
    return fingerprint.metadata_sheet(classify.classified(census.evidence(capped=False)), _labels(census.spark))


def sheet(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _sheets(Census(spark, sf_dir)).select("deposit_id", "n_variables", F.inline("sheet"))
    return rows.select("deposit_id", "n_variables", "name", "label", "type", F.round("low", 4).alias("low"), F.round("high", 4).alias("high"), "n_distinct", "n_present")


_ALL_CLS = sql.stats(archive.ALL_CELLS_SQL, KEYS)
_MAIN = "main AS (SELECT * FROM cls QUALIFY row_number() OVER (PARTITION BY deposit_id, name ORDER BY n DESC, file_id) = 1)"
SHEET_SQL = f"""WITH {_ALL_CLS}, {_MAIN} SELECT deposit_id, count(*) OVER (PARTITION BY deposit_id) AS n_variables, name,
  CASE name WHEN 'qty_share' THEN 'ordered share of the limit' WHEN 'bulk' THEN 'units in bulk' END AS label, CASE WHEN all_integer THEN 'integer' ELSE 'double' END AS type,
  round(vmin, 4) AS low, round(vmax, 4) AS high, CAST(CASE WHEN nd <= 25 THEN nd END AS BIGINT) AS n_distinct, CAST(nonnull AS BIGINT) AS n_present FROM main"""


# -- pairing ---------------------------------------------------------------


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    deposits, papers = archive.deposits(spark, sf_dir), archive.papers(spark, sf_dir)
    return fingerprint.resolve(
        deposits, fingerprint.by_doi(deposits, papers), fingerprint.by_title(deposits, papers), archive.by_hand(spark, sf_dir)
    )


def pairing_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How deposits meet their papers: by DOI, else title, else by hand."""
    right = F.count_if(F.col("deposit_id") == F.col("paper_id"))
    return _pairs(spark, sf_dir).groupBy("method").agg(F.count("*").alias("n"), right.alias("n_right"))


_METHOD = "CASE WHEN p_partkey % 11 <> 0 AND p_partkey % 4 = 0 THEN 'doi' WHEN p_partkey % 11 <> 0 THEN 'title' WHEN p_partkey % 22 = 0 THEN 'manual' ELSE 'unresolved' END"
METHODS_SQL = f"SELECT {_METHOD} AS method, count(*) AS n, count(*) FILTER ({_METHOD} <> 'unresolved') AS n_right FROM part GROUP BY 1"


def _titled(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Every page as a paper, and as a deposit named after it; each third
    deposit carries a title of its own, which no page has."""
    title = F.regexp_extract("html", r"<title>([^<]*)</title>", 1)
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("paper_id"), title.alias("title"))
    own = F.when(F.col("paper_id") % 3 == 0, F.concat(F.lit("unpublished zzq"), F.col("paper_id").cast("string"))).otherwise(F.col("title"))
    return pages.select(F.col("paper_id").alias("deposit_id"), F.concat(F.lit("Replication Data for: "), own).alias("title")), pages


def pairing_by_title(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.by_title(*_titled(spark, sf_dir)).select("deposit_id", "paper_id")


def pairing_status(spark: SparkSession, sf_dir: str) -> DataFrame:
    deposits, papers = _titled(spark, sf_dir)
    return fingerprint.resolve(deposits, fingerprint.by_title(deposits, papers)).groupBy("method").agg(
        F.count("*").alias("n"), F.countDistinct("paper_id").alias("n_papers")
    )


TITLE_SQL = r"""WITH t AS (SELECT page_id, ' ' || trim(regexp_replace(lower(regexp_extract(html, '<title>([^<]*)</title>', 1)), '[^\p{L}\p{Nd}]+', ' ', 'g')) || ' ' AS t FROM pages),
p AS (SELECT DISTINCT a.page_id AS deposit_id, b.page_id AS paper_id FROM (SELECT page_id, CASE WHEN page_id % 3 = 0 THEN ' unpublished zzq' || page_id || ' ' ELSE t END AS t FROM t) a
JOIN (SELECT * FROM t WHERE t <> '  ') b ON a.t <> '  ' AND (contains(b.t, a.t) OR contains(a.t, b.t)))"""


# -- records ---------------------------------------------------------------


def _replayed(asked: DataFrame) -> DataFrame:
    """Responses of A to D: exact picks, twins, predictor-only picks, refusals,
    unknown columns, contradicted and unstated families, malformed text."""
    spark = asked.sparkSession
    who = spark.createDataFrame([(i, e) for i, e in enumerate(EXTRACTORS)], "ei int, extractor string")
    c, ai = F.col("deposit_id"), F.when(F.col("arm") == ARMS[1], 1).otherwise(0)
    g = c % 100
    roll = (c * 7 + F.col("ei") * 3 + ai * 5) % 20
    want = F.concat(F.when((g >= 49) & (g < 70), F.lit("built_")).otherwise(F.lit("")), archive._pick(archive.OUTCOMES, c))
    column = F.when(roll == 15, archive._pick(archive.OUTCOMES, c + 1)).when(roll == 14, "price").when(roll == 17, "not in the metadata").when(roll == 19, "no_such").otherwise(want)
    fam = (c + F.col("ei") + ai) % 9
    family = F.when(fam < 2, "not stated").when(fam == 2, "proportion").otherwise(F.when((c % 7).isin(3, 4), "count").otherwise("linear"))
    row = F.array(F.struct(
        want.alias("outcome"), family.alias("family"), F.lit("headline").alias("role"), column.alias("column"),
        F.when(roll == 16, "predictor").otherwise("outcome").alias("use"),
    ))
    response = F.when(roll == 18, "[{outcome: broken").otherwise(F.to_json(row))
    return asked.select("request_id", "deposit_id", "arm").join(F.broadcast(who)).select("request_id", "extractor", response.alias("response"))


def _scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    census = Census(spark, sf_dir)
    return census.saved("scores", lambda: _scored(census))


def _scored(census: Census) -> DataFrame:
    spark, sf_dir = census.spark, census.sf_dir
    sheets = census.saved("sheets", lambda: _sheets(census))
    pairs = stored(_pairs(spark, sf_dir).where("paper_id IS NOT NULL"), "paper-pairs")
    papers, scripts = archive.papers(spark, sf_dir), archive.scripts(spark, sf_dir)
    arms = [fingerprint.requests(pairs, papers, sheets), fingerprint.requests(pairs, papers, sheets, scripts)]
    asked = stored(arms[0].unionByName(arms[1]), "paper-requests")
    text_only = asked.where(F.col("arm") == ARMS[0])
    said = fingerprint.replay(asked, _replayed(asked)).unionByName(
        fingerprint.extract(asked, fingerprint.extract_keywords).withColumn("extractor", F.lit("keyword"))
    ).unionByName(
        fingerprint.extract_two_step(text_only, fingerprint.distil_keywords, fingerprint.extract_keywords).withColumn("extractor", F.lit("two-step"))
    )
    arm = F.when(F.col("extractor") == "two-step", "comparators").otherwise(F.col("arm"))
    records = said.join(grown(asked.select("request_id", "deposit_id", "arm")), "request_id").select(
        "deposit_id", arm.alias("arm"), "extractor", F.col("deposit_id").alias("case_id"), "response"
    )
    links = census.links.join(grown(pairs.select("deposit_id")), "deposit_id", "left_semi").where("data_file = 'data-1'")
    rows = fingerprint.guard(fingerprint.parse(records).unionByName(fingerprint.from_code(links)), sheets)
    cases = archive.cases(spark, sf_dir).select(F.col("deposit_id").alias("case_id"), F.col("outcome").alias("column"), "family")
    return fingerprint.score(rows, cases, archive.twins(spark, sf_dir))


_PICK = "CASE p % 5 " + " ".join(f"WHEN {i} THEN '{o}'" for i, o in enumerate(archive.OUTCOMES)) + " END"
_TWIN = _PICK.replace("p % 5", "(p + 1) % 5")
_WANT = f"CASE WHEN p % 100 BETWEEN 49 AND 69 THEN 'built_' ELSE '' END || {_PICK}"
_FAMILY = "CASE WHEN p % 7 IN (3, 4) THEN 'count' ELSE 'linear' END"
SCORES_SQL = f"""WITH {_ALL_CLS}, {_MAIN}, truth AS ({archive.TRUTH_SQL}),
k AS (SELECT p, {_WANT} AS want, {_TWIN} AS twin, {_FAMILY} AS fam FROM (SELECT p_partkey AS p FROM part)
  WHERE (p % 11 <> 0 OR p % 22 = 0) AND p IN (SELECT deposit_id FROM main)),
said AS (SELECT *, CASE p % 20 WHEN 15 THEN twin WHEN 17 THEN 'none' ELSE want END AS pick FROM k),
kw AS (SELECT p, CASE WHEN pick IN (SELECT name FROM main m WHERE m.deposit_id = p) THEN pick ELSE 'not in the metadata' END AS col, CASE WHEN p % 20 = 18 THEN 'predictor' ELSE 'outcome' END AS use,
  CASE WHEN p % 4 = 3 THEN 'not stated' ELSE fam END AS text_fam,
  CASE WHEN p % 4 <> 3 THEN fam WHEN p % 100 BETWEEN 10 AND 38 THEN CASE WHEN p % 2 = 0 THEN 'linear' ELSE 'not stated' END ELSE fam END AS code_fam FROM said),
re AS (SELECT p, arm, e, (p * 7 + ei * 3 + ai * 5) % 20 AS roll, (p + ei + ai) % 9 AS fr, want, twin, fam
  FROM k, (VALUES {", ".join(f"({i}, '{a}')" for i, a in enumerate(ARMS))}) a(ai, arm), (VALUES {", ".join(f"({i}, '{e}')" for i, e in enumerate(EXTRACTORS))}) x(ei, e)),
rec AS (SELECT arm, e AS extractor, p, CASE roll WHEN 15 THEN twin WHEN 14 THEN 'price' WHEN 17 THEN 'not in the metadata' WHEN 19 THEN 'no_such' ELSE want END AS col,
    CASE WHEN fr < 2 THEN 'not stated' WHEN fr = 2 THEN 'proportion' ELSE fam END AS fam, CASE WHEN roll = 16 THEN 'predictor' ELSE 'outcome' END AS use, roll = 18 AS bad FROM re
  UNION ALL SELECT '{ARMS[0]}', 'keyword', p, col, text_fam, use, FALSE FROM kw UNION ALL SELECT '{ARMS[1]}', 'keyword', p, col, code_fam, use, FALSE FROM kw
  UNION ALL SELECT 'comparators', 'two-step', p, col, CASE WHEN text_fam = 'linear' THEN 'linear' ELSE 'not stated' END, use, FALSE FROM kw
  UNION ALL SELECT 'comparators', 'code layer', deposit_id, response, family, 'outcome', FALSE FROM truth
    WHERE grp >= 70 AND deposit_id IN (SELECT p FROM k)),
j AS (SELECT rec.*, want, twin, k.fam AS want_fam, CASE WHEN bad THEN 'malformed' WHEN col = 'not in the metadata' THEN 'not_in_metadata' WHEN name IS NULL THEN 'unknown_column'
    WHEN (rec.fam = 'count' AND NOT (all_integer AND vmin >= 0)) OR (rec.fam = 'proportion' AND NOT (vmin >= 0 AND vmax <= 1)) THEN 'inconsistent' ELSE 'accepted' END AS status
  FROM rec JOIN k USING (p) LEFT JOIN main ON main.deposit_id = p AND main.name = col),
f AS (SELECT *, status = 'accepted' AND use = 'outcome' AS used FROM j),
g AS (SELECT arm, extractor, p AS case_id, bool_or(used AND col = want) AS exact, bool_or(used AND col = twin AND col <> want) AS other, bool_or(used AND col IN (want, twin)) AS link,
    bool_or(NOT bad AND use = 'outcome' AND fam = want_fam) AS family, bool_or(used AND col IN (want, twin) AND fam = want_fam) AS link_family, bool_or(used AND col IN (want, twin) AND fam <> 'not stated') AS stated,
    bool_or(used) AS any_used, bool_or(status = 'accepted' AND use = 'predictor') AS predictor, min(status) AS status FROM f GROUP BY 1, 2, 3),
s AS (SELECT arm, extractor, case_id, exact, other AND NOT exact AS derived, link, family, link_family, CASE WHEN link_family THEN NULL WHEN link AND stated THEN 'contradicted' WHEN link THEN 'not_stated'
    WHEN any_used THEN 'wrong_column' WHEN predictor THEN 'predictor_only' ELSE status END AS miss FROM g)"""


def queries():
    return {
        "metadata_sheet": sheet,
        "pairing_methods": pairing_methods,
        "pairing_by_title": pairing_by_title,
        "pairing_status": pairing_status,
        "fingerprint_scores": _scores,
        "fingerprint_grid": lambda spark, sf_dir: fingerprint.grid(_scores(spark, sf_dir)),
        "fingerprint_movement": lambda spark, sf_dir: fingerprint.compare(_scores(spark, sf_dir), *ARMS),
        "fingerprint_misses": lambda spark, sf_dir: fingerprint.miss_kinds(_scores(spark, sf_dir)),
    }


def oracle_sql():
    counts = ", ".join(f"count(*) FILTER ({c}) AS n_{c}" for c in ("exact", "derived", "link", "family", "link_family"))
    return {
        "metadata_sheet": SHEET_SQL,
        "pairing_methods": METHODS_SQL,
        "pairing_by_title": f"{TITLE_SQL} SELECT deposit_id, paper_id FROM p",
        "pairing_status": f"{TITLE_SQL}, b AS (SELECT deposit_id, min(paper_id) AS paper_id FROM p GROUP BY deposit_id) SELECT CASE WHEN paper_id IS NULL THEN 'unresolved' ELSE 'title' END AS method, count(*) AS n, count(DISTINCT paper_id) AS n_papers FROM pages LEFT JOIN b ON deposit_id = page_id GROUP BY 1",
        "fingerprint_scores": f"{SCORES_SQL} SELECT * FROM s",
        "fingerprint_grid": f"{SCORES_SQL} SELECT arm, extractor, count(*) AS n_cases, {counts} FROM s GROUP BY arm, extractor",
        "fingerprint_movement": f"""{SCORES_SQL} SELECT coalesce(a.extractor, b.extractor) AS extractor, count(*) FILTER (b.link_family AND NOT a.link_family) AS gained, count(*) FILTER (a.link_family AND NOT b.link_family) AS lost,
  count(*) FILTER (a.link_family AND b.link_family) AS kept, count(*) FILTER ((a.exact AND b.derived) OR (a.derived AND b.exact)) AS changed
  FROM s a JOIN s b ON a.extractor = b.extractor AND a.case_id = b.case_id AND a.arm = '{ARMS[0]}' AND b.arm = '{ARMS[1]}' GROUP BY 1""",
        "fingerprint_misses": f"{SCORES_SQL} SELECT arm, extractor, miss AS kind, count(*) AS n FROM s WHERE NOT link_family GROUP BY 1, 2, 3",
    }
