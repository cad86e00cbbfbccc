"""Census workloads on the generated archive: harvest, links, flags, coverage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rules import CENSUS, CLEAR_RULES, PREFIXES, RAW
from ..operators import audit, classify, evidence, extraction, screen
from ..sources import archive
from ..sources.store import made, saved
from ..sources.tables import table
from . import sql

FAMILIES = ["linear", "count"]
KEYS = ["deposit_id", "file_id", "name"]
CLS = sql.stats(archive.CELLS_SQL, KEYS)
CLEAR = "class IN ('count', 'proportion')"
SCREENED = "class IN ('count', 'proportion', 'binary', 'ordinal')"
LINKS_SQL = f"""WITH {CLS}, truth AS ({archive.TRUTH_SQL}),
links AS (SELECT t.deposit_id, t.collection, t.command, t.estimator, t.family, t.response, t.place, t.design, t.plain, c.file_id AS data_file, c.class, c.n, c.all_integer
          FROM truth t JOIN cls c ON c.deposit_id = t.deposit_id AND c.name = t.response WHERE t.grp >= 70),
records AS (SELECT deposit_id, estimator, family, response AS outcome, class, n FROM links
          QUALIFY row_number() OVER (PARTITION BY deposit_id, estimator, family, response ORDER BY n DESC, data_file) = 1),
flags AS (SELECT *, CASE WHEN {CLEAR} THEN 'clear' ELSE 'debated' END AS tier FROM records WHERE family = 'linear' AND {SCREENED})"""


class Census:
    """One run over the archive.  Evidence, commands, links and flags are written
    once for a version of the tables and read by every query after that."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def saved(self, name: str, build) -> DataFrame:
        return saved(self.spark, f"census-{name}", self._inputs, build)

    def made(self, name: str) -> DataFrame | None:
        """What was saved before, if it was."""
        return made(self.spark, f"census-{name}", self._inputs)

    @property
    def _inputs(self) -> list[str]:
        return [f"{self.sf_dir}/{t}.parquet" for t in ("part", "lineitem")]

    @property
    def files(self) -> DataFrame:
        return archive.files(self.spark, self.sf_dir)

    def profiled(self, *, capped: bool = True) -> DataFrame:
        """Evidence of every column, from the cells."""
        cells = archive.cells(self.spark, self.sf_dir)
        if capped:
            cells = extraction.kept_files(cells, self.files)
        return evidence.profile_cells(cells, KEYS)

    def evidence(self, *, capped: bool = True) -> DataFrame:
        if not capped:
            return self.saved("evidence-all", lambda: self.profiled(capped=False))
        # A file's evidence is the same with and without the cap: once made for all files, it is not made again.
        every = self.made("evidence-all")
        return self.saved("evidence", self.profiled if every is None else lambda: extraction.kept_files(every, self.files, merge=True))

    @property
    def profiles(self) -> DataFrame:
        return classify.classified(self.evidence())

    def read(self, *, capped: bool = True, prefixes: tuple[str, ...] = PREFIXES) -> DataFrame:
        """Commands of the scripts."""

        def build() -> DataFrame:
            scripts = archive.scripts(self.spark, self.sf_dir)
            if capped:
                scripts = extraction.kept_files(scripts, self.files, merge=True)
            return extraction.pairs(extraction.logical_lines(scripts), prefixes=prefixes)

        return self.saved(f"read-{capped}-{len(prefixes)}", build)

    @property
    def links(self) -> DataFrame:
        names = lambda: self.profiles.select("deposit_id", F.col("file_id").alias("data_file"), "name", "class", "n", "all_integer")
        return self.saved("links", lambda: extraction.match_outcomes(self.read(), names()))

    @property
    def flags(self) -> DataFrame:
        return self.saved("flags", lambda: screen.flagged(self.links))


def by_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole profile, from the cells."""
    return classify.classified(Census(spark, sf_dir).profiled()).select("deposit_id", "file_id", "name", "n", "n_distinct", "class")


def code_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Census(spark, sf_dir).read().select(
        "deposit_id", "command", "estimator", "family", "response", F.array_join("design", " ").alias("design"), "excluded"
    )


def code_pairs_negative(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prose holds no estimator call."""
    docs = table(spark, sf_dir, "documents").select(
        F.col("doc_id").alias("deposit_id"), F.lit("text").alias("file_id"), F.explode(F.array(F.lit("stata"), F.lit("r"))).alias("lang"), "text"
    )
    return extraction.pairs(extraction.logical_lines(docs)).agg(F.count("*").alias("n_pairs"))


def prefix_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deposits and records read with and without harvest limits and the survey
    prefix."""
    census, out = Census(spark, sf_dir), None
    for capped, prefixes, name in ((True, PREFIXES, "census"), (False, PREFIXES, "uncapped"), (True, (*PREFIXES, "svy"), "with survey prefix")):
        one = census.read(capped=capped, prefixes=prefixes).agg(
            F.lit(name).alias("variant"), F.countDistinct("deposit_id").alias("n_deposits"), F.count("*").alias("n_records")
        )
        out = one if out is None else out.unionByName(one)
    return out


VARIANTS_SQL = f"""WITH truth AS ({archive.TRUTH_SQL}), svy AS (SELECT p_partkey AS deposit_id FROM part WHERE p_partkey % 100 BETWEEN 10 AND 38 AND p_partkey % 2 = 0)
SELECT 'census' AS variant, count(DISTINCT deposit_id) AS n_deposits, count(*) AS n_records FROM truth WHERE grp >= 39
UNION ALL SELECT 'uncapped', count(DISTINCT deposit_id), count(*) FROM truth
UNION ALL SELECT 'with survey prefix', count(DISTINCT deposit_id), count(*) FROM (SELECT deposit_id FROM truth WHERE grp >= 39 UNION ALL FROM svy)"""


def sibling_code(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Commands of deposits that share the next deposit's code; the locator
    keeps the true holder."""
    deposits, scripts = archive.deposits(spark, sf_dir), archive.scripts(spark, sf_dir)
    key = F.col("deposit_id")
    shared = deposits.select(F.when(key % 9 == 0, key).alias("deposit_id"), F.when(key % 9 == 0, key + 1).alias("sibling_id")).dropna()
    lines = extraction.logical_lines(extraction.attach_sibling(deposits, scripts, shared))
    own = (F.col("deposit_id") == F.col("code_deposit_id")).alias("own_code")
    return extraction.pairs(lines).groupBy(own).agg(F.count("*").alias("n_records"), F.countDistinct("deposit_id").alias("n_deposits"))


SIBLING_SQL = f"""WITH truth AS ({archive.TRUTH_SQL}), s AS (SELECT p_partkey AS d FROM part WHERE p_partkey % 9 = 0)
SELECT TRUE AS own_code, count(*) AS n_records, count(DISTINCT deposit_id) AS n_deposits FROM truth
UNION ALL SELECT FALSE, count(*), count(DISTINCT d) FROM s JOIN truth ON deposit_id = d + 1"""


def pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Leftover directories: copies of harvested deposits, and some without an id."""
    key = F.col("deposit_id")
    mark = F.sha2(key.cast("string"), 256)
    harvested = archive.deposits(spark, sf_dir).select("deposit_id", mark.alias("checksum"))
    left = harvested.select(
        F.explode(F.when(key % 50 == 0, F.array(F.lit("copy"), F.lit("bare"))).when(key % 50 == 1, F.array(F.lit("new")))).alias("kind"), "deposit_id", "checksum"
    ).select(
        F.when(F.col("kind") != "bare", -1 - F.col("deposit_id")).alias("deposit_id"),
        F.when(F.col("kind") == "copy", F.col("checksum")).otherwise(F.concat("checksum", "kind")).alias("checksum"),
    )
    return extraction.clean_pool(left, harvested).groupBy("reason").agg(F.count("*").alias("n"))


POOL_SQL = """SELECT 'duplicate' AS reason, count(*) AS n FROM part WHERE p_partkey % 50 = 0 UNION ALL SELECT 'no_id', count(*) FROM part WHERE p_partkey % 50 = 0
UNION ALL SELECT 'kept', count(*) FROM part WHERE p_partkey % 50 = 1"""


def outcome_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Census(spark, sf_dir).links.select("deposit_id", "estimator", "family", "response", "column", "link_kind", "data_file", "class")


def _asked_logs(spark: SparkSession, sf_dir: str) -> DataFrame:
    key = F.col("p_partkey")
    response = F.when(key % 3 == 0, "lnbulk").when(key % 3 == 1, "l_disc").otherwise("log(bulk)")
    return table(spark, sf_dir, "part").select(key.alias("deposit_id"), response.alias("response"))


def log_prefix_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Responses with a log prefix link to the raw column unless a column has
    the whole name; a transformed response links to nothing."""
    names = Census(spark, sf_dir).profiles.where("file_id = 'data-1'").select("deposit_id", "name", "class")
    return extraction.match_outcomes(_asked_logs(spark, sf_dir), names).select("deposit_id", "response", "column", "link_kind", "class")


def logged_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The separate, optional check of logged responses whose raw column is a count."""
    names = Census(spark, sf_dir).profiles.where("file_id = 'data-1'").select("deposit_id", "name", "class")
    return screen.transformed(_asked_logs(spark, sf_dir), names).select("deposit_id", "response", "column", "alert_kind")


LOG_SQL = f"""WITH {CLS}, asked AS (SELECT p_partkey AS deposit_id, CASE p_partkey % 3 WHEN 0 THEN 'lnbulk' WHEN 1 THEN 'l_disc' ELSE 'log(bulk)' END AS response,
CASE p_partkey % 3 WHEN 1 THEN 'disc' ELSE 'bulk' END AS raw FROM part),
met AS (SELECT a.deposit_id, response, raw AS "column", class FROM asked a JOIN cls c ON a.deposit_id = c.deposit_id AND c.name = raw AND c.file_id = 'data-1')"""


def flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Census(spark, sf_dir).flags.drop("rule_version")


def clear_flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The archive under another rule table."""
    rules = screen.rule_table(spark, CLEAR_RULES)
    found = screen.flagged(Census(spark, sf_dir).links, rules=rules, version="clear-1")
    return found.groupBy("rule_version", "tier", "class").agg(F.count("*").alias("n"))


def questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records (deposit, estimator, outcome) and questions (deposit, outcome) by
    tier and class."""
    return Census(spark, sf_dir).flags.groupBy("tier", "class").agg(
        F.count("*").alias("n_records"), F.countDistinct("deposit_id", "outcome").alias("n_questions")
    )


def _status(census: Census) -> DataFrame:
    return screen.coverage(archive.deposits(census.spark, census.sf_dir), census.read(), census.links)


def coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deposits by status, by collection and in all."""
    return _status(Census(spark, sf_dir)).rollup("collection", "status").agg(
        F.count("*").alias("n"), F.max("limits").alias("limits")
    ).where("NOT (collection IS NOT NULL AND status IS NULL)").na.fill("all", ["collection", "status"])


COVERAGE_SQL = f"""WITH base AS ({archive._BASE_SQL}), have AS (SELECT DISTINCT l_partkey FROM lineitem),
s AS (SELECT collection, CASE WHEN grp < 39 THEN 'none' WHEN grp < 70 OR l_partkey IS NULL THEN 'unmatched' ELSE 'flaggable' END AS status
      FROM base LEFT JOIN have ON l_partkey = deposit_id)
SELECT collection, status, count(*) AS n, 'lower bound' AS limits FROM s GROUP BY collection, status UNION ALL SELECT 'all', 'all', count(*), 'lower bound' FROM s"""


def rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagged deposits in all, for each 1,000 and as a share of the base."""
    census = Census(spark, sf_dir)
    flagged = census.flags.select("deposit_id").distinct().withColumn("f", F.lit(1))
    s = _status(census).join(flagged, "deposit_id", "left")
    base = F.count_if(F.col("status") == "flaggable")
    return s.agg(
        F.count("*").alias("n_deposits"), base.alias("n_base"), F.count("f").alias("n_flagged"),
        F.round(1000 * F.count("f") / F.count("*"), 4).alias("per_1000"), F.round(F.count("f") / base, 6).alias("of_base"),
    )


RATES_SQL = f"""{LINKS_SQL}
SELECT n_deposits, n_base, n_flagged, round(1000 * n_flagged / n_deposits, 4) AS per_1000, round(n_flagged / n_base, 6) AS of_base FROM
(SELECT (SELECT count(*) FROM part) AS n_deposits, (SELECT count(DISTINCT deposit_id) FROM links) AS n_base, (SELECT count(DISTINCT deposit_id) FROM flags) AS n_flagged)"""


def _harvest(files, **limits):
    return lambda spark, sf_dir: extraction.apply_limits(files(spark, sf_dir), **limits).groupBy("kind", "reason").agg(
        F.count("*").alias("n"), F.sum("bytes").alias("bytes")
    )


def _harvest_sql(files: str, most: int | None = 8) -> str:
    reason = f"CASE WHEN NOT small THEN 'too_large' WHEN place > {most} THEN 'beyond_limit' ELSE 'kept' END" if most else "'kept'"
    return f"""WITH f AS ({files}), s AS (SELECT *, bytes <= {25 << 20} AS small FROM f),
r AS (SELECT *, row_number() OVER (PARTITION BY deposit_id, kind, small ORDER BY listing_order) AS place FROM s)
SELECT kind, {reason} AS reason, count(*) AS n, CAST(sum(bytes) AS BIGINT) AS bytes FROM r GROUP BY 1, 2"""


def family_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return screen.family_norms(Census(spark, sf_dir).links.join(archive.deposits(spark, sf_dir), "deposit_id"), "collection")


def find_outcomes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return screen.find_outcomes(Census(spark, sf_dir).links, "proportion", 25, 40)


def review_queue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 flags to review first: clear tier, most rows, then deposit."""
    census = Census(spark, sf_dir)
    lk = census.links
    rows = census.flags.select("deposit_id", "outcome", "class", "tier").distinct()
    n = lk.groupBy("deposit_id", F.col("column").alias("outcome")).agg(F.max("n").alias("n"))
    order = [F.col("tier"), F.desc("n"), F.col("deposit_id"), F.col("outcome")]
    return rows.join(n, ["deposit_id", "outcome"]).select("deposit_id", "outcome", "class", "tier", "n").orderBy(*order).limit(20)


QUEUE_SQL = f"{LINKS_SQL} SELECT DISTINCT deposit_id, outcome, class, tier, CAST(n AS BIGINT) AS n FROM flags ORDER BY tier, n DESC, deposit_id, outcome LIMIT 20"


def codebook(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Profiles beside a codebook that says what each column is."""
    said = spark.createDataFrame([(n, "share" if k == "proportion" else "units", k) for n, k in archive.RECORDED.items()], "name string, unit string, kind string")
    return audit.with_codebook(Census(spark, sf_dir).profiles, said, ["name"]).groupBy("name", "codebook_unit").agg(
        F.count("*").alias("n"), F.count_if("codebook_differs").alias("n_differ")
    )


CODEBOOK_SQL = f"""WITH {CLS}, said(name, kind) AS (VALUES {", ".join(f"('{n}', '{k}')" for n, k in archive.RECORDED.items())})
SELECT name, CASE WHEN kind IS NULL THEN NULL WHEN kind = 'proportion' THEN 'share' ELSE 'units' END AS codebook_unit, count(*) AS n,
  count(*) FILTER (class <> kind) AS n_differ FROM cls LEFT JOIN said USING (name) GROUP BY 1, 2"""


def raw_transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes of the archive's columns under the raw profiler and the census."""
    found = Census(spark, sf_dir).evidence()
    return classify.transitions(classify.classified(found, rules=RAW), classify.classified(found, rules=CENSUS), KEYS)


RAW_SQL = f"""WITH {sql.stats(archive.CELLS_SQL, KEYS, RAW, 'r_')}, {CLS}
SELECT r.class AS class_from, c.class AS class_to, count(*) AS n FROM r_cls r JOIN cls c USING (deposit_id, file_id, name) GROUP BY 1, 2"""


def queries():
    return {
        "corpus_profile_by_part": by_part,
        "code_pairs": code_pairs,
        "code_pairs_negative": code_pairs_negative,
        "harvest_variants": prefix_variants,
        "sibling_code": sibling_code,
        "pool_cleaning": pool,
        "outcome_links": outcome_links,
        "log_prefix_links": log_prefix_links,
        "logged_count_alerts": logged_counts,
        "census_flags": flags,
        "census_flags_other_rules": clear_flags,
        "census_questions": questions,
        "census_coverage": coverage,
        "census_rates": rates,
        "harvest_limits": _harvest(archive.listing),
        "harvest_archive": _harvest(archive.files),
        "harvest_uncapped": _harvest(archive.listing, max_bytes=None, max_per_kind=None),
        "family_norms": family_norms,
        "find_outcomes": find_outcomes,
        "review_queue_topk": review_queue,
        "codebook_report": codebook,
        "raw_profiler_transitions": raw_transitions,
    }


def oracle_sql():
    strata = "CASE class WHEN 'count' THEN 'count under linear' WHEN 'proportion' THEN 'share under linear' WHEN 'binary' THEN 'linear probability model' ELSE 'ordinal as continuous' END"
    return {
        "corpus_profile_by_part": f"WITH {CLS} SELECT deposit_id, file_id, name, CAST(n AS BIGINT) AS n, CAST(nd AS BIGINT) AS n_distinct, class FROM cls",
        "code_pairs": f"SELECT deposit_id, command, estimator, family, response, design, NOT plain AS excluded FROM ({archive.TRUTH_SQL}) WHERE grp >= 39",
        "code_pairs_negative": "SELECT CAST(0 AS BIGINT) AS n_pairs",
        "harvest_variants": VARIANTS_SQL,
        "sibling_code": SIBLING_SQL,
        "pool_cleaning": POOL_SQL,
        "outcome_links": f"""{LINKS_SQL} SELECT deposit_id, estimator, family, response, response AS "column", 'exact' AS link_kind, data_file, class FROM links""",
        "log_prefix_links": f"""{LOG_SQL} SELECT deposit_id, response, "column", 'log_prefix' AS link_kind, class FROM met WHERE response <> 'log(bulk)'""",
        "logged_count_alerts": f"""{LOG_SQL} SELECT deposit_id, response, "column", 'logged_count' AS alert_kind FROM met WHERE response = 'log(bulk)' AND class = 'count'""",
        "census_flags": f"{LINKS_SQL} SELECT deposit_id, estimator, family, outcome, class, tier, {strata} AS stratum FROM flags",
        "census_flags_other_rules": f"{LINKS_SQL} SELECT 'clear-1' AS rule_version, tier, class, count(*) AS n FROM flags WHERE tier = 'clear' GROUP BY tier, class",
        "census_questions": f"{LINKS_SQL} SELECT tier, class, count(*) AS n_records, count(DISTINCT (deposit_id, outcome)) AS n_questions FROM flags GROUP BY tier, class",
        "census_coverage": COVERAGE_SQL,
        "census_rates": RATES_SQL,
        "harvest_limits": _harvest_sql(archive.LISTING_SQL),
        "harvest_archive": _harvest_sql(archive.FILES_SQL),
        "harvest_uncapped": _harvest_sql(archive.LISTING_SQL, None),
        "family_norms": f"{LINKS_SQL} SELECT collection, class, family, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY collection, class), 6) AS share FROM links GROUP BY collection, class, family",
        "find_outcomes": f"{LINKS_SQL} SELECT DISTINCT deposit_id, response AS outcome, CAST(n AS BIGINT) AS n FROM links WHERE class = 'proportion' AND n BETWEEN 25 AND 40",
        "review_queue_topk": QUEUE_SQL,
        "codebook_report": CODEBOOK_SQL,
        "raw_profiler_transitions": RAW_SQL,
    }
