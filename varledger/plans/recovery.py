"""What the census recovers of the reference cases, and why it misses others.

The SQL knows the cases and the causes of misses from the generator's keys; the
queries find them by joins on what was harvested, read and profiled."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rules import CENSUS, PREFIXES, RAW
from ..operators import benchmark, classify, measures, screen
from ..sources import archive
from . import sql
from .archive import CLEAR, FAMILIES, KEYS, LINKS_SQL, SCREENED, Census

CASES_SQL = f"""{LINKS_SQL}, ref AS ({archive.CASES_SQL}), have AS (SELECT DISTINCT l_partkey FROM lineitem),
cases AS (SELECT ref.*, l_partkey IS NOT NULL AS stored,
  EXISTS (SELECT 1 FROM cls c WHERE c.deposit_id = ref.deposit_id AND c.name = ref.outcome) AS located,
  EXISTS (SELECT 1 FROM flags f WHERE f.deposit_id = ref.deposit_id) AS deposit_flagged,
  EXISTS (SELECT 1 FROM flags f WHERE f.deposit_id = ref.deposit_id AND f.outcome = ref.outcome) AS outcome_flagged
  FROM ref LEFT JOIN have ON l_partkey = deposit_id)"""


def _recovered(spark: SparkSession, sf_dir: str) -> DataFrame:
    flags = Census(spark, sf_dir).flags
    return screen.recovery(archive.cases(spark, sf_dir), flags, flags)


def recovery_deposit(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = _recovered(spark, sf_dir).groupBy("deposit_id", "label").agg(F.bool_or("deposit_flagged").alias("hit"))
    return d.groupBy("label").agg(F.count("*").alias("n_deposits"), F.count_if("hit").alias("n_flagged"))


def recovery_case(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _recovered(spark, sf_dir).groupBy("label").agg(
        F.count("*").alias("n_cases"), F.count_if("deposit_flagged").alias("n_in_flagged_deposit"), F.count_if("outcome_flagged").alias("n_outcome_flagged")
    )


def outcome_location(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cases whose outcome is a profiled column of the capped harvest."""
    return benchmark.located(archive.cases(spark, sf_dir), Census(spark, sf_dir).profiles)


def miss_reasons(spark: SparkSession, sf_dir: str) -> DataFrame:
    census = Census(spark, sf_dir)
    every = archive.cells(spark, sf_dir).select("deposit_id", "name").distinct()
    missed = benchmark.misses(
        archive.cases(spark, sf_dir), census.flags, read=census.read(), read_uncapped=census.read(capped=False),
        read_prefixed=census.read(prefixes=(*PREFIXES, "svy")), names=census.profiles, names_uncapped=every,
    )
    return missed.groupBy("reason").agg(F.count("*").alias("n"))


MISS_SQL = f"""{CASES_SQL} SELECT CASE WHEN grp < 10 THEN 'script_limit' WHEN grp < 39 AND deposit_id % 2 = 0 THEN 'prefix' WHEN grp < 39 THEN 'no_command'
  WHEN grp < 49 AND stored THEN 'data_limit' WHEN grp < 70 OR NOT stored THEN 'built_in_code' ELSE 'class' END AS reason, count(*) AS n
FROM cases WHERE label = 'mismatch' AND NOT outcome_flagged GROUP BY 1"""


def _confusion(kind: str):
    return lambda spark, sf_dir: screen.confusion(archive.cases(spark, sf_dir), Census(spark, sf_dir).links, kind)


def _confusion_sql(said: str) -> str:
    return f"""{CASES_SQL}, s AS (SELECT deposit_id, response AS outcome, bool_or(family = 'linear' AND {said}) AS s FROM links GROUP BY 1, 2),
j AS (SELECT label = 'mismatch' AS t, coalesce(s, FALSE) AS s FROM cases LEFT JOIN s USING (deposit_id, outcome))
SELECT count(*) FILTER (t AND s) AS tp, count(*) FILTER (NOT t AND s) AS fp, count(*) FILTER (t AND NOT s) AS fn, count(*) FILTER (NOT t AND NOT s) AS tn FROM j"""


def norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recorded class by family over the cases."""
    return screen.norm_map(archive.cases(spark, sf_dir), FAMILIES, cls="recorded_class")


def link_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return screen.norm_map(Census(spark, sf_dir).links, FAMILIES)


def _profiled(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Class of each stored outcome by the census gates and by the raw profiler,
    over all files (the reference outcomes were read one by one)."""
    found = Census(spark, sf_dir).evidence(capped=False).where("file_id = 'data-1'")
    return {n: classify.classified(found, rules=r).select("deposit_id", "name", "class") for n, r in (("census", CENSUS), ("raw", RAW))}


def profiler_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    cases, out = archive.cases(spark, sf_dir), None
    for name, profiles in _profiled(spark, sf_dir).items():
        one = benchmark.agreement(cases, profiles).withColumn("profiler", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def detector_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision and recall of the rule on the cases, with the recorded classes
    (saturated, since these define the labels) and with profiled ones."""
    cases = archive.cases(spark, sf_dir)
    sides = {"recorded": cases.select("deposit_id", F.col("outcome").alias("name"), F.col("recorded_class").alias("class")), **_profiled(spark, sf_dir)}
    out = None
    for name, profiles in sides.items():
        one = benchmark.detector(cases, profiles).withColumn("classes", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


_ALL = "SELECT * FROM (" + archive.ALL_CELLS_SQL + ") WHERE file_id = 'data-1'"
_BOTH = f"""WITH {sql.stats(_ALL, KEYS, CENSUS, 'c_')}, {sql.stats(_ALL, KEYS, RAW, 'r_')}, ref AS ({archive.CASES_SQL}),
sides AS (SELECT 'recorded' AS side, deposit_id, outcome AS name, recorded_class AS class FROM ref
  UNION ALL SELECT 'census', deposit_id, name, class FROM c_cls UNION ALL SELECT 'raw', deposit_id, name, class FROM r_cls),
j AS (SELECT k.side, ref.*, s.class FROM ref, (VALUES ('recorded'), ('census'), ('raw')) k(side) LEFT JOIN sides s ON s.side = k.side AND s.deposit_id = ref.deposit_id AND s.name = ref.outcome)"""
AGREEMENT_SQL = f"""{_BOTH} SELECT side AS profiler, count(*) AS n, count(class) AS n_located, count(*) FILTER (class = recorded_class) AS n_same FROM j WHERE side <> 'recorded' GROUP BY side"""
DETECTOR_SQL = f"""{_BOTH} SELECT side AS classes, count(*) FILTER (t AND s) AS tp, round(count(*) FILTER (t AND s) / count(*) FILTER (s), 6) AS precision, round(count(*) FILTER (t AND s) / count(*) FILTER (t), 6) AS recall
FROM (SELECT side, label = 'mismatch' AS t, coalesce(family = 'linear' AND {SCREENED}, FALSE) AS s FROM j) GROUP BY side"""


def candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return benchmark.candidates(Census(spark, sf_dir).links).groupBy("stratum").agg(
        F.count("*").alias("n_links"), F.countDistinct("deposit_id").alias("n_deposits")
    )


CANDIDATES_SQL = f"""{LINKS_SQL} SELECT CASE WHEN family = 'linear' AND class = 'count' THEN 'count-linear' WHEN family = 'count' AND class = 'count' THEN 'count-count'
  WHEN family = 'linear' AND class = 'proportion' THEN 'proportion' WHEN family = 'linear' AND class IN ('binary', 'ordinal') THEN 'binary/ordinal' ELSE 'other fields' END AS stratum,
  count(*) AS n_links, count(DISTINCT deposit_id) AS n_deposits FROM links GROUP BY 1"""


def recheck(spark: SparkSession, sf_dir: str) -> DataFrame:
    census = Census(spark, sf_dir)
    main = census.profiles.where("file_id = 'data-1'")
    checked = benchmark.recheck(archive.cases(spark, sf_dir), main, census.links)
    return checked.groupBy("resolves", "same_class", "link_confirmed").agg(F.count("*").alias("n"))


RECHECK_SQL = f"""{CASES_SQL} SELECT EXISTS (SELECT 1 FROM cls c WHERE c.deposit_id = k.deposit_id) AS resolves,
  EXISTS (SELECT 1 FROM cls c WHERE c.deposit_id = k.deposit_id AND c.name = k.outcome AND c.file_id = 'data-1' AND c.class = k.recorded_class) AS same_class,
  EXISTS (SELECT 1 FROM links l WHERE l.deposit_id = k.deposit_id AND l.response = k.outcome AND l.family = k.family) AS link_confirmed, count(*) AS n
FROM cases k GROUP BY 1, 2, 3"""


# -- adjudication ----------------------------------------------------------


def _verdict() -> F.Column:
    """A rubric in arithmetic: the flagged class is what the column is by its
    meaning, and every sixth such fit is a defensible approximation."""
    meant = F.create_map(*[F.lit(x) for kv in archive.RECORDED.items() for x in kv])[F.col("outcome")]
    return (meant == F.col("class")) & (F.col("deposit_id") % 6 != 0)


_MEANT = "CASE outcome " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in archive.RECORDED.items()) + " END"
_VERDICT_SQL = f"{_MEANT} = class AND deposit_id % 6 <> 0"


def positives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three definitions of a positive side by side, over questions: member of
    the reference cases, selected by the rule, credited by the rubric."""
    selected = Census(spark, sf_dir).flags.where("tier = 'clear'").select("deposit_id", "outcome", "class").distinct()
    return benchmark.positives(archive.cases(spark, sf_dir), selected.withColumn("credited", _verdict())).groupBy(
        "member", "selected", "credited"
    ).agg(F.count("*").alias("n"))


POSITIVES_SQL = f"""{CASES_SQL}, q AS (SELECT DISTINCT deposit_id, outcome, class FROM flags WHERE tier = 'clear'),
u AS (SELECT coalesce(k.deposit_id, q.deposit_id) AS d, k.deposit_id IS NOT NULL AS member, q.deposit_id IS NOT NULL AS selected, coalesce({_VERDICT_SQL.replace('outcome', 'q.outcome').replace('deposit_id', 'q.deposit_id')}, FALSE) AS credited
  FROM (SELECT deposit_id, outcome FROM cases WHERE label = 'mismatch') k FULL JOIN q ON k.deposit_id = q.deposit_id AND k.outcome = q.outcome)
SELECT member, selected, credited, count(*) AS n FROM u GROUP BY 1, 2, 3"""


def _clear(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Census(spark, sf_dir).flags.where("tier = 'clear'").withColumn("record_id", F.concat_ws("|", "deposit_id", "estimator", "outcome"))


def adjudicated_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision over all clear questions by class, with Wilson bounds."""
    q = _clear(spark, sf_dir).select("deposit_id", "outcome", "class").distinct()
    return measures.precision(q.withColumn("positive", _verdict()), ["class"])


def draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sixty records a class, collapsed to questions after the draw, and sixty
    questions a class, made distinct before it."""
    records = _clear(spark, sf_dir)
    after = measures.stratified_draw(records, "class", "record_id", 60)
    distinct = records.groupBy("class", "deposit_id", "outcome").agg(F.min("record_id").alias("record_id"))
    before = measures.stratified_draw(distinct, "class", "record_id", 60)
    out = None
    for name, drawn in (("collapsed after", after), ("distinct before", before)):
        one = drawn.groupBy("class").agg(
            F.lit(name).alias("policy"), F.count("*").alias("n_drawn"), F.countDistinct("deposit_id", "outcome").alias("n_questions")
        )
        out = one if out is None else out.unionByName(one)
    return out


DRAWS_SQL = f"""{LINKS_SQL}, r AS (SELECT *, deposit_id || '|' || estimator || '|' || outcome AS id FROM flags WHERE {CLEAR}),
a AS (SELECT 'collapsed after' AS policy, class, deposit_id, outcome, row_number() OVER (PARTITION BY class ORDER BY md5(id), id) AS k FROM r),
d AS (SELECT class, deposit_id, outcome, min(id) AS id FROM r GROUP BY 1, 2, 3),
b AS (SELECT 'distinct before' AS policy, class, deposit_id, outcome, row_number() OVER (PARTITION BY class ORDER BY md5(id), id) AS k FROM d)
SELECT policy, class, count(*) AS n_drawn, count(DISTINCT (deposit_id, outcome)) AS n_questions FROM (FROM a UNION ALL FROM b) WHERE k <= 60 GROUP BY 1, 2"""


def weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision by record weight: a question counts once over its records."""
    records = _clear(spark, sf_dir).groupBy("class", "deposit_id", "outcome").agg(F.count("*").alias("n_records"))
    return measures.inverse_record_precision(records.withColumn("positive", _verdict()), ["class"])


WEIGHTED_SQL = f"""{LINKS_SQL}, q AS (SELECT class, deposit_id, outcome, count(*) AS n FROM flags WHERE {CLEAR} GROUP BY 1, 2, 3)
SELECT class, round(sum(CASE WHEN {_VERDICT_SQL} THEN 1.0 / n ELSE 0 END) / sum(1.0 / n), 6) AS precision FROM q GROUP BY class"""


def queries():
    return {
        "screen_confusion": _confusion("screen"),
        "bare_rule_confusion": _confusion("bare"),
        "datatype_only_confusion": _confusion("datatype"),
        "scale_only_confusion": _confusion("scale"),
        "norm_map": norms,
        "norm_map_links": link_norms,
        "recovery_deposit": recovery_deposit,
        "recovery_case": recovery_case,
        "outcome_location": outcome_location,
        "miss_reasons": miss_reasons,
        "profiler_agreement": profiler_agreement,
        "detector_scores": detector_scores,
        "benchmark_candidates": candidates,
        "benchmark_recheck": recheck,
        "positives_three_ways": positives,
        "adjudicated_precision": adjudicated_precision,
        "adjudication_draws": draws,
        "adjudicated_precision_weighted": weighted,
    }


def oracle_sql():
    from .statistics import WILSON

    return {
        "screen_confusion": _confusion_sql(SCREENED),
        "bare_rule_confusion": _confusion_sql("class <> 'continuous'"),
        "datatype_only_confusion": _confusion_sql("all_integer"),
        "scale_only_confusion": _confusion_sql("class IN ('binary', 'categorical', 'ordinal')"),
        "norm_map": f"SELECT recorded_class AS class, count(*) FILTER (family = 'linear') AS linear, count(*) FILTER (family = 'count') AS count FROM ({archive.CASES_SQL}) GROUP BY 1",
        "norm_map_links": f"{LINKS_SQL} SELECT class, count(*) FILTER (family = 'linear') AS linear, count(*) FILTER (family = 'count') AS count FROM links GROUP BY class",
        "recovery_deposit": f"{CASES_SQL} SELECT label, count(DISTINCT deposit_id) AS n_deposits, count(DISTINCT CASE WHEN deposit_flagged THEN deposit_id END) AS n_flagged FROM cases GROUP BY label",
        "recovery_case": f"{CASES_SQL} SELECT label, count(*) AS n_cases, count(*) FILTER (deposit_flagged) AS n_in_flagged_deposit, count(*) FILTER (outcome_flagged) AS n_outcome_flagged FROM cases GROUP BY label",
        "outcome_location": f"{CASES_SQL} SELECT label, count(*) AS n_cases, count(*) FILTER (located) AS n_located, round(count(*) FILTER (located) / count(*), 6) AS rate FROM cases GROUP BY label",
        "miss_reasons": MISS_SQL,
        "profiler_agreement": AGREEMENT_SQL,
        "detector_scores": DETECTOR_SQL,
        "benchmark_candidates": CANDIDATES_SQL,
        "benchmark_recheck": RECHECK_SQL,
        "positives_three_ways": POSITIVES_SQL,
        "adjudicated_precision": f"{LINKS_SQL}, q AS (SELECT DISTINCT class, deposit_id, outcome FROM flags WHERE {CLEAR}), g AS (SELECT class, count(*) AS n, count(*) FILTER ({_VERDICT_SQL}) AS k FROM q GROUP BY class) SELECT class, n, k, round(k / n, 6) AS share, {WILSON} FROM g",
        "adjudication_draws": DRAWS_SQL,
        "adjudicated_precision_weighted": WEIGHTED_SQL,
    }
