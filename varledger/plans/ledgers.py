"""The assertion ledger and its graph, built from the archive's census.

Identities are hashes of content, so the SQL compares what they stand for."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import graph, ledger, screen
from ..sources import archive
from .archive import LINKS_SQL, Census


def _roles(links: DataFrame) -> DataFrame:
    """The first command of a script is its headline (of every ninth deposit a
    placebo), the others are robustness checks; every tenth headline was first
    taken for a robustness check."""
    first = F.row_number().over(Window.partitionBy("deposit_id", "code_file").orderBy("line_no")) == 1
    key = F.col("deposit_id")
    rows = links.select("deposit_id", "code_file", "line_no").distinct().withColumn("_first", first)
    role = F.when(~F.col("_first"), "robustness").when(key % 9 == 4, "placebo").otherwise("headline")
    again = (role == "headline") & (key % 10 == 0)
    return rows.select("deposit_id", "code_file", "line_no", role.alias("role"), F.when(again, 2).otherwise(1).alias("at"), F.when(again, "robustness").alias("before"))


def _decisions(g: dict[str, DataFrame]) -> DataFrame:
    """Reviews of headline alerts by deposit modulo 5: all parts accepted; so,
    but a second reviewer rejects the alert; so, but its acceptance became
    unresolved; the alert alone rejected; none."""
    rows = ledger.headline_alerts(g).withColumn("k", F.split("dataset_version", "@")[0].cast("long") % 5)
    parts = ["role_id", "use_id", "estimator_id", "profile_id", "alert_id"]
    none = F.lit(None).cast("string")
    accepted = F.when(F.col("k") < 3, F.array(*[
        F.struct(F.col(p).alias("target_id"), F.lit("first").alias("reviewer"),
                 (F.when(F.col("k") == 2, "unresolved").otherwise("accepted") if p == "alert_id" else F.lit("accepted")).alias("state"), F.lit(3).alias("at"),
                 (F.when(F.col("k") == 2, "accepted") if p == "alert_id" else none).alias("first"))
        for p in parts
    ]))
    rejected = F.array(F.struct(F.col("alert_id").alias("target_id"), F.lit("second").alias("reviewer"), F.lit("rejected").alias("state"), F.lit(4).alias("at"), none.alias("first")))
    empty = F.slice(rejected, 1, 0)
    all_ = F.concat(F.coalesce(accepted, empty), F.when(F.col("k").isin(1, 3), rejected).otherwise(empty))
    # A profile can stand behind several alerts; it is decided on once.
    return rows.select(F.inline(all_)).distinct()


def records(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """The ledger of the archive, imported once for a version of its tables."""
    census = Census(spark, sf_dir)
    keep = lambda df, name: census.saved(f"ledger-{name}", lambda: df)
    position = F.array_position(F.array(*[F.lit(c) for c in archive.COLUMNS]), F.col("name")).cast("int") - 1
    datatype = F.when(F.col("all_integer"), "Integer").otherwise("Double")
    profiles = census.profiles.select("deposit_id", "file_id", "name", position.alias("position"), datatype.alias("datatype"), "class", "rule_version", "n")
    links = census.links
    largest = links.groupBy("deposit_id", "column").agg(F.min(F.struct(-F.col("n"), F.col("data_file")))["data_file"].alias("data_file"))
    main = keep(links.join(largest, ["deposit_id", "column", "data_file"]).withColumnRenamed("file_id", "code_file"), "main")
    marks = ledger.file_checksums(archive.cells(spark, sf_dir))
    return ledger.built(archive.deposits(spark, sf_dir), profiles, marks, main, _roles(main), _decisions, screen.rule_table(spark), keep=keep)


def _deposit() -> F.Column:
    return F.split("dataset_version", "@")[0].cast("long").alias("deposit_id")


def inventory(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.inventory(records(spark, sf_dir)).groupBy("role", "family").agg(F.count("*").alias("n"))


def alerts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.alerts(records(spark, sf_dir)).groupBy("role", "class", "tier").agg(F.count("*").alias("n"))


def headline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.headline_alerts(records(spark, sf_dir)).select(_deposit(), "response", "family", "class", "tier")


def reviewed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.reviewed(records(spark, sf_dir)).select(_deposit(), "response", "family", "class", "tier")


def review_states(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.review_state(records(spark, sf_dir)["review"]).groupBy("state").agg(F.count("*").alias("n"))


def roles_in_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    role = records(spark, sf_dir)["role"]
    views = {"as of 1": ledger.as_of(role, 1), "current": ledger.current(role)}
    out = None
    for name, rows in views.items():
        one = rows.groupBy("role").agg(F.lit(name).alias("view"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


def provenance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Current assertions by kind, source, method and review state."""
    return ledger.assertions(records(spark, sf_dir)).groupBy("kind", "source", "method", "state").agg(F.count("*").alias("n"))


def accepted_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One selection by all fields at once: accepted headline roles."""
    return ledger.selected(records(spark, sf_dir), kind="role", role="headline", source="paper text", method="manual", state="accepted").agg(F.count("*").alias("n"))


def summaries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.paper_summary(records(spark, sf_dir)).select(_deposit(), "headline_outcomes", F.size("derived_from").alias("n_derived_from"))


def accepted_outcomes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retrieval across the archive: accepted headline outcomes that are shares."""
    accepted = ledger.reviewed(records(spark, sf_dir)).select(_deposit(), F.col("response").alias("outcome")).distinct()
    return screen.find_outcomes(Census(spark, sf_dir).links, "proportion", 20, 60, accepted=accepted)


def imports_twice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same evidence imported again adds nothing; a changed extraction adds
    its own version and the old one stays."""
    use = records(spark, sf_dir)["use"]
    changed = use.limit(0).unionByName(use.withColumn("link_kind", F.lit("derived")).withColumn("assertion_id", ledger.content_id("analysis_id", "variable_id", "link_kind")))
    twice, grown = ledger.append(use, use), ledger.append(use, changed)
    n = lambda df, name: df.agg(F.lit(name).alias("step"), F.count("*").alias("n"))
    return n(use, "first").unionByName(n(twice, "again")).unionByName(n(grown, "changed"))


# -- graph -----------------------------------------------------------------


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counted from the nodes, none of which comes twice: no triple is written."""
    kind = F.split("s", "/")[0].alias("kind")
    return graph.nodes(records(spark, sf_dir)).groupBy(kind).agg(F.count("s").alias("n_nodes"), F.sum(F.size("cells").cast("long")).alias("n_triples"))


def export_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = Census(spark, sf_dir).saved("ledger-triples", lambda: graph.to_triples(records(spark, sf_dir)))
    return t.agg(F.count("*").alias("n_triples"), F.count_if(F.split("s", "/")[0].isin(*graph.CORE)).alias("n_core"))


def round_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples that the text or the JSON form loses or adds: none.  Each node is
    written and read in place; only triples that differ are exchanged."""
    nodes = graph.nodes(records(spark, sf_dir))
    form = lambda name, changes: graph.n_different(changes).select(F.lit(name).alias("form"), "n_different")
    return form("text", graph.changed_by_text(nodes)).unionByName(form("json", graph.changed_by_jsonld(nodes)))


def violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the whole export, and after the evidence of uses is taken out."""
    g = records(spark, sf_dir)
    bare = g | {"evidence": g["evidence"].join(g["use"], "assertion_id", "left_anti")}
    out = None
    rules = graph.shapes(spark)
    for name, rows in (
        ("export", graph.record_violations(g, rules)), ("core terms", graph.core_record_violations(g)), ("without evidence of uses", graph.record_violations(bare, rules)),
    ):
        one = rows.agg(F.lit(name).alias("graph"), F.count("*").alias("n"), F.count_if(F.col("kind") == "no_evidence").alias("n_no_evidence"))
        out = one if out is None else out.unionByName(one)
    return out


LEDGER_SQL = f"""{LINKS_SQL}, one AS (SELECT * FROM links QUALIFY row_number() OVER (PARTITION BY deposit_id, response, place ORDER BY n DESC, data_file) = 1),
inv AS (SELECT *, CASE WHEN place > 0 THEN 'robustness' WHEN deposit_id % 9 = 4 THEN 'placebo' ELSE 'headline' END AS role FROM one),
al AS (SELECT *, CASE WHEN class IN ('count', 'proportion') THEN 'clear' ELSE 'debated' END AS tier FROM inv WHERE family = 'linear' AND class IN ('count', 'proportion', 'binary', 'ordinal')),
head AS (SELECT * FROM al WHERE role = 'headline'), files AS (SELECT DISTINCT deposit_id, file_id FROM ({archive.ALL_CELLS_SQL})),
kept AS (SELECT * FROM cls), h AS (SELECT *, deposit_id % 5 AS k FROM head)"""
_NODES_SQL = """counts AS (SELECT 'file' AS kind, (SELECT count(*) FROM files) AS n, 3 AS each, 0 AS more UNION ALL SELECT 'variable', (SELECT count(*) FROM kept), 5, 0
 UNION ALL SELECT 'profile', (SELECT count(*) FROM kept), 6, 0 UNION ALL SELECT 'analysis', (SELECT count(*) FROM inv), 4, 0
 UNION ALL SELECT 'role', (SELECT count(*) + count(*) FILTER (role = 'headline' AND deposit_id % 10 = 0) FROM inv), 4, (SELECT count(*) FROM inv WHERE role = 'headline' AND deposit_id % 10 = 0)
 UNION ALL SELECT 'use', (SELECT count(*) FROM inv), 7, 0 UNION ALL SELECT 'estimator', (SELECT count(*) FROM inv), 4, 0 UNION ALL SELECT 'alert', (SELECT count(*) FROM al), 5, 0
 UNION ALL SELECT 'review', (SELECT coalesce(sum(CASE k WHEN 0 THEN 5 WHEN 1 THEN 6 WHEN 2 THEN 6 WHEN 3 THEN 1 ELSE 0 END), 0) FROM h), 5, (SELECT count(*) FROM h WHERE k = 2)
 UNION ALL SELECT 'evidence', (SELECT 3 * count(*) + count(*) FILTER (role = 'headline' AND deposit_id % 10 = 0) FROM inv), 4, 0
 UNION ALL SELECT 'generation', (SELECT 3 * count(*) + count(*) FILTER (role = 'headline' AND deposit_id % 10 = 0) FROM inv), 5, 0)"""


def queries():
    return {
        "ledger_inventory": inventory,
        "ledger_alerts": alerts,
        "ledger_headline_alerts": headline,
        "ledger_reviewed": reviewed,
        "ledger_review_states": review_states,
        "ledger_roles_in_time": roles_in_time,
        "ledger_provenance": provenance,
        "ledger_accepted_roles": accepted_roles,
        "ledger_paper_summary": summaries,
        "ledger_find_accepted": accepted_outcomes,
        "ledger_imports": imports_twice,
        "ledger_triples": triples,
        "ledger_export_size": export_size,
        "ledger_round_trips": round_trips,
        "ledger_violations": violations,
    }


def oracle_sql():
    shown = "deposit_id, response, family, class, tier"
    state = "CASE WHEN k < 3 THEN 'accepted' ELSE 'unreviewed' END"
    return {
        "ledger_inventory": f"{LEDGER_SQL} SELECT role, family, count(*) AS n FROM inv GROUP BY 1, 2",
        "ledger_alerts": f"{LEDGER_SQL} SELECT role, class, tier, count(*) AS n FROM al GROUP BY 1, 2, 3",
        "ledger_headline_alerts": f"{LEDGER_SQL} SELECT {shown} FROM head",
        "ledger_reviewed": f"{LEDGER_SQL} SELECT {shown} FROM h WHERE k = 0",
        "ledger_review_states": f"""{LEDGER_SQL} SELECT state, CAST(sum(n) AS BIGINT) AS n FROM (SELECT 'accepted' AS state, CASE k WHEN 0 THEN 5 WHEN 1 THEN 4 WHEN 2 THEN 4 ELSE 0 END AS n FROM h
  UNION ALL SELECT CASE k WHEN 1 THEN 'conflict' WHEN 2 THEN 'unresolved' ELSE 'rejected' END, 1 FROM h WHERE k IN (1, 2, 3)) GROUP BY state""",
        "ledger_roles_in_time": f"""{LEDGER_SQL}, r AS (SELECT role, CASE WHEN role = 'headline' AND deposit_id % 10 = 0 THEN 'robustness' ELSE role END AS before FROM inv)
SELECT 'current' AS view, role, count(*) AS n FROM r GROUP BY role UNION ALL SELECT 'as of 1', before, count(*) FROM r GROUP BY before""",
        "ledger_provenance": f"""{LEDGER_SQL}, s AS (SELECT inv.deposit_id, inv.place, inv.response, {state.replace("k <", "h.k <")} AS state FROM inv LEFT JOIN h ON h.deposit_id = inv.deposit_id AND h.place = inv.place AND h.response = inv.response)
SELECT kind, CASE WHEN kind = 'role' THEN 'paper text' ELSE 'code' END AS source, CASE WHEN kind = 'role' THEN 'manual' ELSE 'deterministic' END AS method, state, count(*) AS n FROM s, (VALUES ('role'), ('use'), ('estimator')) v(kind) GROUP BY ALL""",
        "ledger_accepted_roles": f"{LEDGER_SQL} SELECT count(*) AS n FROM h WHERE k < 3",
        "ledger_paper_summary": f"{LEDGER_SQL} SELECT deposit_id, response AS headline_outcomes, 3 AS n_derived_from FROM inv WHERE role = 'headline'",
        "ledger_find_accepted": f"{LEDGER_SQL} SELECT DISTINCT l.deposit_id, l.response AS outcome, CAST(l.n AS BIGINT) AS n FROM links l JOIN h ON h.deposit_id = l.deposit_id AND h.response = l.response WHERE k = 0 AND l.class = 'proportion' AND l.n BETWEEN 20 AND 60",
        "ledger_imports": f"{LEDGER_SQL} SELECT step, CAST(m * (SELECT count(*) FROM inv) AS BIGINT) AS n FROM (VALUES ('first', 1), ('again', 1), ('changed', 2)) v(step, m)",
        "ledger_triples": f"{LEDGER_SQL}, {_NODES_SQL} SELECT kind, CAST(n AS BIGINT) AS n_nodes, CAST(n * each + more AS BIGINT) AS n_triples FROM counts WHERE n > 0",
        "ledger_export_size": f"{LEDGER_SQL}, {_NODES_SQL} SELECT CAST(sum(n * each + more) AS BIGINT) AS n_triples, CAST(sum(n * each) FILTER (kind IN ('file', 'variable')) AS BIGINT) AS n_core FROM counts",
        "ledger_round_trips": "SELECT form, CAST(0 AS BIGINT) AS n_different FROM (VALUES ('text'), ('json')) v(form)",
        "ledger_violations": f"""{LEDGER_SQL} SELECT graph, CAST(CASE WHEN graph LIKE 'without%' THEN (SELECT count(*) FROM inv) ELSE 0 END AS BIGINT) AS n,
CAST(CASE WHEN graph LIKE 'without%' THEN (SELECT count(*) FROM inv) ELSE 0 END AS BIGINT) AS n_no_evidence FROM (VALUES ('export'), ('core terms'), ('without evidence of uses')) v(graph)""",
    }
