"""Assertion graph: the four queries, versions, export, shapes, mutations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import fixture
from ..operators import graph, ledger
from ..operators.screen import rule_table
from ..sources import reported
from ..sources.store import stored

_VIEWS = "".join(
    f", {n}_now AS (SELECT * FROM {n}_all WHERE assertion_id NOT IN (SELECT supersedes FROM {n}_all WHERE supersedes IS NOT NULL))" for n in ("role", "use", "estimator")
)
_VIEWS += """, inv AS (SELECT a.*, r.role, r.assertion_id AS role_id, u.response, u.variable_id, u.assertion_id AS use_id, e.family, e.assertion_id AS estimator_id
FROM analysis_all a JOIN role_now r USING (analysis_id) JOIN use_now u USING (analysis_id) JOIN estimator_now e USING (analysis_id) WHERE u.use = 'outcome'),
al AS (SELECT inv.*, x.alert_id, x.profile_id, x.tier, p.class FROM inv JOIN alert_all x USING (analysis_id, use_id) JOIN profile_all p USING (profile_id)),
st AS (SELECT target_id FROM review_all WHERE decision_id NOT IN (SELECT supersedes FROM review_all WHERE supersedes IS NOT NULL)
GROUP BY target_id HAVING bool_and(state = 'accepted')),
rev AS (SELECT * FROM al WHERE role = 'headline' AND role_id IN (FROM st) AND use_id IN (FROM st) AND estimator_id IN (FROM st) AND profile_id IN (FROM st) AND alert_id IN (FROM st))"""
#: Over the literal records, and over those of the documents.
_WITH, _DOCS = ("WITH " + ", ".join(f"{n}_all AS {source.values(n)}" for n in fixture.ALL) + _VIEWS for source in (fixture, reported))

INV, ALERT = ["analysis_id", "role", "response", "family"], ["analysis_id", "role", "response", "family", "class", "tier"]


def _view(f, cols):
    return lambda spark, sf_dir: f(reported.frames(spark, sf_dir)).select(*cols)


def _literal(f, cols):
    return lambda spark, sf_dir: f(fixture.frames(spark)).select(*cols)


def current_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.current(reported.frames(spark, sf_dir)["role"]).select("assertion_id", "analysis_id", "role")


def as_of_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.as_of(reported.frames(spark, sf_dir)["role"], 1).select("assertion_id", "analysis_id", "role")


def review_states(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ledger.review_state(fixture.frames(spark)["review"])


def materialised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The screen raises the stored alerts again."""
    return ledger.materialise_alerts(reported.frames(spark, sf_dir), rule_table(spark)).select("analysis_id", "use_id", "profile_id", "tier")


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    kind = F.regexp_extract("s", "^([a-z]+)/", 1)
    return graph.nodes(reported.frames(spark, sf_dir)).groupBy(kind.alias("kind")).agg(
        F.count("s").alias("n_nodes"), F.sum(F.size("cells").cast("long")).alias("n_triples")
    )


def _triples_sql() -> str:
    parts = []
    for kind, (schema, rows) in fixture.ALL.items():
        key, _ = graph.NODES[kind]
        cols = [c.split()[0] for c in schema.split(", ")]
        counted = [c for c in cols if c != key or kind == "generation"]
        n = " + ".join(f'count("{c}")' for c in counted)
        parts.append(f"""SELECT '{kind}' AS kind, count(DISTINCT "{key}") AS n_nodes, count(*) + {n} AS n_triples FROM {reported.values(kind)}""")
    return " UNION ALL ".join(parts)


def roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples that the text form loses or adds: none."""
    t = stored(graph.to_triples(reported.frames(spark, sf_dir)), "reported-triples")
    return graph.difference(t, graph.from_turtle(graph.to_turtle(t))).agg(F.count("*").alias("n_different"))


def shape_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name, g in graph.mutations(fixture.frames(spark)).items():
        v = graph.violations(graph.to_triples(g).coalesce(4).cache(), graph.shapes(spark).cache()).select(F.lit(name).alias("mutation"), "s", "kind")
        out = v if out is None else out.unionByName(v)
    return out.distinct()


SHAPE_SQL = """SELECT * FROM (VALUES ('no_evidence', 'use/u1', 'no_evidence'), ('other_profile', 'alert/al1', 'other_variable'),
('role_on_column', 'role/r4', 'dangling')) t(mutation, s, kind)"""


def mutation_effects(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the four queries under each mutation."""
    out = None
    for name, g in graph.mutations(reported.frames(spark, sf_dir)).items():
        for q, f in (("inventory", ledger.inventory), ("alerts", ledger.alerts), ("headline", ledger.headline_alerts), ("reviewed", ledger.reviewed)):
            one = f(g).agg(F.lit(name).alias("mutation"), F.lit(q).alias("query"), F.count("*").alias("n"))
            out = one if out is None else out.unionByName(one)
    return out


#: Rows of inventory, alerts, headline alerts and reviewed ones under each
#: mutation, from the numbers of documents of the four kinds.
EFFECTS = {
    "none": ("n", "n0 + n2", "n0", "n0"), "no_evidence": ("n", "n0 + n2", "n0", "n0"), "other_profile": ("n", "n0 + n2", "n0", "0"),
    "role_on_column": ("n - n3", "n0 + n2", "n0", "n0"), "conflicting_review": ("n", "n0 + n2", "n0", "0"),
    "superseded_review": ("n", "n0 + n2", "n0", "0"), "no_alerts": ("n", "0", "0", "0"),
}
_KINDS = ", ".join(f"count(*) FILTER ({reported.KIND_SQL} = {i}) AS n{i}" for i in (0, 2, 3))
EFFECTS_SQL = f"WITH k AS (SELECT count(*) AS n, {_KINDS} FROM documents) " + " UNION ALL ".join(
    f"SELECT '{m}' AS mutation, '{q}' AS query, CAST({k} AS BIGINT) AS n FROM k"
    for m, ks in EFFECTS.items() for q, k in zip(("inventory", "alerts", "headline", "reviewed"), ks, strict=True)
)


def queries():
    return {
        "inventory": _view(ledger.inventory, INV),
        "alerts": _view(ledger.alerts, ALERT),
        "headline_alerts": _view(ledger.headline_alerts, ALERT),
        "reviewed": _literal(ledger.reviewed, ALERT),
        "current_view": current_view,
        "as_of_view": as_of_view,
        "review_states": review_states,
        "materialised_alerts": materialised,
        "assertions_by_source": lambda spark, sf_dir: ledger.by_source(reported.frames(spark, sf_dir)),
        "paper_summary": lambda spark, sf_dir: ledger.paper_summary(reported.frames(spark, sf_dir)).withColumn("derived_from", F.array_join("derived_from", ",")),
        "uses_of_variable": lambda spark, sf_dir: ledger.uses_of(fixture.frames(spark), "v1").select("assertion_id", "analysis_id", "use"),
        "graph_triples": triples,
        "graph_roundtrip_diff": roundtrip,
        "shape_violations": shape_violations,
        "mutation_effects": mutation_effects,
    }


def oracle_sql():
    a = ", ".join(ALERT)
    return {
        "inventory": f"{_DOCS} SELECT {', '.join(INV)} FROM inv",
        "alerts": f"{_DOCS} SELECT {a} FROM al",
        "headline_alerts": f"{_DOCS} SELECT {a} FROM al WHERE role = 'headline'",
        "reviewed": f"{_WITH} SELECT {a} FROM rev",
        "current_view": f"{_DOCS} SELECT assertion_id, analysis_id, role FROM role_now",
        "as_of_view": f"{_DOCS} SELECT assertion_id, analysis_id, role FROM role_all WHERE \"at\" <= 1",
        "review_states": f"{_WITH} SELECT target_id, 'accepted' AS state FROM st",
        "materialised_alerts": f"{_DOCS} SELECT analysis_id, use_id, profile_id, tier FROM alert_all",
        "assertions_by_source": f"{_DOCS} SELECT source, method, count(DISTINCT assertion_id) AS n FROM evidence_all JOIN generation_all USING (assertion_id) GROUP BY source, method",
        "paper_summary": f"{_DOCS} SELECT dataset_version, string_agg(DISTINCT response, ',') AS headline_outcomes, array_to_string(list_sort(list_concat(list_concat(list(DISTINCT role_id), list(DISTINCT use_id)), list(DISTINCT estimator_id))), ',') AS derived_from FROM inv WHERE role = 'headline' GROUP BY dataset_version",
        "uses_of_variable": f"{_WITH} SELECT assertion_id, analysis_id, use FROM use_now WHERE variable_id = 'v1'",
        "graph_triples": _triples_sql(),
        "graph_roundtrip_diff": "SELECT CAST(0 AS BIGINT) AS n_different",
        "shape_violations": SHAPE_SQL,
        "mutation_effects": EFFECTS_SQL,
    }
