"""Four analyses with their assertions, alerts and reviews: the literal record
set on which the four queries and the graph checks are shown."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

ANALYSIS = ("analysis_id string, dataset_version string, paper_loc string, command string", [
    ("a1", "d1@1", "table 2", "regress"), ("a2", "d1@1", "table 3", "glm"),
    ("a3", "d1@1", "table A1", "regress"), ("a4", "d1@1", "table 1", "t.test"),
])
ROLE = ("assertion_id string, analysis_id string, role string, at int, supersedes string", [
    ("r0", "a1", "robustness", 1, None), ("r1", "a1", "headline", 2, "r0"), ("r2", "a2", "robustness", 1, None),
    ("r3", "a3", "placebo", 1, None), ("r4", "a4", "balance", 1, None),
])
USE = ("assertion_id string, analysis_id string, variable_id string, response string, use string, link_kind string, at int, supersedes string", [
    ("u1", "a1", "v1", "bulk_units", "outcome", "exact", 1, None), ("u2", "a2", "v1", "bulk_units", "outcome", "exact", 1, None),
    ("u3", "a3", "v2", "priority_digit", "outcome", "exact", 1, None), ("u4", "a4", "v3", "returned_share", "outcome", "exact", 1, None),
    ("u5", "a1", "v4", "total_quantity", "predictor", "exact", 1, None),
])
ESTIMATOR = ("assertion_id string, analysis_id string, family string, at int, supersedes string", [
    ("e1", "a1", "linear", 1, None), ("e2", "a2", "count", 1, None), ("e3", "a3", "linear", 1, None), ("e4", "a4", "t-test", 1, None),
])
PROFILE = ("profile_id string, variable_id string, class string, rule_version string", [
    ("p1", "v1", "count", "census-1"), ("p2", "v2", "ordinal", "census-1"), ("p3", "v3", "proportion", "census-1"), ("p4", "v4", "continuous", "census-1"),
])
ALERT = ("alert_id string, analysis_id string, use_id string, profile_id string, tier string", [
    ("al1", "a1", "u1", "p1", "clear"), ("al3", "a3", "u3", "p2", "debated"),
])
REVIEW = ("decision_id string, target_id string, reviewer string, state string, at int, supersedes string", [
    ("d0", "r1", "first", "unresolved", 1, None), ("d1", "r1", "first", "accepted", 3, "d0"), ("d2", "u1", "first", "accepted", 3, None),
    ("d3", "e1", "second", "accepted", 3, None), ("d4", "p1", "second", "accepted", 3, None), ("d5", "al1", "first", "accepted", 4, None),
])
EVIDENCE = ("evidence_id string, assertion_id string, source string, locator string", [
    ("ev1", "r1", "paper text", "p. 12"), ("ev2", "u1", "code", "main.do:14"), ("ev3", "e1", "code", "main.do:14"), ("ev4", "r2", "paper text", "p. 14"),
    ("ev5", "u2", "code", "rob.R:3"), ("ev6", "e2", "code", "rob.R:3"), ("ev7", "r3", "paper text", "p. 30"), ("ev8", "u3", "code", "app.do:2"),
    ("ev9", "e3", "code", "app.do:2"), ("ev10", "r4", "paper text", "p. 9"), ("ev11", "u4", "data profile", "f1"), ("ev12", "e4", "paper text", "p. 9"),
    ("ev13", "u5", "code", "main.do:14"), ("ev14", "r0", "paper text", "p. 12"),
])
GENERATION = ("assertion_id string, method string, tool string, at int, time_uncertainty string", [
    *[(a, "manual", "editor", None, "within the week") for a in ("r0", "r1", "r2", "r3", "r4")],
    *[(a, "deterministic", "code parser", 1, None) for a in ("u1", "u2", "u3", "u4", "u5", "e1", "e2", "e3", "e4")],
])
FILE = ("file_key string, dataset_version string, file_checksum string", [("f1", "d1@1", "c0ffee")])
VARIABLE = ("variable_id string, file_key string, name string, position int, datatype string", [
    ("v1", "f1", "bulk_units", 0, "Integer"), ("v2", "f1", "priority_digit", 1, "Integer"), ("v3", "f1", "returned_share", 2, "Double"), ("v4", "f1", "total_quantity", 3, "Double"),
])
ALL = {
    "file": FILE, "variable": VARIABLE, "analysis": ANALYSIS, "role": ROLE, "use": USE, "estimator": ESTIMATOR, "profile": PROFILE, "alert": ALERT,
    "review": REVIEW, "evidence": EVIDENCE, "generation": GENERATION,
}


def frames(spark: SparkSession) -> dict[str, DataFrame]:
    return {name: spark.createDataFrame(rows, schema) for name, (schema, rows) in ALL.items()}


def values(name: str) -> str:
    """The same rows as a DuckDB subquery."""
    schema, rows = ALL[name]
    cols = ", ".join(f'"{c.split()[0]}"' for c in schema.split(", "))
    lit = lambda v: "NULL" if v is None else str(v) if isinstance(v, int) else f"'{v}'"
    return f"(SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) t({cols}))"
