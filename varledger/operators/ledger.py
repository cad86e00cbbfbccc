"""Append-only assertions: identities, versions, review states and views."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def content_id(*columns: str) -> Column:
    """Identity of an assertion by its content, so that imports repeat safely."""
    return F.sha2(F.to_json(F.struct(*columns)), 256)


def variable_id(checksum: str = "file_checksum", position: str = "position") -> Column:
    """Identity of a variable: file checksum and position, never its name."""
    return F.sha2(F.concat_ws("|", checksum, F.col(position).cast("string")), 256)


def file_checksums(cells: DataFrame) -> DataFrame:
    """deposit_id, file_id, file_checksum: a checksum of each file's cells
    (deposit_id, file_id, name, value) that does not depend on their order."""
    return cells.select("deposit_id", "file_id", F.xxhash64("name", "value").cast("decimal(38,0)").alias("h")).groupBy("deposit_id", "file_id").agg(
        F.sha2(F.concat_ws("|", "deposit_id", "file_id", F.sum("h").cast("string"), F.count("*").cast("string")), 256).alias("file_checksum")
    )


def append(existing: DataFrame, incoming: DataFrame, key: str = "assertion_id") -> DataFrame:
    """Existing rows and those incoming that are not there yet.  A changed
    extraction has other content, so another id, and the old row stays."""
    return existing.unionByName(incoming.dropDuplicates([key]).join(existing.select(key), key, "left_anti"))


def current(rows: DataFrame, key: str = "assertion_id") -> DataFrame:
    """Rows that no other row supersedes."""
    old = rows.where("supersedes IS NOT NULL").select(F.col("supersedes").alias(key)).distinct()
    return rows.join(old, key, "left_anti")


def as_of(rows: DataFrame, at: int, key: str = "assertion_id") -> DataFrame:
    """The current view as it stood at a time."""
    return current(rows.where(F.col("at") <= at), key)


def retract(rows: DataFrame, key_value: str, at: int, key: str = "assertion_id") -> DataFrame:
    """A withdrawn row stays in the ledger; a row without content supersedes it."""
    gone = rows.where(F.col(key) == key_value).select(
        *[
            (F.lit(f"{key_value}-withdrawn") if c == key else F.lit(at) if c == "at" else F.lit(key_value) if c == "supersedes" else F.lit(None))
            .cast(rows.schema[c].dataType).alias(c)
            for c in rows.columns
        ]
    )
    return rows.unionByName(gone)


def review_state(decisions: DataFrame) -> DataFrame:
    """State of each target from current decisions: accepted only without a
    current unresolved or rejected one; disagreement stays visible."""
    now = current(decisions, "decision_id")
    yes, no = F.bool_or(F.col("state") == "accepted"), F.bool_or(F.col("state") == "rejected")
    open_ = F.bool_or(F.col("state") == "unresolved")
    return now.groupBy("target_id").agg(
        F.when(yes & (no | open_), "conflict").when(yes, "accepted").when(no, "rejected").otherwise("unresolved").alias("state")
    )


# -- the four queries ------------------------------------------------------


def inventory(g: dict[str, DataFrame]) -> DataFrame:
    """Reported analyses with role, response and estimator."""
    role = current(g["role"]).select("analysis_id", "role", F.col("assertion_id").alias("role_id"))
    use = current(g["use"]).where("use = 'outcome'").select(
        "analysis_id", "variable_id", "response", F.col("assertion_id").alias("use_id")
    )
    est = current(g["estimator"]).select("analysis_id", "family", F.col("assertion_id").alias("estimator_id"))
    return g["analysis"].join(role, "analysis_id").join(use, "analysis_id").join(est, "analysis_id")


def alerts(g: dict[str, DataFrame]) -> DataFrame:
    """Those with an alert on the same analysis and use."""
    profile = g["profile"].select("profile_id", "class")
    return inventory(g).join(g["alert"], ["analysis_id", "use_id"]).join(profile, "profile_id")


def headline_alerts(g: dict[str, DataFrame]) -> DataFrame:
    return alerts(g).where("role = 'headline'")


def reviewed(g: dict[str, DataFrame]) -> DataFrame:
    """Headline alerts of which role, use, estimator, profile and alert are all
    currently accepted."""
    ok = review_state(g["review"]).where("state = 'accepted'").select("target_id")
    out = headline_alerts(g)
    for target in ("role_id", "use_id", "estimator_id", "profile_id", "alert_id"):
        out = out.join(ok.withColumnRenamed("target_id", target), target, "left_semi")
    return out


def materialise_alerts(g: dict[str, DataFrame], rules: DataFrame) -> DataFrame:
    """Alerts that the screen raises over uses and profiles."""
    rows = inventory(g).join(g["profile"], "variable_id").join(F.broadcast(rules), ["family", "class"])
    return rows.select(content_id("analysis_id", "use_id", "profile_id", "tier").alias("alert_id"), "analysis_id", "use_id", "profile_id", "tier")


def uses_of(g: dict[str, DataFrame], variable: str) -> DataFrame:
    return current(g["use"]).where(F.col("variable_id") == variable)


def by_source(g: dict[str, DataFrame]) -> DataFrame:
    """Assertions by evidence source and generation method."""
    return g["evidence"].join(g["generation"], "assertion_id").groupBy("source", "method").agg(F.countDistinct("assertion_id").alias("n"))


def assertions(g: dict[str, DataFrame]) -> DataFrame:
    """Every current assertion with the three questions of provenance as fields
    of their own: assertion_id, kind, analysis_id, role, source, method, state
    (unreviewed where no decision names it)."""
    rows = None
    for kind in ("role", "use", "estimator"):
        role = F.col("role") if kind == "role" else F.lit(None).cast("string")
        one = current(g[kind]).select("assertion_id", F.lit(kind).alias("kind"), "analysis_id", role.alias("role"))
        rows = one if rows is None else rows.unionByName(one)
    shown = g["evidence"].select("assertion_id", "source").distinct()
    made = g["generation"].select("assertion_id", "method").distinct()
    state = review_state(g["review"]).withColumnRenamed("target_id", "assertion_id")
    return rows.join(shown, "assertion_id", "left").join(made, "assertion_id", "left").join(state, "assertion_id", "left").withColumn(
        "state", F.coalesce("state", F.lit("unreviewed"))
    )


def selected(
    g: dict[str, DataFrame], *, kind: str | None = None, role: str | None = None, source: str | None = None, method: str | None = None,
    state: str | None = None,
) -> DataFrame:
    """Current assertions by any of role, evidence source, method and state."""
    out = assertions(g)
    for column, value in {"kind": kind, "role": role, "source": source, "method": method, "state": state}.items():
        if value is not None:
            out = out.where(F.col(column) == value)
    return out


def paper_summary(g: dict[str, DataFrame]) -> DataFrame:
    """Headline outcomes of each dataset version, with the assertions that each
    summary is derived from."""
    ids = F.array_distinct(F.flatten(F.collect_list(F.array("role_id", "use_id", "estimator_id"))))
    return inventory(g).where("role = 'headline'").groupBy("dataset_version").agg(
        F.array_join(F.array_sort(F.collect_set("response")), ",").alias("headline_outcomes"), F.array_sort(ids).alias("derived_from")
    )


# -- building a ledger from what a census found ----------------------------


def built(
    deposits: DataFrame, profiles: DataFrame, checksums: DataFrame, links: DataFrame, roles: DataFrame, decisions, rules: DataFrame, *,
    keep: Callable[[DataFrame, str], DataFrame] = lambda df, name: df,
) -> dict[str, DataFrame]:
    """Records of a census run, with identities by content.  ``keep`` may write
    each record set, since later ones and all views read them.

    ``profiles`` (deposit_id, file_id, name, position, datatype, class,
    rule_version, n), ``checksums`` by file, ``links`` (deposit_id, code_file,
    line_no, command, family, response, column, link_kind, data_file), ``roles``
    (deposit_id, code_file, line_no, role, at, before: an earlier role or null).
    ``decisions`` makes review rows (target_id, reviewer, state, at, first: the
    state it replaces or null) from the records without reviews.
    """
    version = F.concat_ws("@", "deposit_id", "version")
    files = checksums.join(deposits.select("deposit_id", version.alias("dataset_version")), "deposit_id").withColumn(
        "file_key", F.concat_ws("/", "deposit_id", "file_id")
    )
    held = profiles.join(files, ["deposit_id", "file_id"]).withColumn("variable_id", variable_id())
    analysis_id = F.sha2(F.concat_ws("|", "deposit_id", "code_file", "line_no"), 256)
    of = F.sha2(F.concat_ws("|", F.lit("profile"), "variable_id", "rule_version", F.lit("full")), 256)
    held = keep(held, "held")
    g = {
        "file": keep(files.select("file_key", "dataset_version", "file_checksum"), "file"),
        "variable": held.select("variable_id", "file_key", "name", "position", "datatype"),
        "profile": held.select(of.alias("profile_id"), "variable_id", "class", "rule_version", F.lit("full").alias("scope"), "n"),
    }
    named = held.select("deposit_id", F.col("file_id").alias("data_file"), F.col("name").alias("column"), "variable_id", "dataset_version")
    used = keep(links.join(named, ["deposit_id", "data_file", "column"]).withColumn("analysis_id", analysis_id), "used")
    code_loc = F.concat_ws(":", "code_file", "line_no")
    g["analysis"] = keep(used.select("analysis_id", "dataset_version", code_loc.alias("code_loc"), "command").distinct(), "analysis")

    def asserted(rows: DataFrame, *content: str) -> DataFrame:
        return rows.withColumn("assertion_id", content_id("kind", *content)).drop("kind")

    none = F.lit(None).cast("string")
    placed = roles.withColumn("analysis_id", analysis_id).join(used.select("analysis_id").distinct(), "analysis_id", "left_semi")
    early = asserted(placed.where("before IS NOT NULL").select(F.lit("role").alias("kind"), "analysis_id", F.col("before").alias("role"), F.lit(1).alias("at"), none.alias("supersedes")), "analysis_id", "role", "at")
    late = placed.join(early.select("analysis_id", F.col("assertion_id").alias("supersedes")), "analysis_id", "left").select(F.lit("role").alias("kind"), "analysis_id", "role", "at", "supersedes")
    g["role"] = keep(early.unionByName(asserted(late, "analysis_id", "role", "at")), "role")
    g["use"] = asserted(
        used.select(F.lit("use").alias("kind"), "analysis_id", "variable_id", "response", F.lit("outcome").alias("use"), "link_kind", F.lit(1).alias("at"), none.alias("supersedes")),
        "analysis_id", "variable_id", "use",
    )
    g["estimator"] = keep(asserted(used.select(F.lit("estimator").alias("kind"), "analysis_id", "family", F.lit(1).alias("at"), none.alias("supersedes")).distinct(), "analysis_id", "family"), "estimator")
    shown = {"role": "paper text", "use": "code", "estimator": "code"}
    evidence = None
    for kind, source in shown.items():
        one = g[kind].join(g["analysis"], "analysis_id").select("assertion_id", F.lit(source).alias("source"), F.col("code_loc").alias("locator"))
        evidence = one if evidence is None else evidence.unionByName(one)
    g["evidence"] = keep(evidence.select(content_id("assertion_id", "source", "locator").alias("evidence_id"), "assertion_id", "source", "locator"), "evidence")
    manual, parsed = g["role"].select("assertion_id"), g["use"].select("assertion_id").unionByName(g["estimator"].select("assertion_id"))
    g["generation"] = manual.select(
        "assertion_id", F.lit("manual").alias("method"), F.lit("editor").alias("tool"), F.lit(None).cast("int").alias("at"), F.lit("within the week").alias("time_uncertainty")
    ).unionByName(parsed.select(
        "assertion_id", F.lit("deterministic").alias("method"), F.lit("code parser").alias("tool"), F.lit(1).alias("at"), none.alias("time_uncertainty")
    ))
    g["alert"] = keep(materialise_alerts(g, rules), "alert")
    made = decisions(g).withColumn("decision_id", content_id("target_id", "reviewer", "state", "at"))
    first = made.where("first IS NOT NULL").select(
        content_id("target_id", "reviewer", "first").alias("decision_id"), "target_id", "reviewer", F.col("first").alias("state"),
        (F.col("at") - 1).alias("at"), none.alias("supersedes"),
    )
    over = F.when(F.col("first").isNotNull(), content_id("target_id", "reviewer", "first"))
    g["review"] = keep(made.select("decision_id", "target_id", "reviewer", "state", "at", over.alias("supersedes")).unionByName(first), "review")
    return g
