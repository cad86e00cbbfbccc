"""Registered workloads against DuckDB on the smallest tables."""

import pytest

NAMES = [
    "profile_lineitem", "profile_by_scope_event_type", "five_column_comparison", "class_transitions", "regression_cases", "structural_kinds",
    "failure_mode_hints", "audit_priority_undeclared", "audit_priority_declared", "lineage_difference", "code_pairs", "sibling_code", "pool_cleaning",
    "code_pairs_negative", "harvest_variants", "census_flags", "census_questions", "census_coverage", "harvest_limits", "harvest_archive",
    "bare_rule_confusion", "norm_map", "miss_reasons", "positives_three_ways", "adjudication_draws", "metadata_sheet", "pairing_methods",
    "fingerprint_grid", "pairing_by_title", "pairing_status", "inventory", "reviewed", "as_of_view", "graph_triples", "ledger_reviewed",
    "ledger_triples", "ledger_round_trips", "refit_bulk_share", "refit_plan", "refit_records", "refit_report", "refit_groups_negbin",
    "precision_by_lang", "kappa_quality_toxic", "stratified_draw", "sliding_profile", "session_profile",
]


@pytest.mark.parametrize("name", NAMES)
def test_matches_sql(same, name):
    same(name)


def test_entry_runs_and_has_rows(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 8


def test_every_oracle_has_a_query():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
