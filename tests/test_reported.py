"""Ledger queries over the analyses that the documents report."""

import pytest

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", [
    "alerts", "headline_alerts", "current_view", "materialised_alerts", "assertions_by_source", "paper_summary", "graph_roundtrip_diff", "mutation_effects",
])
def test_matches_sql(same, name):
    same(name)


@pytest.mark.parametrize("name", ["alerts", "as_of_view", "inventory"])
def test_rows_follow_a_given_table(spark, name):
    import __spark_entry__ as entry

    n = {kind: spark.read.parquet(f"{SMALL}/documents.parquet").where(f"coalesce(length(text), 0) % 4 = {kind}").count() for kind in range(4)}
    want = {"alerts": n[0] + n[2], "as_of_view": sum(n.values()), "inventory": sum(n.values())}[name]
    assert entry.queries()[name](spark, SMALL).count() == want > 4


def test_cases_follow_documents_with_one_outcome_each(spark):
    import __spark_entry__ as entry

    from varledger.plans.profiles import CASES

    rows = entry.queries()["regression_cases"](spark, SMALL).collect()
    assert {r.doc_id for r in rows} == {r.doc_id for r in spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id").collect()}
    assert {r.case_name for r in rows} == set(CASES) and len({tuple(r)[1:] for r in rows}) == len(CASES)


def test_each_query_reads_the_documents(spark, monkeypatch):
    """Not only the first of an application."""
    import __spark_entry__ as entry

    from varledger.sources import reported

    read = []
    monkeypatch.setattr(reported, "table", lambda spark, sf_dir, name, table=reported.table: read.append(name) or table(spark, sf_dir, name))
    for name in ("as_of_view", "inventory", "as_of_view"):
        entry.queries()[name](spark, SMALL)
    assert read == ["documents"] * 3
