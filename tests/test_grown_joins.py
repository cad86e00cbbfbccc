"""Joins whose sides have a row a deposit go without the driver."""

import pytest

SMALL = "/root/testdata/sf0.001"


def _plan(df):
    df.collect()
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["pairing_methods", "pairing_status"])
def test_pairing_broadcasts_nothing(spark, name):
    import __spark_entry__ as entry

    plan = _plan(entry.queries()[name](spark, SMALL))
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_scores_join_without_broadcasts(spark):
    from varledger.plans import papers
    from varledger.plans.archive import Census

    plan = _plan(papers._scored(Census(spark, SMALL)))
    assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_capped_evidence_is_that_of_all_files_without_the_skipped(spark):
    """Taken from the evidence of all files, or made anew."""
    from varledger.operators import extraction
    from varledger.plans.archive import Census

    census, cols = Census(spark, SMALL), ["deposit_id", "file_id", "name", "n", "vmin", "vmax", "support", "n_distinct"]
    taken = extraction.kept_files(census.evidence(capped=False), census.files, merge=True)
    anew = census.profiled()
    assert taken.count() == anew.count() > 0
    assert not taken.select(cols).exceptAll(anew.select(cols)).count()
