"""Census, recovery and fingerprint queries over every deposit: sf0.01 has ten
times the parts of the smallest tables."""

import pytest
from comparing import rows_of

MEDIUM = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def medium():
    import duckdb

    con = duckdb.connect()
    for t in ("part", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{MEDIUM}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", [
    "recovery_deposit", "recovery_case", "outcome_location", "miss_reasons", "detector_scores", "refit_report", "ledger_reviewed",
    "fingerprint_scores", "fingerprint_grid", "fingerprint_movement", "fingerprint_misses",
])
def test_every_deposit_takes_part(spark, medium, name):
    import __spark_entry__ as entry

    got = entry.queries()[name](spark, MEDIUM).toPandas()
    assert rows_of(got) == rows_of(medium.execute(entry.oracle_sql()[name]).df())


def test_no_query_is_cut_by_a_key():
    import __spark_entry__ as entry

    assert not [n for n, q in entry.oracle_sql().items() if "p_partkey <=" in q or "deposit_id <=" in q]
