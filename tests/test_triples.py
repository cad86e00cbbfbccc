"""Triples of records that repeat, differ under one key, or lack a field."""


def test_records_of_one_key_share_a_node(spark):
    from varledger.operators import graph

    alerts = spark.createDataFrame(
        [("x", "a1", "u1", "p1", "clear"), ("x", "a1", "u1", "p1", "clear"), ("x", "a1", "u1", "p1", "debated"), ("y", "a2", "u2", None, "clear")],
        "alert_id string, analysis_id string, use_id string, profile_id string, tier string",
    )
    got = [tuple(r) for r in graph.to_triples({"alert": alerts}).collect()]
    assert len(got) == len(set(got)) == 6 + 4
    assert {t[2] for t in got if t[:2] == ("alert/x", "tier")} == {"clear", "debated"}
    assert not [t for t in got if t[:2] == ("alert/y", "profile_id")]


def test_triples_are_counted_without_an_exchange_of_triples(spark):
    """Rows meet by their key; the triples of a node are made in place."""
    from varledger.functions import fixture
    from varledger.operators import graph

    plan = graph.to_triples(fixture.frames(spark))._jdf.queryExecution().optimizedPlan().toString()
    generated = plan.index("Generate")
    assert "Aggregate" not in plan[:generated]
