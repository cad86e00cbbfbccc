"""Checks of nodes in place against those of triples."""

from pyspark.sql import functions as F

HEX = "a0" * 32


def _records(spark):
    """The fixture's records, wrong in every way that the shapes and joins see."""
    from varledger.functions import fixture

    g = fixture.frames(spark)
    other = g["alert"].where("alert_id = 'al1'").withColumn("profile_id", F.lit("p2"))
    return g | {
        "alert": g["alert"].unionByName(other),
        "role": g["role"].withColumn("role", F.when(F.col("assertion_id") != "r1", F.col("role"))).withColumn(
            "analysis_id", F.when(F.col("assertion_id") == "r4", F.lit(HEX)).otherwise(F.col("analysis_id"))
        ),
        "variable": g["variable"].withColumn("extra", F.lit(1)),
        "file": g["file"].withColumn("file_checksum", F.lit(3)),
        "estimator": g["estimator"].withColumn("more", F.lit("x")),
        "evidence": g["evidence"].where("assertion_id <> 'u1'"),
        "generation": g["generation"].drop("time_uncertainty"),
        "review": g["review"].withColumn("at", F.col("at").cast("string")),
    }


def test_violations_of_nodes_are_those_of_triples(spark):
    from varledger.operators import graph

    g, rules = _records(spark), graph.shapes(spark)
    t = spark.createDataFrame(graph.to_triples(g).collect(), graph.TRIPLE)
    rows = lambda df: sorted(tuple(r) for r in df.select("s", "p", "kind").collect())
    want = rows(graph.violations(t, rules))
    assert rows(graph.record_violations(g, rules)) == want
    assert {k for *_, k in want} == {"cardinality", "closed", "node_kind", "dangling", "no_evidence", "no_time", "other_variable"}
    core = rows(graph.core_violations(t))
    assert rows(graph.core_record_violations(g)) == core and len(core) == 5


def test_packed_keys_are_equal_where_texts_are(spark):
    from varledger.operators import graph

    texts = [f"use/{HEX}", "t", "", f"use/{HEX}\n", "é/" + "0f" * 32, "h" + "0f" * 32, "x/" + "AF" * 32, "0f" * 31 + "0", "0f" * 32]
    df = spark.createDataFrame([(t,) for t in texts], "v string").select("v", graph._packed(F.col("v")).alias("b"))
    rows = df.select("v", "b", graph._unpacked(F.col("b")).alias("u")).collect()
    assert all(r.v == r.u for r in rows) and len({bytes(r.b) for r in rows}) == len(texts)
    assert len(rows[0].b) == 37


def test_round_trips_exchange_only_what_differs(spark):
    """A line break that the text form escapes comes back; a node name with a
    quote and an unreadable line count as differences do."""
    from varledger.operators import graph

    t = spark.createDataFrame(
        [("use/u1", "response", 'a "b"\n\\n', "text"), ("use/u1", "at", "1", "integer"), ("use/u1", "at", "2", "odd>kind"), ("use/<%3C>", "use_id", "use/x", "node")], graph.TRIPLE
    )
    nodes = t.groupBy("s").agg(F.collect_list(F.struct("p", "o", "o_kind")).alias("cells"))
    n = lambda df: df.first()[0]
    for changes, back in ((graph.changed_by_text(nodes), graph.from_turtle(graph.to_turtle(t))), (graph.changed_by_jsonld(nodes), graph.from_jsonld(graph.to_jsonld(t)))):
        assert n(graph.n_different(changes)) == graph.difference(t, back).count()
    assert graph.changed_by_text(nodes).count() > 0


def test_whole_ledger_queries_write_no_triples():
    import inspect

    from varledger.plans import ledgers

    for query in (ledgers.round_trips, ledgers.violations):
        assert "to_triples" not in inspect.getsource(query)
