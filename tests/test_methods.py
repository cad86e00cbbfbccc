"""Worked examples, measures and invariants of the methods."""

import json

import numpy as np
import pytest
from pyspark.sql import functions as F

from varledger.functions import fixture
from varledger.functions.rules import CENSUS, HARDENED, PILOT
from varledger.operators import audit, benchmark, classify, evidence, extraction, fingerprint, graph, ledger, measures, refit, screen
from varledger.sources import tables
from varledger.streaming import ingest


def profiled(spark, values, rules=CENSUS):
    cells = spark.createDataFrame([("x", None if v is None else float(v)) for v in values], "col string, value double")
    return classify.classified(evidence.profile_cells(cells, ["col"]), rules=rules).first()


@pytest.mark.parametrize(
    ("values", "expected"),
    [
        ([0, 50, 100], "binary"),
        ([2, 3, 3, 4, 4, 4, 5, 5, 6, 7, 9, 11], "ordinal"),
        ([1, 2, 3, 4, 5, 98, 99], "ordinal"),
        ([0, 0.25, 0.5, 0.75, 1], "ordinal"),
        ([i / 40 for i in range(41)], "proportion"),
        ([i * 2.4 for i in range(42)] + [100], "continuous"),
        ([i * i * i for i in range(40)], "count"),
        ([i * i * i for i in range(40)] + [2_000_000], "heavy-tailed"),
        ([4, 4, 4], "binary"),
        ([None, None], "categorical"),
        ([float("nan"), float("inf"), 1.5, 2.5, 3.25], "continuous"),
    ],
)
def test_census_classes(spark, values, expected):
    assert profiled(spark, values)["class"] == expected


def test_pilot_and_hardened_differ_from_final(spark):
    rating = [i / 8 for i in range(9)]
    assert profiled(spark, rating, PILOT)["class"] == "proportion"
    assert profiled(spark, rating, HARDENED)["class"] == "proportion"
    assert profiled(spark, rating)["class"] == "ordinal"
    codes = [1, 2, 3, 98, 99] * 3
    assert profiled(spark, codes, PILOT)["class"] == "count"
    assert profiled(spark, codes)["class"] == "ordinal"


def test_support_is_exact_at_the_limit(spark):
    for n, complete in ((25, True), (26, False)):
        row = profiled(spark, list(range(n)) * 3 + [None] * 5)
        assert row.complete is complete
        assert row.n_distinct == n
        if complete:
            assert [s["count"] for s in row.support] == [3] * n


def test_profile_does_not_depend_on_partitions(spark):
    cells = spark.range(2000).select((F.col("id") % 7).alias("g"), ((F.col("id") * 37) % 101).cast("double").alias("value"))
    cols = ["g", "n", "vmin", "vmax", "n_distinct", F.round("mean", 9), F.round("skew", 6)]
    a = evidence.profile_cells(cells.repartition(7), ["g"]).select(*cols).orderBy("g").collect()
    assert a == evidence.profile_cells(cells.coalesce(1), ["g"]).select(*cols).orderBy("g").collect()


def test_profile_plan_has_one_scan_and_no_python(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")
    p = classify.classified(evidence.profile_columns(df, ["l_quantity", "l_tax", "l_discount"]))
    plan = p._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan parquet") == 1
    assert "Python" not in plan
    assert "l_comment" not in plan and "l_extendedprice" not in plan


def cells_of(spark, values):
    return spark.createDataFrame([("x", float(v)) for v in values], "col string, value double")


def test_audit_needs_a_declaration(spark):
    p = evidence.profile_cells(cells_of(spark, [1, 2, 3, 4, 5, 98, 99]), ["col"])
    assert audit.audited(p, None, ["col"]).first().audit_class == "unresolved"
    said = spark.createDataFrame([("x", 98.0, "e1"), ("x", 99.0, "e2")], "col string, value double, evidence_id string")
    row = audit.audited(p, said, ["col"]).first()
    assert (row.audit_class, row["class"], row.dropped_rows) == ("ordinal", "ordinal", 2)
    unproven = said.withColumn("evidence_id", F.lit(None).cast("string"))
    assert audit.audited(p, unproven, ["col"]).first().audit_class == "unresolved"


@pytest.mark.parametrize(("values", "verdict"), [([-1, 1], "binary"), ([0, 99], "binary"), ([-1, 0, 1], "unresolved"), ([0, 50, 100], "unresolved"), ([3, 3], "unresolved")])
def test_only_a_class_reached_by_stripping_is_unresolved(spark, values, verdict):
    row = audit.audited(evidence.profile_cells(cells_of(spark, values), ["col"]), None, ["col"]).first()
    assert row.audit_class == verdict
    assert [s["value"] for s in row.support] == sorted(set(values))


def test_audit_counts_declared_rows_beyond_the_support(spark, tmp_path):
    (tmp_path / "codes.csv").write_text("col,value,evidence_id\nx,99,page 3\nx,n/a,page 4\nx,5,\ny,7,page 5\n")
    said = audit.declarations(tables.delimited(spark, str(tmp_path / "codes.csv")), ["col"])
    assert {tuple(r) for r in said.collect()} == {("x", 99.0, "page 3"), ("y", 7.0, "page 5")}
    cells = cells_of(spark, [*range(40), 99, 99, 99])
    row = audit.audited(evidence.profile_cells(cells, ["col"]), said, ["col"], cells=cells).first()
    assert (row.overflow, row.dropped_rows, row.support) == (True, 3, None)


def test_type_flags(spark):
    df = spark.createDataFrame([("1", "1.0", "true", "2020-01-01", "a"), ("2", "3", "false", "2020-02-01", "1"), (None,) * 5], "a string, b string, c string, d string, e string")
    got = {r.column: r.xsd_datatype for r in evidence.type_flags(df).collect()}
    assert got == {"a": "Integer", "b": "Double", "c": "Boolean", "d": "Date", "e": "String"}


def pairs_of(spark, lang, text):
    df = spark.createDataFrame([(1, "f", lang, text)], "deposit_id long, file_id string, lang string, text string")
    return [(r.command, r.family, r.response, r.excluded) for r in extraction.pairs(extraction.logical_lines(df)).orderBy("line_no").collect()]


def test_stata_commands(spark):
    text = "\n".join(
        ["* regress no x", "regress y x", "qui reg y2 ///", "  x // why", "svy: regress y3 x", "xi: reg y4 i.z", "bysort g: reg y5 x if x > 1",
         "/* reg y6 x", "reg y7 x */", "summarize y8", "logit y9 x", "zinb y10 x, inflate(z)"]
    )
    got = pairs_of(spark, "stata", text)
    assert [g[:3] for g in got] == [
        ("regress", "linear", "y"), ("reg", "linear", "y2"), ("reg", "linear", "y4"), ("reg", "linear", "y5"), ("logit", "binary", "y9"), ("zinb", "count", "y10"),
    ]
    assert [g[3] for g in got[:4]] == [False, False, False, True]


def test_r_commands(spark):
    text = "\n".join(
        ["# lm(no ~ x)", "a <- lm(y ~ x, data = d)", "b <- glm(y2 ~ x,", "  family = binomial(link = 'logit'))", "c <- glm(y3 ~ x)", "e <- lm(log(y4) ~ x)",
         "f <- glm(y5 ~ x, family = quasipoisson)", "plot(y ~ x)", "g <- lm_robust(y6 ~ x, weights = w)", "h <- mylm(y7 ~ x)",
         "k <- lm(y8 ~ x, data = d, subset = z > 1)"]
    )
    got = pairs_of(spark, "r", text)
    assert [g[:3] for g in got] == [
        ("lm", "linear", "y"), ("glm", "binary", "y2"), ("glm", "linear", "y3"), ("lm", "linear", "log(y4)"), ("glm", "count", "y5"), ("lm_robust", "linear", "y6"), ("lm", "linear", "y8"),
    ]
    # R's weights are accepted, though not reconstructed; its subset is not.
    assert [g[3] for g in got[-2:]] == [False, True]
    assert pairs_of(spark, "rmd", "lm(a ~ b)\n```{r}\nlm(y ~ x)\n```\n")[0][2] == "y"


def test_designs_of_commands(spark):
    stata = "reg y a b, robust\nreg y i.g a if z > 1\nreg y a [pw=w]\nreg y c.a##i.g\nreg y log(a)"
    r = "lm(y ~ a + factor(g), data = d)\nlm(y ~ a * b)\nlm(y ~ a:b + c, weights = w)\nlm(y ~ poly(a, 2))\nlm(y ~ as.factor(g))"
    rows = [(1, "s", "stata", stata), (1, "t", "r", r)]
    df = spark.createDataFrame(rows, "deposit_id long, file_id string, lang string, text string")
    got = [(x.design, x.excluded) for x in extraction.pairs(extraction.logical_lines(df)).orderBy("file_id", "line_no").collect()]
    assert got == [
        (["a", "b"], False), (["i.g", "a"], True), (["a"], True), (None, True), (None, False),
        (["a", "i.g"], False), (["a", "b", "a:b"], False), (["a:b", "c"], False), (None, False), (["i.g"], False),
    ]


def test_exact_name_beats_log_prefix(spark):
    names = spark.createDataFrame([(1, "l_tax", "count"), (1, "tax", "ordinal"), (1, "pop", "count")], "deposit_id long, name string, class string")
    asked = spark.createDataFrame([(1, "l_tax"), (1, "lnpop"), (1, "log(pop)"), (1, "gone")], "deposit_id long, response string")
    got = {(r.response, r.column, r.link_kind) for r in extraction.match_outcomes(asked, names).collect()}
    assert got == {("l_tax", "l_tax", "exact"), ("lnpop", "pop", "log_prefix")}


def test_uncapped_harvest_keeps_all(spark):
    files = spark.createDataFrame([(1, "do", i, 10 ** (i + 4)) for i in range(12)], "deposit_id long, kind string, listing_order int, bytes long")
    assert extraction.apply_limits(files).where("kept").count() == 4
    assert extraction.apply_limits(files, max_bytes=None, max_per_kind=None).where("kept").count() == 12


def test_flags_are_what_the_rules_name(spark):
    rows = [(1, f, c, f"{f}{c}") for f in ("linear", "count") for c in ("count", "binary", "continuous", "heavy-tailed")]
    links = spark.createDataFrame(rows, "deposit_id long, family string, class string, column string")
    assert {(r["class"], r.tier) for r in screen.flagged(links).collect()} == {("count", "clear"), ("binary", "debated")}


def test_a_record_is_one_estimator_on_one_outcome(spark):
    """Three estimators on a column are three records of one question; a name in
    two files takes the class of the larger."""
    rows = [(1, e, "linear", "share", c, f, n) for e in ("lm", "lm_robust", "lmer") for c, f, n in (("proportion", "a", 9), ("ordinal", "b", 40), ("count", "c", 40))]
    links = spark.createDataFrame(rows, "deposit_id long, estimator string, family string, column string, class string, data_file string, n long")
    got = screen.flagged(links).collect()
    assert {(r.estimator, r["class"]) for r in got} == {(e, "ordinal") for e in ("lm", "lm_robust", "lmer")} and len(got) == 3


def test_queries_are_nested_and_mutations_show(spark):
    for name, g in graph.mutations(fixture.frames(spark)).items():
        ids = [{r.analysis_id for r in f(g).select("analysis_id").collect()} for f in (ledger.inventory, ledger.alerts, ledger.headline_alerts, ledger.reviewed)]
        assert ids[3] <= ids[2] <= ids[1] <= ids[0], name
        if name == "none":
            assert [len(i) for i in ids] == [4, 2, 1, 1]


def test_ledger_appends_once_and_retracts(spark):
    g = fixture.frames(spark)["role"]
    assert ledger.append(g, g).count() == g.count()
    gone = ledger.retract(g, "r3", 9)
    assert gone.count() == g.count() + 1
    assert "r3" not in {r.assertion_id for r in ledger.current(gone).collect()}
    assert "r3" in {r.assertion_id for r in ledger.as_of(gone, 8).collect()}


def test_turtle_round_trip_with_quotes_and_breaks(spark):
    texts = ['say "x"\nand \\n', "ends in \\\nbreak", "\\\\n", "tab\tcr\rlf\n", '"', "\\", "a > b <c> %3E", "\x01\x01", "\\1", "", " .", '"^^<text> .']
    rows = [("a/1", f"p{i}", x, "text") for i, x in enumerate(texts)] + [("a/1", "q", "b/2", "node"), ("a/1", "q", "b/3>\n%", "node"), ("a/<1>", "r", "3", "integer")]
    t = spark.createDataFrame(rows, graph.TRIPLE)
    lines = graph.to_turtle(t)
    assert not any("\n" in r.value or "\r" in r.value for r in lines.collect())
    assert graph.difference(t, graph.from_turtle(lines)).count() == 0
    documents = graph.to_jsonld(t)
    assert documents.count() == 2 and all('"@context"' in r.value for r in documents.collect())
    assert graph.difference(t, graph.from_jsonld(documents)).count() == 0


def test_every_record_class_is_closed(spark):
    g = fixture.frames(spark)
    t = graph.to_triples(g)
    assert graph.violations(t, graph.shapes(spark)).count() == 0 and graph.core_violations(t).count() == 0
    kinds = [k for k in graph.NODES if k not in graph.CORE]
    odd = t.where("p = 'type'").groupBy(F.split("s", "/")[0].alias("k")).agg(F.min("s").alias("s")).select("s", F.lit("extra").alias("p"), F.lit("x").alias("o"), F.lit("text").alias("o_kind"))
    assert {r.s.split("/")[0] for r in graph.violations(t.unionByName(odd), graph.shapes(spark)).where("kind = 'closed'").collect()} == set(kinds)
    assert {r.s.split("/")[0] for r in graph.core_violations(t.unionByName(odd)).collect()} == set(graph.CORE)
    untimed = g | {"generation": g["generation"].withColumn("time_uncertainty", F.lit(None).cast("string"))}
    assert {r.kind for r in graph.violations(graph.to_triples(untimed), graph.shapes(spark)).collect()} == {"no_time"}


def test_assertions_by_each_question_of_provenance(spark):
    g = fixture.frames(spark)
    ids = lambda **by: {r.assertion_id for r in ledger.selected(g, **by).collect()}
    assert ids(role="headline") == {"r1"} and ids(kind="role", state="unreviewed") == {"r2", "r3", "r4"}
    assert ids(method="deterministic", source="data profile") == {"u4"}
    assert ids(state="accepted") == {"r1", "u1", "e1"}
    conflict = g | {"review": g["review"].unionByName(spark.createDataFrame([("d9", "u1", "second", "rejected", 5, None)], g["review"].schema))}
    states = {r.target_id: r.state for r in ledger.review_state(conflict["review"]).collect()}
    assert states["u1"] == "conflict" and states["e1"] == "accepted"
    again = ledger.paper_summary(g).first()
    assert again.derived_from == ["e1", "r1", "u1"]


@pytest.mark.parametrize(("k", "n", "low", "high"), [(66, 119, 0.465, 0.641), (37, 60, 0.490, 0.729), (29, 59, 0.368, 0.616)])
def test_wilson(spark, k, n, low, high):
    lo, hi = measures.wilson(F.lit(float(k)), F.lit(float(n)))
    row = spark.range(1).select(lo.alias("lo"), hi.alias("hi")).first()
    assert (round(row.lo, 3), round(row.hi, 3)) == (low, high)


def test_weighted_precision_of_two_strata(spark):
    strata = spark.createDataFrame([(37, 60, 671), (29, 59, 167)], "k long, n long, weight long")
    assert abs(measures.weighted_precision(strata).first().precision - 0.5917) < 5e-4


def test_self_conflict_policies(spark):
    v = spark.createDataFrame([("s", 1, True), ("s", 1, False), ("s", 2, True)], "session string, question_id int, positive boolean")
    assert {r.question_id: r.positive for r in measures.collapse(v, favourable=True).collect()} == {1: True, 2: True}
    assert {r.question_id: r.positive for r in measures.collapse(v, favourable=False).collect()} == {1: None, 2: True}


def _irls(x, y, logit):
    x = np.column_stack([np.ones(len(x)), x])
    b = np.zeros(2)
    b[0] = np.log(y.mean() / (1 - y.mean())) if logit else np.log(y.mean())
    for _ in range(50):
        eta = x @ b
        mu = 1 / (1 + np.exp(-eta)) if logit else np.exp(eta)
        w = mu * (1 - mu) if logit else mu
        b = np.linalg.solve(x.T @ (x * w[:, None]), x.T @ (w * (eta + (y - mu) / w)))
    return b


@pytest.mark.parametrize("family", ["poisson", "fraclogit"])
def test_glm_matches_numpy(spark, family):
    rng = np.random.default_rng(1)
    x = rng.normal(size=400)
    mu = np.exp(0.3 + 0.5 * x)
    y = rng.poisson(mu).astype(float) if family == "poisson" else np.clip(mu / (1 + mu) + rng.normal(0, 0.05, 400), 0.01, 0.99)
    df = spark.createDataFrame(list(zip(y.tolist(), x.tolist(), strict=True)), "y double, x double")
    fit = refit.glm(df, "y", ["x"], family=family)
    assert np.allclose(list(fit["coefficients"].values()), _irls(x, y, family == "fraclogit"), atol=1e-6)


def test_ols_of_two_terms_and_singular_design(spark):
    df = spark.range(50).select((3.0 + 2 * F.col("id") - F.col("id") * F.col("id")).alias("y"), F.col("id").cast("double").alias("a"), (F.col("id") * F.col("id")).cast("double").alias("b"))
    fit = refit.ols(df, "y", ["a", "b"])
    assert np.allclose(list(fit["coefficients"].values()), [3, 2, -1], atol=1e-6)
    assert refit.ols(df.withColumn("c", 2 * F.col("a")), "y", ["a", "c"]) is None
    assert refit.violation_share(df, "y", ["a", "b"], fit, "count").first().share is None


def test_fits_of_factors_interactions_and_caps():
    rng = np.random.default_rng(5)
    g, a, b = np.repeat(np.arange(6.0), 20), rng.normal(size=120), rng.normal(size=120)
    y = 0.4 + 0.05 * g + 0.1 * a * b
    cols = {"y": y, "g": g, "a": a, "b": b}
    want = np.column_stack([np.ones(120), *[(g == k).astype(float) for k in range(1, 6)], a * b])
    fit = want @ np.linalg.lstsq(want, y, rcond=None)[0]
    got = refit.fit_rows(cols, "y", ["i.g", "a:b"], "count")
    assert (got["status"], got["n"], got["k"], got["n_outside"]) == ("fitted", 120, 7, int((fit < -1e-6).sum()))
    assert refit.fit_rows(cols | {"y": y - 5}, "y", ["a"], "count")["status"] == "response_outside"
    assert refit.fit_rows(cols | {"c": 2 * a}, "y", ["a", "c"], "count")["status"] == "singular"
    assert refit.fit_rows(cols | {"g": np.arange(120.0)}, "y", ["i.g"], "count")["status"] == "few_rows"
    assert refit.design_matrix({"g": np.arange(400.0)}, ["i.g"]) is None
    holed = cols | {"a": np.where(np.arange(120) < 95, np.nan, a)}
    assert refit.fit_rows(holed, "y", ["a"], "count")["status"] == "few_rows"


def test_refit_plan_takes_the_largest_file_and_eight_commands(spark):
    flags = spark.createDataFrame([(1, "lm", "y", "count"), (1, "lmer", "y", "count")], "deposit_id long, estimator string, outcome string, class string")
    rows = [(1, "lm", "y", "s", i, ["x"] if i else ["x", "i.g"], False) for i in range(10)] + [(1, "lm", "y", "s", 20, ["gone"], False), (1, "lmer", "y", "s", 30, ["x"], True)]
    commands = spark.createDataFrame(rows, "deposit_id long, estimator string, column string, file_id string, line_no int, design array<string>, excluded boolean")
    held = [(1, f, n, k) for f, k, names in (("big", 90, "yx"), ("small", 50, "yxg"), ("other", 99, "yg")) for n in names]
    profiles = spark.createDataFrame(held, "deposit_id long, file_id string, name string, n long")
    got = refit.plan(flags, commands, profiles).collect()
    assert {(r.line_no, r.data_file, r.n_rows) for r in got} == {(0, "small", 50), *((i, "big", 90) for i in range(1, 8))}
    assert {r.estimator for r in got} == {"lm"}


def test_row_cap_is_bounded_and_does_not_depend_on_partitions(spark):
    df = spark.range(5000).select((F.col("id") % 2).alias("k"), F.col("id").alias("v"), F.when(F.col("id") % 2 == 0, 2500).otherwise(50).alias("n"))
    df = df.where("k = 0 OR v < 100")
    pick = lambda d: sorted(tuple(r) for r in refit.hash_cap(d, ["k"], "n", rows=200).collect())
    one = pick(df.coalesce(1))
    assert one == pick(df.repartition(7))
    assert sum(k == 0 for k, _, _ in one) == 200 and sum(k == 1 for k, _, _ in one) == 50


def test_miss_reasons(spark):
    cases = spark.createDataFrame([(i, "y", "mismatch") for i in range(1, 8)] + [(8, "y", "control")], "deposit_id long, outcome string, label string")
    has = lambda ids, col: spark.createDataFrame([(i, "y") for i in ids], f"deposit_id long, {col} string")
    got = benchmark.misses(
        cases, has([1], "outcome"), read=has([1, 2, 3, 4], "response"), read_uncapped=has([1, 2, 3, 4, 5], "response"), read_prefixed=has([1, 2, 3, 4, 6], "response"),
        names=has([1, 2, 5, 6], "name"), names_uncapped=has([1, 2, 3, 5, 6, 7], "name"),
    )
    assert {r.deposit_id: r.reason for r in got.collect()} == {2: "class", 3: "data_limit", 4: "built_in_code", 5: "script_limit", 6: "prefix", 7: "no_command"}


def test_pairing_and_extraction(spark):
    d = spark.createDataFrame([(1, "Replication Data for: The Long  Title!", "doi:10.1/A"), (2, "Nothing alike", None), (3, "Lost", None)], "deposit_id long, title string, doi string")
    p = spark.createDataFrame([(7, "The long title, revised", "https://doi.org/10.1/a"), (8, "Other", None)], "paper_id long, title string, doi string")
    hand = spark.createDataFrame([(3, 8, "manual")], "deposit_id long, paper_id long, method string")
    both = fingerprint.resolve(d, fingerprint.by_doi(d, p), fingerprint.by_title(d, p), hand)
    assert {(r.deposit_id, r.paper_id, r.method) for r in both.collect()} == {(1, 7, "doi"), (2, None, "unresolved"), (3, 8, "manual")}
    assert fingerprint.by_title(d, p).count() == 1
    asked = spark.createDataFrame([("q1", "x"), ("q2", "y")], "request_id string, request string")
    assert {r.response for r in fingerprint.extract(asked, str.upper, calls=2).collect()} == {"X", "Y"}
    sheet = '[{"name":"turnout"},{"name":"price"}]'
    text = "Our outcome is turnout, explained by price by a Poisson count model. The predictor is price."
    request = '{"text": "%s", "sheet": %s}' % (text, sheet)
    rows = json.loads(fingerprint.extract_keywords(request))
    assert [(r["column"], r["use"], r["family"]) for r in rows] == [("turnout", "outcome", "count"), ("price", "predictor", "count")]
    silent = '{"text": "The outcome is gdp.", "sheet": %s, "code": "# nbreg\\nreg y x"}' % sheet
    assert [(r["column"], r["family"]) for r in json.loads(fingerprint.extract_keywords(silent))] == [("not in the metadata", "linear")]
    asked = spark.createDataFrame([("q1", request)], "request_id string, request string")
    two = json.loads(fingerprint.extract_two_step(asked, fingerprint.distil_keywords, fingerprint.extract_keywords).first().response)
    assert [(r["column"], r["family"]) for r in two] == [("turnout", "not stated"), ("price", "not stated")]


def test_sheet_guard_and_miss_kinds(spark):
    cells = [(1, f, n, float(v)) for f, n, vs in (("a", "hits", [0, 3, 9]), ("b", "hits", [0.5] * 9), ("a", "rate", [0.1, 0.9, 0.5])) for v in vs]
    profiles = classify.classified(evidence.profile_cells(spark.createDataFrame(cells, "deposit_id long, file_id string, name string, value double"), ["deposit_id", "file_id", "name"]))
    sheet = fingerprint.metadata_sheet(profiles, spark.createDataFrame([("rate", "a share")], "name string, label string"))
    got = {v["name"]: (v["label"], v["type"], v["low"], v["high"], v["n_distinct"], v["n_present"]) for v in sheet.first().sheet}
    assert got == {"hits": (None, "double", 0.5, 0.5, 1, 9), "rate": ("a share", "double", 0.1, 0.9, 3, 3)}
    said = [("rate", "proportion"), ("rate", "count"), ("rate", "linear"), ("hits", "binary"), ("nope", "linear"), ("not in the metadata", "linear"), ("rate", "not stated")]
    rows = spark.createDataFrame([(1, i, "arm", "x", i, "o", f, "headline", c, "outcome", "read") for i, (c, f) in enumerate(said)],
                                 "deposit_id long, request int, arm string, extractor string, case_id int, outcome string, family string, role string, column string, use string, status string")
    guarded = fingerprint.guard(rows, sheet)
    assert [r.status for r in guarded.orderBy("request").collect()] == ["accepted", "inconsistent", "accepted", "accepted", "unknown_column", "not_in_metadata", "accepted"]
    cases = spark.createDataFrame([(i, "rate", "proportion") for i in range(7)], "case_id int, column string, family string")
    twins = spark.createDataFrame([(3, "hits")], "case_id int, column string")
    scores = {r.case_id: (r.link, r.family, r.link_family, r.miss) for r in fingerprint.score(guarded, cases, twins).collect()}
    assert scores == {
        0: (True, True, True, None), 1: (False, False, False, "inconsistent"), 2: (True, False, False, "contradicted"), 3: (True, False, False, "contradicted"),
        4: (False, False, False, "unknown_column"), 5: (False, False, False, "not_in_metadata"), 6: (True, False, False, "not_stated"),
    }


def test_stream_equals_batch(spark, tmp_path):
    ev = spark.read.parquet("/root/testdata/sf0.001/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", "ts", "user_id", "event_type", "value")
    ev.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    stream = ingest.distinct_deliveries(stream, watermark="400 days")
    q = (
        ingest.windowed_profile(stream, by=["event_type"], watermark=None).select("window", "event_type", "n", "class")
        .writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "state")).foreachBatch(ingest.version_sink(str(tmp_path / "versions"), ["window", "event_type"])).start()
    )
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    stored = spark.read.parquet(str(tmp_path / "versions"))
    last = {(r.window.start, r.event_type): (r.n, r["class"]) for r in stored.groupBy("window", "event_type").agg(F.max_by(F.struct("n", "class"), "n").alias("m")).select("window", "event_type", "m.*").collect()}
    want = {(r.window.start, r.event_type): (r.n, r["class"]) for r in ingest.windowed_profile(ev, by=["event_type"]).collect()}
    assert last == want


def run_stream(spark, df, tmp_path, build, parts=None, **sink):
    """The table that a stream over files, one a batch, has written in the end."""
    for part in parts or [df.repartition(3)]:
        part.write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    writer = build(stream).writeStream.outputMode(sink.get("mode", "update")).option("checkpointLocation", str(tmp_path / "s"))
    q = writer.format("memory").queryName(sink["name"]).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return spark.table(sink["name"])


def test_running_profile_keeps_bounded_state_and_a_class(spark, tmp_path):
    values = {"few": [i % 5 for i in range(50)], "many": [i**3 for i in range(60)], "share": [i / 40 for i in range(41)], "codes": [1, 2, 3, 98, 99, 4], "none": [None, None, float("nan")]}
    cells = spark.createDataFrame([(c, None if v is None else float(v)) for c, vs in values.items() for v in vs], "column string, value double")
    got = run_stream(spark, cells, tmp_path, ingest.cumulative, name="running")
    last = {r.column: r.r for r in got.groupBy("column").agg(F.max_by(F.struct("nonnull", "n_distinct", "complete", "mean", "skew", "class"), "n").alias("r")).collect()}
    want = {r.column: r for r in classify.classified(evidence.profile_cells(cells, ["column"])).collect()}
    for c, row in want.items():
        assert (last[c].nonnull, last[c].n_distinct, last[c].complete, last[c]["class"]) == (row.nonnull, row.n_distinct, row.complete, row["class"]), c
        assert row.skew is None or abs(last[c].skew - row.skew) < 1e-9
    assert {c: r["class"] for c, r in last.items()} == {"few": "ordinal", "many": "count", "share": "proportion", "codes": "ordinal", "none": "categorical"}


@pytest.mark.parametrize("mode", ["append", "complete"])
def test_output_modes(spark, tmp_path, mode):
    """Append gives windows once they are closed, complete all of them each time."""
    ev = spark.range(200).select("id", F.timestamp_seconds(F.col("id") * 7200).alias("ts"), (F.col("id") % 7).cast("double").alias("value"))
    shown = lambda s: ingest.windowed_profile(s, length="1 day", watermark="1 hour").select(F.col("window.start").alias("at"), "n", "class")
    parts = [ev.where(F.floor(F.col("id") / 70) == i).coalesce(1) for i in range(3)]
    got = {(r.at, r.n, r["class"]) for r in run_stream(spark, ev, tmp_path, shown, parts, name=f"windows_{mode}", mode=mode).collect()}
    want = {(r.at, r.n, r["class"]) for r in shown(ev).collect()}
    assert got == want if mode == "complete" else got <= want and 0 < len(got) < len(want)


def test_late_rows_are_counted_and_queued(spark, tmp_path):
    day = lambda d, v: (F.timestamp_seconds(F.lit(d * 86400)).alias("ts"), F.lit(v).alias("value"))
    batches = [[(10, 1), (11, 2)], [(12, 3), (5, 4)], [(20, 5), (11, 6), (18, 7)]]
    taken = []
    router = ingest.late_router(str(tmp_path), lambda df, i: taken.append((i, sorted(r.value for r in df.collect()))))
    frames = []
    for rows in batches:
        out = None
        for d, v in rows:
            one = spark.range(1).select(*day(d, v))
            out = one if out is None else out.unionByName(one)
        frames.append(out)
    for i, df in enumerate(frames):
        router(df, i)
    router(frames[1], 1)  # delivered again
    assert taken == [(0, [1, 2]), (1, [3]), (2, [5, 6, 7]), (1, [3])]
    counts = {r.batch_id: (r.n, r.n_late) for r in spark.read.parquet(str(tmp_path / "counts")).collect()}
    assert counts == {0: (2, 0), 1: (2, 1), 2: (3, 0)}
    assert [r.value for r in spark.read.parquet(str(tmp_path / "late")).collect()] == [4]


def test_alerts_when_either_side_arrives(spark, tmp_path):
    """Profile first, use first, no rule, and too far apart in time."""
    at = lambda d: F.timestamp_seconds(F.lit(d * 86400))
    rows = [("v1", "count", 10, "a1", "linear", 12), ("v2", "binary", 15, "a2", "linear", 11), ("v3", "continuous", 10, "a3", "linear", 10), ("v4", "count", 2, "a4", "linear", 19)]
    p = u = None
    for v, c, t, a, f, s in rows:
        one = spark.range(1).select(F.lit(v).alias("variable_id"), F.lit(c).alias("class"), at(t).alias("profiled_at"))
        two = spark.range(1).select(F.lit(a).alias("analysis_id"), F.lit(v).alias("variable_id"), F.lit(f).alias("family"), at(s).alias("extracted_at"))
        p, u = (one, two) if p is None else (p.unionByName(one), u.unionByName(two))
    p.write.parquet(str(tmp_path / "p"))
    u.write.parquet(str(tmp_path / "u"))
    read = lambda n, like: spark.readStream.schema(like.schema).option("maxFilesPerTrigger", 2).parquet(str(tmp_path / n))
    found = ingest.alerts(read("p", p), read("u", u), screen.rule_table(spark))
    q = found.writeStream.outputMode("append").option("checkpointLocation", str(tmp_path / "s")).format("memory").queryName("raised").start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    assert {(r.analysis_id, r.tier) for r in spark.table("raised").collect()} == {("a1", "clear"), ("a2", "debated")}


def test_benchmark_rechecks_and_detector(spark):
    profiles = spark.createDataFrame([(1, "y", "count"), (2, "z", "continuous")], "deposit_id long, name string, class string")
    links = spark.createDataFrame([(1, "y", "linear", "count", "reg"), (2, "z", "linear", "continuous", "lm")], "deposit_id long, column string, family string, class string, command string")
    cases = spark.createDataFrame(
        [(1, "y", "linear", "count", "mismatch"), (2, "z", "linear", "count", "control"), (3, "w", "linear", "count", "mismatch")],
        "deposit_id long, outcome string, family string, recorded_class string, label string",
    )
    assert {(r.deposit_id, r.stratum) for r in benchmark.candidates(links).collect()} == {(1, "count-linear"), (2, "other fields")}
    checked = benchmark.recheck(cases, profiles, links)
    got = {r.deposit_id: (r.resolves, r.same_class, r.link_confirmed) for r in checked.collect()}
    assert got == {1: (True, True, True), 2: (True, False, True), 3: (False, False, False)}
    assert tuple(benchmark.agreement(cases, profiles).first()) == (3, 2, 1)
    assert tuple(benchmark.detector(cases, profiles).first()) == (1, 1.0, 0.5)
    assert {r.label: (r.n_cases, r.n_located) for r in benchmark.located(cases, profiles).collect()} == {"mismatch": (2, 1), "control": (1, 1)}
