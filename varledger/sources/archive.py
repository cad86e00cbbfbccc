"""A generated archive: one deposit for each part, with data cells from its
order lines, scripts, files, papers and reference cases that follow from the
part's key alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import table

COLUMNS = ("qty_share", "bulk", "disc", "returned", "line_no", "price")
#: Columns of the smaller extract that some deposits hold beside their data.
EXTRACT = ("qty_share", "bulk", "price")
#: Outcome by key modulo 5.
OUTCOMES = ("qty_share", "bulk", "disc", "returned", "line_no")
#: What each outcome is by its meaning, whatever its stored values look like.
RECORDED = {"qty_share": "proportion", "bulk": "count", "disc": "proportion", "returned": "binary", "line_no": "ordinal"}
LARGE, SMALL = 30_000_000, 1_000_000


def deposits(spark: SparkSession, sf_dir: str) -> DataFrame:
    key = F.col("p_partkey")
    return table(spark, sf_dir, "part").select(
        key.alias("deposit_id"), F.lit("1").alias("version"), F.col("p_type").alias("collection"),
        F.concat(F.lit("Replication Data for: "), _title(key)).alias("title"),
        F.when(key % 4 == 0, F.concat(F.lit("doi:10.5555/P"), key.cast("string"))).alias("doi"),
    )


# -- files -----------------------------------------------------------------
#
# Of key % 100: under 10 the script is listed ninth of its kind; under 39 no
# command is read (even keys: the survey prefix); under 49 the data file is too
# large; under 70 the outcome is built in code; from 70 on everything is there,
# and a third of those deposits hold an extract of their data as well.


def files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """deposit_id, file_id, kind, listing_order, bytes of every file."""
    key = F.col("p_partkey")
    g = key % 100
    kind = F.when(_lang(key) == "stata", "do").when(_lang(key) == "r", "R").otherwise("Rmd")

    def one(name, kind, order, size):
        return F.struct(name.alias("file_id"), kind.alias("kind"), order.cast("int").alias("listing_order"), size.cast("long").alias("bytes"))

    data = one(F.lit("data-1"), F.lit("csv"), F.lit(0), F.when((g >= 39) & (g < 49), LARGE).otherwise(SMALL))
    extract = F.when((g >= 70) & (key % 3 == 0), F.array(one(F.lit("data-2"), F.lit("csv"), F.lit(1), F.lit(SMALL // 2))))
    script = one(F.lit("code-1"), kind, F.when(g < 10, 10).otherwise(2), F.lit(2000))
    notes = F.when(g < 10, F.transform(F.sequence(F.lit(2), F.lit(9)), lambda i: one(F.concat(F.lit("note-"), i.cast("string")), kind, i, F.lit(500))))
    none = F.array().cast(f"array<{_FILE}>")
    every = F.concat(F.array(data), F.coalesce(extract, none), F.coalesce(notes, none), F.array(script))
    return table(spark, sf_dir, "part").select(key.alias("deposit_id"), F.inline(every))


_FILE = "struct<file_id:string,kind:string,listing_order:int,bytes:bigint>"
_LANG_SQL = "CASE WHEN p_partkey % 100 BETWEEN 10 AND 38 THEN CASE WHEN p_partkey % 2 = 0 THEN 'stata' ELSE 'r' END WHEN p_partkey % 7 IN (2, 3) THEN 'r' WHEN p_partkey % 7 = 5 THEN 'rmd' ELSE 'stata' END"
FILES_SQL = f"""SELECT p_partkey AS deposit_id, f.file_id, CASE WHEN f.kind = 'code' THEN CASE {_LANG_SQL} WHEN 'stata' THEN 'do' WHEN 'r' THEN 'R' ELSE 'Rmd' END ELSE f.kind END AS kind, f.listing_order,
  CAST(CASE WHEN file_id = 'data-1' AND p_partkey % 100 BETWEEN 39 AND 48 THEN {LARGE} ELSE f.bytes END AS BIGINT) AS bytes
FROM part, (VALUES ('data-1', 'csv', 0, {SMALL}), ('data-2', 'csv', 1, {SMALL // 2}), ('code-1', 'code', 2, 2000), ('code-1', 'code', 10, 2000),
  {", ".join(f"('note-{i}', 'code', {i}, 500)" for i in range(2, 10))}) f(file_id, kind, listing_order, bytes)
WHERE CASE WHEN file_id = 'data-2' THEN p_partkey % 100 >= 70 AND p_partkey % 3 = 0 WHEN file_id LIKE 'note-%' THEN p_partkey % 100 < 10
  WHEN file_id = 'code-1' THEN (p_partkey % 100 < 10) = (listing_order = 10) ELSE TRUE END"""


# -- data ------------------------------------------------------------------


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the data files: deposit_id, file_id and the columns; those that
    an extract lacks are null.  Some deposits store the share as a percentage."""
    q, key = F.col("l_quantity"), F.col("l_partkey")
    share = F.when(key % 3 == 1, q * 2).otherwise(q / 50)
    rows = table(spark, sf_dir, "lineitem").select(
        key.alias("deposit_id"), share.alias("qty_share"), F.when(q >= 45, q).otherwise(0.0).alias("bulk"),
        F.col("l_discount").alias("disc"), (F.col("l_returnflag") == "R").cast("double").alias("returned"),
        F.col("l_linenumber").cast("double").alias("line_no"), F.col("l_extendedprice").alias("price"),
    )
    of = F.col("deposit_id")
    both = F.when((of % 100 >= 70) & (of % 3 == 0) & (F.col("line_no") <= 2), F.array(F.lit("data-1"), F.lit("data-2"))).otherwise(
        F.array(F.lit("data-1"))
    )
    held = rows.withColumn("file_id", F.explode(both))
    return held.select(
        "deposit_id", "file_id",
        *[F.col(c) if c in EXTRACT else F.when(F.col("file_id") == "data-1", F.col(c)).alias(c) for c in COLUMNS],
    )


def cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """deposit_id, file_id, name, value of every stored cell."""
    long = wide(spark, sf_dir).unpivot(["deposit_id", "file_id"], list(COLUMNS), "name", "value")
    return long.where((F.col("file_id") == "data-1") | F.col("name").isin(*EXTRACT))


_VALUE_SQL = {
    "qty_share": "CASE WHEN l_partkey % 3 = 1 THEN l_quantity * 2 ELSE l_quantity / 50 END",
    "bulk": "CASE WHEN l_quantity >= 45 THEN l_quantity ELSE 0 END",
    "disc": "l_discount",
    "returned": "CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END",
    "line_no": "l_linenumber",
    "price": "l_extendedprice",
}
ALL_CELLS_SQL = " UNION ALL ".join(
    [f"SELECT l_partkey AS deposit_id, 'data-1' AS file_id, '{n}' AS name, CAST({e} AS DOUBLE) AS v FROM lineitem" for n, e in _VALUE_SQL.items()]
    + [
        f"SELECT l_partkey, 'data-2', '{n}', CAST({_VALUE_SQL[n]} AS DOUBLE) FROM lineitem WHERE l_partkey % 100 >= 70 AND l_partkey % 3 = 0 AND l_linenumber <= 2"
        for n in EXTRACT
    ]
)
#: Without the files that the harvest skips.
CELLS_SQL = f"SELECT * FROM ({ALL_CELLS_SQL}) WHERE NOT deposit_id % 100 BETWEEN 39 AND 48"


def _pick(values: tuple[str, ...], key: Column) -> Column:
    out = F.lit(values[-1])
    for i, v in enumerate(values[:-1]):
        out = F.when(key % len(values) == i, F.lit(v)).otherwise(out)
    return out


# -- scripts ---------------------------------------------------------------


def _lang(key: Column) -> Column:
    g, kind = key % 100, key % 7
    return F.when((g >= 10) & (g < 39), F.when(key % 2 == 0, "stata").otherwise("r")).otherwise(
        F.when(kind.isin(2, 3), "r").when(kind == 5, "rmd").otherwise("stata")
    )


def _line(*parts) -> Column:
    return F.concat(*[p if isinstance(p, Column) else F.lit(p) for p in parts])


def scripts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """deposit_id, file_id, lang, text of every script.  A main command, by key
    modulo 7, and further ones on the same outcome by key modulo 4: another
    estimator, another design, or nine more records of a command."""
    key = F.col("p_partkey")
    g, kind, more = key % 100, key % 7, key % 4
    name = F.concat(F.when((g >= 49) & (g < 70), F.lit("built_")).otherwise(F.lit("")), _pick(OUTCOMES, key))
    stata_head = F.lit("* earlier: regress other price\nuse data, clear\n/* reg never price */\n")
    r_head = F.lit("# lm(other ~ price)\nd <- read.csv('data.csv')\n")
    nothing = F.when(key % 2 == 0, _line(stata_head, "svy: regress ", name, " price\n")).otherwise(
        _line(r_head, "summary(d$", name, ")\n")
    )
    in_stata = (
        F.when(more == 1, _line("xtreg ", name, " price, fe\n")).when(more == 2, _line("regress ", name, " i.line_no\n"))
        .when(more == 3, F.repeat(_line("regress ", name, " price\n"), 9)).otherwise("")
    )
    in_r = (
        F.when(more == 1, _line("lm_robust(", name, " ~ price, data = d)\n"))
        .when(more == 2, _line("lm(", name, " ~ factor(line_no), data = d)\n"))
        .when(more == 3, _line("lm(", name, " ~ price:disc, data = d)\n")).otherwise("")
    )
    some = (
        F.when(kind == 0, _line(stata_head, "regress ", name, " ///\n    price // main\n", in_stata))
        .when(kind == 1, _line(stata_head, "reg ", name, " price, robust\n", in_stata))
        .when(kind == 2, _line(r_head, "fit <- lm(", name, " ~ price,\n  data = d)\n", in_r))
        .when(kind == 3, _line(r_head, "m <- glm(", name, " ~ price, family = poisson(), data = d)\n", in_r))
        .when(kind == 4, _line(stata_head, "quietly nbreg ", name, " price\n", in_stata))
        .when(kind == 5, _line("# Report\n\n```{r fit}\n", r_head, "m <- glm(", name, " ~ price, data = d)\n", in_r, "```\nlm(prose ~ x) in text\n"))
        .otherwise(_line(stata_head, "xi: reg ", name, " i.line_no if price > 0\n", in_stata))
    )
    main = F.struct(F.lit("code-1").alias("file_id"), F.when((g >= 10) & (g < 39), nothing).otherwise(some).alias("text"))
    notes = F.transform(F.sequence(F.lit(2), F.lit(9)), lambda i: F.struct(F.concat(F.lit("note-"), i.cast("string")).alias("file_id"), F.lit("* notes\n# only\n").alias("text")))
    held = F.when(g < 10, F.concat(F.array(main), notes)).otherwise(F.array(main))
    return table(spark, sf_dir, "part").select(key.alias("deposit_id"), _lang(key).alias("lang"), F.inline(held)).select(
        "deposit_id", "file_id", "lang", "text"
    )


_OUTCOME_SQL = f"""CASE p_partkey % 5 {" ".join(f"WHEN {i} THEN '{o}'" for i, o in enumerate(OUTCOMES))} END"""
_BASE_SQL = f"""SELECT p_partkey AS deposit_id, p_type AS collection, p_partkey % 100 AS grp, {_LANG_SQL} AS lang, p_partkey % 7 AS kind, p_partkey % 4 AS more,
  {_OUTCOME_SQL} AS outcome, CASE WHEN p_partkey % 100 BETWEEN 49 AND 69 THEN 'built_' ELSE '' END || {_OUTCOME_SQL} AS response FROM part"""
#: Every command record that a reader of all scripts finds, from the keys
#: alone: ``place`` orders a script's, ``plain`` those open to a refit.
TRUTH_SQL = f"""
SELECT deposit_id, collection, grp, outcome, response, 0 AS place,
  CASE kind WHEN 0 THEN 'regress' WHEN 1 THEN 'reg' WHEN 2 THEN 'lm' WHEN 3 THEN 'glm' WHEN 4 THEN 'nbreg' WHEN 5 THEN 'glm' ELSE 'reg' END AS command,
  CASE WHEN kind IN (0, 1, 6) THEN 'regress' WHEN kind = 2 THEN 'lm' WHEN kind = 4 THEN 'nbreg' ELSE 'glm' END AS estimator,
  CASE WHEN kind IN (3, 4) THEN 'count' ELSE 'linear' END AS family, CASE WHEN kind = 6 THEN 'i.line_no' ELSE 'price' END AS design, kind IN (0, 1, 2) AS plain
FROM ({_BASE_SQL}) WHERE grp < 10 OR grp >= 39
UNION ALL
SELECT deposit_id, collection, grp, outcome, response, 1 + CAST(i AS INTEGER),
  CASE WHEN lang = 'stata' THEN CASE more WHEN 1 THEN 'xtreg' ELSE 'regress' END WHEN more = 1 THEN 'lm_robust' ELSE 'lm' END,
  CASE WHEN lang = 'stata' THEN CASE more WHEN 1 THEN 'xtreg' ELSE 'regress' END WHEN more = 1 THEN 'lm_robust' ELSE 'lm' END,
  'linear', CASE WHEN more = 2 THEN 'i.line_no' WHEN more = 3 AND lang <> 'stata' THEN 'price:disc' ELSE 'price' END, NOT (lang = 'stata' AND more = 1)
FROM ({_BASE_SQL}), range(0, 9) r(i) WHERE (grp < 10 OR grp >= 39) AND more > 0 AND (i = 0 OR (more = 3 AND lang = 'stata'))
"""


# -- benchmark cases -------------------------------------------------------


def cases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One reference case a deposit: deposit_id, outcome as the analysis names
    it, family and recorded class by meaning, label."""
    key = F.col("p_partkey")
    g = key % 100
    base = _pick(OUTCOMES, key)
    name = F.concat(F.when((g >= 49) & (g < 70), F.lit("built_")).otherwise(F.lit("")), base)
    family = F.when((key % 7).isin(3, 4), "count").otherwise("linear")
    recorded = F.create_map(*[F.lit(x) for kv in RECORDED.items() for x in kv])[base]
    return table(spark, sf_dir, "part").select(
        key.alias("deposit_id"), name.alias("outcome"), family.alias("family"), recorded.alias("recorded_class"),
        F.when(family == "linear", "mismatch").otherwise("control").alias("label"),
    )


CASES_SQL = f"""SELECT deposit_id, grp, outcome AS base, response AS outcome, CASE WHEN kind IN (3, 4) THEN 'count' ELSE 'linear' END AS family,
  CASE outcome {" ".join(f"WHEN '{k}' THEN '{v}'" for k, v in RECORDED.items())} END AS recorded_class, CASE WHEN kind IN (3, 4) THEN 'control' ELSE 'mismatch' END AS label
FROM ({_BASE_SQL})"""


# -- papers ----------------------------------------------------------------


def _title(key: Column) -> Column:
    return F.concat_ws(" ", F.col("p_name"), F.lit("study"), key.cast("string"))


def papers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """paper_id, doi, title, text of each deposit's paper.  Every eleventh came
    out under another title and identifier.  Of key % 20, 15 writes of a twin
    column, 17 of no stored column, 18 only of predictors; every fourth leaves
    the estimator unstated."""
    key = F.col("p_partkey")
    g, roll, moved = key % 100, key % 20, key % 11 == 0
    own = F.concat(F.when((g >= 49) & (g < 70), F.lit("built_")).otherwise(F.lit("")), _pick(OUTCOMES, key))
    what = F.when(roll == 15, _pick(OUTCOMES, key + 1)).when(roll == 17, "an index of our own").otherwise(own)
    model = F.when(key % 4 == 3, "").when((key % 7).isin(3, 4), " by a Poisson count model").otherwise(" by ordinary least squares")
    text = F.when(roll == 18, _line("We explain growth", model, ". The predictor is ", own, ".")).otherwise(
        _line("Our main outcome is ", what, ", explained by price", model, ".")
    )
    return table(spark, sf_dir, "part").select(
        key.alias("paper_id"), F.concat(F.when(moved, "https://doi.org/10.7777/m").otherwise("https://doi.org/10.5555/p"), key.cast("string")).alias("doi"),
        F.when(moved, F.concat(F.lit("Manuscript no "), key.cast("string"))).otherwise(_title(key)).alias("title"), text.alias("text"),
    )


def by_hand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs found by hand: every second of those that moved."""
    key = F.col("p_partkey")
    found = table(spark, sf_dir, "part").select(F.when(key % 22 == 0, key).alias("deposit_id"), F.when(key % 22 == 0, key).alias("paper_id"))
    return found.dropna().withColumn("method", F.lit("manual"))


def twins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """case_id, column: the accepted twin of each case's outcome."""
    key = F.col("p_partkey")
    return table(spark, sf_dir, "part").select(key.alias("case_id"), _pick(OUTCOMES, key + 1).alias("column"))


def listing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A longer listing of files, some large, some beyond the eighth of their
    kind."""
    key = F.col("p_partkey")
    return table(spark, sf_dir, "part").select(
        key.alias("deposit_id"), F.explode(F.sequence(F.lit(0).cast("long"), key % 30)).alias("listing_order")
    ).select(
        "deposit_id", F.col("listing_order").cast("int").alias("listing_order"),
        F.when(F.col("listing_order") % 3 == 0, "do").otherwise("csv").alias("kind"),
        ((F.col("deposit_id") * 7919 + F.col("listing_order") * 1000003) % 40000000).alias("bytes"),
    )


LISTING_SQL = """
SELECT p_partkey AS deposit_id, CAST(i AS INTEGER) AS listing_order, CASE WHEN i % 3 = 0 THEN 'do' ELSE 'csv' END AS kind,
       (p_partkey * 7919 + i * 1000003) % 40000000 AS bytes
FROM (SELECT p_partkey, unnest(range(0, p_partkey % 30 + 1)) AS i FROM part)
"""
