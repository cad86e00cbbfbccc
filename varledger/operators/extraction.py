"""Harvest limits, script normalisation and regression commands, by regular
expressions only; what does not match is left out rather than guessed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.rules import COMMANDS, GLM_FAMILIES, PREFIXES, SHORT_FORMS
from .joins import grown

NAME = r"^[A-Za-z_.][A-Za-z0-9_.]*$"


def apply_limits(files: DataFrame, *, max_bytes: int | None = 25 << 20, max_per_kind: int | None = 8) -> DataFrame:
    """Add kept and reason.  Size goes first; then the first files of a kind in
    listing order stay.  None lifts a limit (the uncapped harvest)."""
    small = F.lit(True) if max_bytes is None else F.col("bytes") <= max_bytes
    order = Window.partitionBy("deposit_id", "kind", "_small").orderBy("listing_order")
    out = files.withColumn("_small", small).withColumn("_place", F.row_number().over(order))
    near = F.lit(True) if max_per_kind is None else F.col("_place") <= max_per_kind
    reason = F.when(~F.col("_small"), "too_large").when(~near, "beyond_limit").otherwise("kept")
    return out.withColumn("reason", reason).withColumn("kept", F.col("reason") == "kept").drop("_small", "_place")


def clean_pool(deposits: DataFrame, known: DataFrame) -> DataFrame:
    """Deposits with a reason to drop leftovers: no archive id, or a checksum
    that a harvested deposit has already."""
    seen = known.select("checksum").distinct().withColumn("_seen", F.lit(True))
    out = deposits.join(seen, "checksum", "left")
    return out.withColumn(
        "reason", F.when(F.col("deposit_id").isNull(), "no_id").when(F.col("_seen"), "duplicate").otherwise("kept")
    ).drop("_seen")


def attach_sibling(deposits: DataFrame, scripts: DataFrame, siblings: DataFrame) -> DataFrame:
    """Scripts of each deposit and of the one it shares code with; the locator
    keeps the true holder in code_deposit_id."""
    own = scripts.withColumn("code_deposit_id", F.col("deposit_id"))
    other = (
        siblings.select("deposit_id", F.col("sibling_id").alias("code_deposit_id"))
        .join(scripts.withColumnRenamed("deposit_id", "code_deposit_id"), "code_deposit_id")
    )
    return own.unionByName(other).join(deposits.select("deposit_id"), "deposit_id", "left_semi")


def logical_lines(scripts: DataFrame) -> DataFrame:
    """One row for each logical line: comments out, continuations joined, only
    the code chunks of R Markdown."""
    t = F.regexp_replace("text", r"\r\n?", "\n")
    stata = F.regexp_replace(t, r"///[^\n]*\n", " ")
    stata = F.regexp_replace(stata, r"(?s)/\*.*?\*/", " ")
    stata = F.regexp_replace(stata, r"(?m)^[ \t]*\*[^\n]*$", "")
    stata = F.regexp_replace(stata, r"(?m)(^|[ \t])//[^\n]*$", "")

    def r_code(x: Column) -> Column:
        return F.regexp_replace(F.regexp_replace(x, r"#[^\n]*", ""), r"([,(~+=])[ \t]*\n[ \t]*", "$1 ")

    chunks = F.array_join(F.regexp_extract_all(t, F.lit(r"(?s)```\{r[^}]*\}\n(.*?)```"), 1), "\n")
    code = F.when(F.col("lang") == "stata", stata).when(F.col("lang") == "rmd", r_code(chunks)).otherwise(r_code(t))
    return (
        scripts.select(*[c for c in scripts.columns if c != "text"], F.posexplode(F.split(code, "\n")).alias("line_no", "line"))
        .where(F.trim("line") != "")
    )


def families(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(COMMANDS, "dialect string, command string, family string, refit boolean")


def _any(words) -> str:
    return "|".join(sorted((w.replace(".", r"\.") for w in words), key=len, reverse=True))


def stata_pattern(prefixes: tuple[str, ...] = PREFIXES) -> str:
    commands = _any(c for d, c, _, _ in COMMANDS if d == "stata")
    lead = rf"(?:(?:{_any(prefixes)})(?:[ \t]+[\w ,()]*?)?[ \t]*:[ \t]*|(?:quietly|qui|capture|cap|noisily|noi)[ \t]+)*"
    return rf"^[ \t]*{lead}({commands})[ \t]+([A-Za-z_]\w*)\b(.*)$"


def r_pattern() -> str:
    commands = _any(c for d, c, _, _ in COMMANDS if d == "r")
    return rf"^.*?(?<![\w.])({commands})[ \t]*\([ \t]*(?:formula[ \t]*=[ \t]*)?([\w.]+(?:\([^()]*\))?)[ \t]*~[ \t]*(.*)$"


def _mapped(column: Column, pairs: dict[str, str]) -> Column:
    return F.coalesce(F.create_map(*[F.lit(x) for kv in pairs.items() for x in kv])[column], column)


def pairs(lines: DataFrame, *, prefixes: tuple[str, ...] = PREFIXES) -> DataFrame:
    """deposit_id, file_id, line_no, dialect, command, estimator (a short form
    by its full name), response, terms, design, family and whether a refit is
    excluded, of each estimator call.  The survey prefix is not accepted unless
    named in ``prefixes``.

    Each line meets the pattern of its own language once.  Excluded from refits
    are Stata's if, in, bracketed weights, absorbed effects and interactions
    and R's subset; weights of R are accepted, though not reconstructed.
    """
    spark = lines.sparkSession
    stata = F.col("lang") == "stata"
    mark = "\u0001"
    groups = f"$1{mark}$2{mark}$3"
    cut = F.when(stata, F.regexp_replace("line", stata_pattern(prefixes), groups)).otherwise(
        F.regexp_replace("line", r_pattern(), groups)
    )
    more = [c for c in lines.columns if c not in ("deposit_id", "file_id", "line_no", "lang", "line")]
    found = lines.select(
        *more, "deposit_id", "file_id", "line_no", F.when(stata, "stata").otherwise("r").alias("dialect"), F.split(cut, mark).alias("p")
    ).where(F.size("p") == 3)
    found = found.select(
        *more, "deposit_id", "file_id", "line_no", "dialect", *[F.col("p")[i].alias(n) for i, n in enumerate(("command", "response", "terms"))]
    )
    out = found.join(F.broadcast(families(spark)), ["dialect", "command"])
    argument = F.regexp_extract("terms", r"family[ \t]*=[ \t]*[\"']?(\w+)", 1)
    by_argument = F.create_map(*[x for k, v in GLM_FAMILIES.items() for x in (F.lit(k), F.lit(v))])
    glm = F.when(argument == "", "linear").otherwise(F.coalesce(by_argument[argument], F.lit("other")))
    marks = F.when(
        F.col("dialect") == "stata",
        F.col("terms").rlike(r"\b(if|in)\b[ \t]+\S|\[[ \t]*[apfi]?w(eight)?[ \t]*=|absorb\(|#"),
    ).otherwise(F.col("terms").rlike(r"subset[ \t]*="))
    return out.select(
        *more, "deposit_id", "file_id", "line_no", "dialect", "command", _mapped(F.col("command"), SHORT_FORMS).alias("estimator"),
        "response", "terms", design().alias("design"),
        F.when(F.col("family") == "by family", glm).otherwise(F.col("family")).alias("family"), (~F.col("refit") | marks).alias("excluded"),
    )


def design() -> Column:
    """Terms of a command as an array: a plain name, i.name for a factor, or
    a:b for a numeric interaction; null where any term is something else."""
    plain = r"[A-Za-z_][A-Za-z0-9_.]*"
    stata = F.split(F.trim(F.regexp_extract("terms", r"^([^,\[]*?)(?:[ \t]+(?:if|in)\b[^,]*)?(?:[,\[].*)?$", 1)), r"[ \t]+")

    def r_term(t: Column) -> Column:
        factor = F.regexp_extract(t, rf"^(?:as\.)?factor\(({plain})\)$", 1)
        a, b = (F.regexp_extract(t, rf"^({plain})\s*\*\s*({plain})$", i) for i in (1, 2))
        return (
            F.when(factor != "", F.array(F.concat(F.lit("i."), factor)))
            .when(a != "", F.array(a, b, F.concat_ws(":", a, b))).otherwise(F.array(F.regexp_replace(t, r"\s", "")))
        )

    right = F.trim(F.regexp_extract("terms", r"^((?:[^,()]|\([^()]*\))*)", 1))
    tokens = F.when(F.col("dialect") == "stata", stata).otherwise(F.flatten(F.transform(F.split(right, r"\s*\+\s*"), r_term)))
    return F.when(F.forall(tokens, lambda t: t.rlike(rf"^(i\.)?{plain}$|^{plain}:{plain}$")), F.array_distinct(tokens))


def kept_files(rows: DataFrame, files: DataFrame, *, merge: bool = False, **limits) -> DataFrame:
    """Rows of the files that the harvest keeps.  ``merge`` where they are few
    a file, as scripts and profiles are and cells are not."""
    kept = apply_limits(files, **limits).where("kept").select("deposit_id", "file_id")
    return rows.join(grown(kept) if merge else kept, ["deposit_id", "file_id"], "left_semi")


def match_outcomes(found: DataFrame, names: DataFrame, *, log_prefixes: tuple[str, ...] = ("ln", "l_")) -> DataFrame:
    """Responses that are plain names of a column of the same deposit.  An exact
    name wins; of the rest, a log prefix before a column's name links to it."""
    plain = found.where(F.col("response").rlike(NAME))
    exact = plain.join(grown(names.withColumnRenamed("name", "column")), (plain.response == F.col("column")) & (plain.deposit_id == names.deposit_id)).drop(names.deposit_id)
    exact = exact.withColumn("link_kind", F.lit("exact"))
    rest = plain.join(grown(names.select("deposit_id", F.col("name").alias("response"))), ["deposit_id", "response"], "left_anti")
    raw = F.lit(None).cast("string")
    for p in sorted(log_prefixes, key=len):
        raw = F.when(F.col("response").startswith(p), F.substring("response", len(p) + 1, 10_000)).otherwise(raw)
    logged = rest.withColumn("column", raw).join(grown(names.withColumnRenamed("name", "column")), ["deposit_id", "column"])
    return exact.unionByName(logged.withColumn("link_kind", F.lit("log_prefix")))
