"""Quality rules as a short-circuit cascade, in DataFrame functions only.

Text statistics are computed once a row.  Each rule rejects a row by an
expression over them or the text.  On a bounded sample, drawn before any
statistics, the cost of each rule is timed and its rejection rate counted;
rules are then tried in the order of rejection per cost, and a row that one
rule rejects is not put to the others.  Rules that only compare numbers cost
less than the clock's noise and rank by their rejections; what the cascade
saves are the passes over the text.  The order changes the work, never the
verdict.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from statistics import median

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD_SPACE, written

GAP = r"[\x20\x09-\x0D]+"
WINDOW = 8


def _repeats(rows: DataFrame) -> DataFrame:
    """Add n_repeat_words to rows with ``words``: words in windows that occur
    twice or more in the row, counted once each.  All steps are linear in the
    row's length but for one sort, which only rows with repeats need."""
    n = F.size("words")
    rows = rows.withColumn(
        "h",
        F.when(
            n > WINDOW,
            # Element by element: slice() would copy the whole array each time.
            F.transform(
                F.sequence(F.lit(0), n - WINDOW),
                lambda i: F.xxhash64(*[F.get(F.col("words"), i + k) for k in range(WINDOW)]),
            ),
        ).otherwise(F.expr("cast(array() as array<bigint>)")),
    )
    # Hash and place, sorted, for rows where some hash repeats.
    rows = rows.withColumn(
        "s",
        F.when(
            F.size(F.array_distinct("h")) < F.size("h"),
            F.array_sort(F.transform("h", lambda x, i: F.struct(x.alias("h"), i.alias("p")))),
        ).otherwise(F.expr("cast(array() as array<struct<h:bigint,p:int>>)")),
    )
    s = F.col("s")
    rows = rows.withColumn(
        "p",
        F.array_sort(
            F.transform(
                F.filter(
                    s, lambda x, i: (x["h"] == F.get(s, i - 1)["h"]) | (x["h"] == F.get(s, i + 1)["h"])
                ),
                lambda x: x["p"],
            )
        ),
    )
    step = F.zip_with("p", F.slice("p", 2, F.greatest(F.size("p"), F.lit(1))), lambda a, b: F.least(F.lit(WINDOW), F.coalesce(b - a, F.lit(WINDOW))))
    covered = F.aggregate(step, F.lit(0).cast("long"), lambda t, x: t + x)
    # The rand() term is always 0.  It keeps the optimizer from moving a later
    # filter on this count below these steps, where it would repeat them for
    # every element.
    barrier = F.floor(F.rand(0)).cast("long")
    return rows.withColumn("n_repeat_words", covered + barrier).drop("h", "s", "p")


def text_statistics(docs: DataFrame, *, text_col: str = "text") -> DataFrame:
    """``docs`` as column ``row`` with the statistics the rules use.  A null
    text has the statistics of an empty one."""
    text = F.coalesce(F.col(f"row.`{text_col}`").cast("string"), F.lit(""))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")).withColumn("text", text)
    core = F.btrim(F.col("text"), F.lit(WORD_SPACE))
    rows = rows.withColumn(
        "words", F.when(F.length(core) > 0, F.split(core, GAP)).otherwise(F.expr("cast(array() as array<string>)"))
    )
    rows = rows.withColumn("lines", F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    rows = _repeats(rows)
    return rows.select(
        "row",
        "text",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.regexp_count("text", F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.size("lines").cast("long").alias("n_lines"),
        "n_repeat_words",
    )


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[], Column]


def _share_of(part: str, whole: str, limit: float) -> Callable[[], Column]:
    return lambda: F.col(part) > F.lit(limit) * F.col(whole)


#: Usual thresholds of published web corpora; each must keep clean prose.
RULES = (
    Rule("symbols", _share_of("n_symbols", "n_words", 0.1)),
    Rule("duplicate_lines", _share_of("n_dup_lines", "n_lines", 0.34)),
    Rule(
        "word_length",
        lambda: (F.col("word_chars") < 2.5 * F.col("n_words")) | (F.col("word_chars") > 12 * F.col("n_words")),
    ),
    Rule(
        "letters",
        lambda: F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]*?\p{L}[^\x20\x09-\x0D]*+")) < 0.7 * F.col("n_words"),
    ),
    Rule(
        "capitals",
        lambda: F.regexp_count("text", F.lit(r"\p{Lu}")) * 2 > F.col("word_chars"),
    ),
)


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def sampled(docs: DataFrame, rows: int) -> DataFrame:
    """About ``rows`` rows from all partitions, at most ``rows``."""
    n = docs.count()
    return docs.where(F.rand(11) < 1.2 * rows / max(n, 1)).limit(rows)


def ordered(stats: DataFrame, rules: tuple[Rule, ...] = RULES, *, sample_rows: int = 1000, times: int = 4, passes: int = 3) -> list[Rule]:
    """``rules`` by rejection per cost on at most ``sample_rows`` rows that the
    base keeps.  A rule's cost is the median time of ``passes`` passes over the
    sample (each row ``times`` times) less that of passes without a rule, and
    no less than the spread of those, which is the clock's noise."""
    sample = written(
        stats.drop("row").limit(sample_rows).where(~base_failed()).withColumn("again", F.explode(F.sequence(F.lit(1), F.lit(times)))),
        "quality-sample",
    )

    def timed(test: Column) -> tuple[list[float], int, int]:
        took = []
        for _ in range(passes):
            began = time.perf_counter()
            got = sample.agg(F.count_if(test).alias("hit"), F.count("*").alias("n"), F.max("text").isNull()).first()
            took.append(time.perf_counter() - began)
        return took, got.hit, got.n

    timed(F.lit(True))
    idle = timed(F.lit(True))[0]
    noise = max(idle) - min(idle)
    score = {}
    for rule in rules:
        took, hit, n = timed(rule.rejects())
        score[rule.name] = (hit + 1) / (n + 2) / max(median(took) - median(idle), noise, 1e-3)
    return sorted(rules, key=lambda r: (-score[r.name], r.name))


def cascade(rules: list[Rule]) -> Column:
    """True for a row that no rule rejects; evaluation stops at the first that
    does."""
    verdict = F.when(base_failed(), F.lit(False))
    for rule in rules:
        verdict = verdict.when(rule.rejects(), F.lit(False))
    return verdict.otherwise(F.lit(True))


def judge(docs: DataFrame, *, text_col: str = "text", rules: tuple[Rule, ...] = RULES, sample_rows: int = 1000) -> DataFrame:
    """``row`` (all input columns), the statistics, base_failed and kept.

    Null and empty texts have no words and fail the base; null ids and repeated
    rows pass through; an empty table gives no rows.
    """
    stats = text_statistics(docs, text_col=text_col)
    chosen = ordered(text_statistics(sampled(docs, sample_rows), text_col=text_col), rules, sample_rows=sample_rows)
    return stats.select(
        "row", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        base_failed().alias("base_failed"), cascade(chosen).alias("kept"),
    )
