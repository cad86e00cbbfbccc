"""Pairing of papers with deposits, extraction requests, replayed records and
their scores.  No model is called here: extraction quality is an input, or
that of a keyword reader."""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .joins import grown

RECORD = "array<struct<outcome:string,family:string,role:string,column:string,use:string>>"


def normal_title(title: Column) -> Column:
    """Lower case, replication prefix off, runs of anything but letters and
    digits as one space."""
    t = F.lower(title)
    t = F.regexp_replace(t, r"^\s*(replication (data|files|materials|code) for)\s*:?\s*", "")
    return F.trim(F.regexp_replace(t, r"[^\p{L}\p{Nd}]+", " "))


def normal_doi(doi: Column) -> Column:
    return F.regexp_replace(F.lower(F.trim(doi)), r"^(https?://(dx\.)?doi\.org/|doi:)", "")


def by_doi(deposits: DataFrame, papers: DataFrame) -> DataFrame:
    a = deposits.where("doi IS NOT NULL").select("deposit_id", normal_doi(F.col("doi")).alias("k"))
    b = papers.where("doi IS NOT NULL").select("paper_id", normal_doi(F.col("doi")).alias("k"))
    return a.join(grown(b), "k").select("deposit_id", "paper_id", F.lit("doi").alias("method"))


def by_title(deposits: DataFrame, papers: DataFrame) -> DataFrame:
    """Pairs of which one normalised title lies inside the other at word bounds.
    Titles meet through the rarest word of the contained side only, which any
    container must hold, so there is no bare product."""
    a = deposits.select("deposit_id", normal_title(F.col("title")).alias("ta")).where("ta <> ''")
    b = papers.select("paper_id", normal_title(F.col("title")).alias("tb")).where("tb <> ''")
    words_a = a.select("deposit_id", "ta", F.explode(F.array_distinct(F.split("ta", " "))).alias("w"))
    words_b = b.select("paper_id", "tb", F.explode(F.array_distinct(F.split("tb", " "))).alias("w"))
    df = words_a.select("w").unionByName(words_b.select("w")).groupBy("w").agg(F.count("*").alias("df"))

    def rarest(words: DataFrame, key: str, t: str) -> DataFrame:
        ranked = words.join(grown(df), "w").groupBy(key, t).agg(F.min(F.struct("df", "w")).alias("m"))
        return ranked.select(key, t, F.col("m.w").alias("w"))

    bound = lambda t: F.concat(F.lit(" "), t, F.lit(" "))
    inside = rarest(words_a, "deposit_id", "ta").join(grown(words_b), "w").where(bound(F.col("tb")).contains(bound(F.col("ta"))))
    around = rarest(words_b, "paper_id", "tb").join(grown(words_a), "w").where(bound(F.col("ta")).contains(bound(F.col("tb"))))
    cols = ["deposit_id", "paper_id"]
    return inside.select(cols).unionByName(around.select(cols)).distinct().withColumn("method", F.lit("title"))


def resolve(deposits: DataFrame, *methods: DataFrame) -> DataFrame:
    """One pair for each deposit by the first method that has any (smallest
    paper), else unresolved."""
    ranked = None
    for i, m in enumerate(methods):
        part = m.withColumn("r", F.lit(i))
        ranked = part if ranked is None else ranked.unionByName(part)
    best = ranked.groupBy("deposit_id").agg(F.min(F.struct("r", "paper_id", "method")).alias("b"))
    return deposits.select("deposit_id").join(grown(best), "deposit_id", "left").select(
        "deposit_id", F.col("b.paper_id").alias("paper_id"), F.coalesce("b.method", F.lit("unresolved")).alias("method")
    )


VARIABLE = "array<struct<name:string,label:string,type:string,low:double,high:double,n_distinct:long,n_present:long>>"


def metadata_sheet(profiles: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """deposit_id, sheet, n_variables: of each variable its name, its label where
    a codebook has one (``labels``: name, label), type, range, distinct values
    (null beyond the exact limit) and present values.  No class and no data.
    One entry a name: the file with most rows speaks for it."""
    best = profiles.groupBy("deposit_id", "name").agg(
        F.min(F.struct((-F.col("n")).alias("o"), "file_id", "all_integer", "vmin", "vmax", "complete", "n_distinct", "nonnull")).alias("b")
    )
    if labels is None:
        best = best.withColumn("label", F.lit(None).cast("string"))
    else:
        best = best.join(labels.select("name", "label"), "name", "left")
    entry = F.struct(
        "name", "label", F.when(F.col("b.all_integer"), "integer").otherwise("double").alias("type"), F.col("b.vmin").alias("low"),
        F.col("b.vmax").alias("high"), F.when(F.col("b.complete"), F.col("b.n_distinct")).alias("n_distinct"), F.col("b.nonnull").alias("n_present"),
    )
    return best.groupBy("deposit_id").agg(F.array_sort(F.collect_list(entry)).alias("sheet"), F.count("*").alias("n_variables"))


def requests(pairs: DataFrame, papers: DataFrame, sheets: DataFrame, scripts: DataFrame | None = None) -> DataFrame:
    """One request for each paired paper; with scripts it is the code arm."""
    out = pairs.select("deposit_id", "paper_id").join(grown(papers.select("paper_id", "text")), "paper_id").join(grown(sheets), "deposit_id")
    arm = "text+metadata"
    if scripts is not None:
        code = scripts.groupBy("deposit_id").agg(F.array_join(F.array_sort(F.collect_list("text")), "\n").alias("code"))
        out, arm = out.join(grown(code), "deposit_id", "left"), "text+metadata+code"
    body = F.to_json(F.struct("deposit_id", *[c for c in ("text", "sheet", "code") if c in out.columns]))
    return out.select("deposit_id", "paper_id", F.lit(arm).alias("arm"), body.alias("request"), F.sha2(body, 256).alias("request_id"))


def extract(asked: DataFrame, extractor: Callable[[str], str], *, calls: int | None = None) -> DataFrame:
    """Apply an extractor once to each request: the seam where a model would
    stand.  A repeated task repeats its calls under the same request_id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [extractor(r) for r in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], names=["request_id", "response"])

    rows = asked.select("request_id", "request")
    return (rows.repartition(calls, "request_id") if calls else rows).mapInArrow(run, "request_id string, response string")


def extract_two_step(asked: DataFrame, distil: Callable[[str], str], settle: Callable[[str], str]) -> DataFrame:
    """Baseline of two calls: distil the paper, then settle what is left on the
    columns of the sheet."""
    first = extract(asked, distil)
    second = first.join(grown(asked.select("request_id", "request")), "request_id").select(
        "request_id",
        F.to_json(F.struct(F.col("response").alias("text"), F.from_json(F.get_json_object("request", "$.sheet"), VARIABLE).alias("sheet"))).alias("request"),
    )
    return extract(second, settle)


def replay(asked: DataFrame, responses: DataFrame) -> DataFrame:
    """Stored responses (request_id, extractor, response) in place of a model:
    request_id, extractor, response of every request that has one."""
    return asked.select("request_id").join(grown(responses), "request_id")


_COMMENT = re.compile(r"^\s*(#|\*|/\*|//)")


def distil_keywords(request: str) -> str:
    """First step of the two: the sentence that names an outcome or predictor,
    with what it says of least squares; other models are not carried over."""
    text = json.loads(request)["text"]
    said = [x for x in re.split(r"(?<=\.)\s+", text) if re.search(r"\b(outcome|predictor) is\b", x)]
    ols = " by ordinary least squares." if "ordinary least squares" in text else ""
    return " ".join(re.split(r",| by ", x)[0].rstrip(".") + "." for x in said) + ols


def extract_keywords(request: str) -> str:
    """A small extractor without a model: the column that stands after "outcome
    is" or "predictor is", and the family by words of the text, or failing that
    by the commands of the code."""
    body = json.loads(request)
    names = sorted((v["name"] for v in body["sheet"]), key=len, reverse=True)
    text, code = body["text"], body.get("code") or ""
    family = "not stated"
    if re.search(r"\b(Poisson|count model)\b", text):
        family = "count"
    elif re.search(r"\b(least squares|linear)\b", text):
        family = "linear"
    else:
        lines = [x for x in code.split("\n") if not _COMMENT.match(x)]
        if any(re.search(r"\b(poisson|nbreg)\b", x) for x in lines):
            family = "count"
        elif any(re.search(r"\b(regress|reg)\b|\b[a-z]?lm(_robust)?\(", x) for x in lines):
            family = "linear"
    out = []
    for use, said in re.findall(r"\b(outcome|predictor) is ([^,.]*)", text):
        column = next((n for n in names if re.search(rf"\b{re.escape(n)}\b", said)), "not in the metadata")
        out.append({"outcome": said, "family": family, "role": "headline", "column": column, "use": use})
    return json.dumps(out)


def from_code(links: DataFrame) -> DataFrame:
    """Records of the code layer: what deposited commands say, as a comparator."""
    return links.select(
        "deposit_id", F.lit("comparators").alias("arm"), F.lit("code layer").alias("extractor"), F.col("deposit_id").alias("case_id"),
        F.col("response").alias("outcome"), "family", F.lit(None).cast("string").alias("role"), "column", F.lit("outcome").alias("use"),
        F.lit("read").alias("status"),
    )


def parse(records: DataFrame) -> DataFrame:
    """Rows of each response; a malformed one has status ``malformed``."""
    a = F.from_json("response", RECORD, {"mode": "PERMISSIVE"})
    out = records.withColumn("a", a)
    bad = F.col("a").isNull() | (F.size("a") == 0)
    return out.withColumn("status", F.when(bad, "malformed").otherwise("read")).select(
        *[c for c in records.columns if c != "response"], "status", F.inline_outer("a")
    )


def guard(rows: DataFrame, sheets: DataFrame) -> DataFrame:
    """Reject picks of columns that the sheet does not have, and picks whose
    type and range contradict the stated family: a count is integer and not
    negative, a share lies in the unit interval, a binary has two values."""
    known = sheets.select("deposit_id", F.inline("sheet")).select("deposit_id", F.col("name").alias("column"), "type", "low", "high", "n_distinct")
    out = rows.join(grown(known), ["deposit_id", "column"], "left")
    fits = (
        F.when(F.col("family") == "count", (F.col("type") == "integer") & (F.col("low") >= 0))
        .when(F.col("family") == "proportion", (F.col("low") >= 0) & (F.col("high") <= 1))
        .when(F.col("family") == "binary", F.col("n_distinct") <= 2).otherwise(True)
    )
    return out.withColumn(
        "status",
        F.when(F.col("status") != "read", F.col("status"))
        .when(F.col("column") == "not in the metadata", "not_in_metadata")
        .when(F.col("type").isNull(), "unknown_column")
        .when(~F.coalesce(fits, F.lit(False)), "inconsistent").otherwise("accepted"),
    ).drop("type", "low", "high", "n_distinct")


def score(rows: DataFrame, cases: DataFrame, twins: DataFrame) -> DataFrame:
    """Per (arm, extractor, case): exact link, derived link (an accepted twin),
    any link, the family by itself, link and family, and the kind of miss.

    Picks as a predictor do not count.  The kinds, the first that holds: a link
    whose family was not stated or contradicts the case; an accepted pick of
    another column; one as a predictor only; else what the guard said.
    """
    pick = rows.join(grown(cases.select("case_id", F.col("column").alias("want"), F.col("family").alias("want_family"))), "case_id")
    pick = pick.join(grown(twins.select("case_id", F.col("column").alias("twin"))), "case_id", "left")
    used = (F.col("status") == "accepted") & (F.col("use") == "outcome")
    exact = used & (F.col("column") == F.col("want"))
    derived = used & (F.col("column") == F.col("twin")) & (F.col("column") != F.col("want"))
    family = (F.col("use") == "outcome") & (F.col("family") == F.col("want_family"))
    yes = lambda c: F.coalesce(F.bool_or(c), F.lit(False))
    link, both = yes(exact | derived), yes(family & (exact | derived))
    stated = yes((exact | derived) & (F.col("family") != "not stated"))
    kind = (
        F.when(both, F.lit(None).cast("string")).when(link & stated, "contradicted").when(link, "not_stated").when(yes(used), "wrong_column")
        .when(yes((F.col("status") == "accepted") & (F.col("use") == "predictor")), "predictor_only").otherwise(F.min("status"))
    )
    return pick.groupBy("arm", "extractor", "case_id").agg(
        yes(exact).alias("exact"), (yes(derived) & ~yes(exact)).alias("derived"), link.alias("link"),
        yes(family).alias("family"), both.alias("link_family"), kind.alias("miss"),
    )


def grid(scores: DataFrame) -> DataFrame:
    n = lambda c: F.count_if(F.col(c)).alias(f"n_{c}")
    return scores.groupBy("arm", "extractor").agg(
        F.count("*").alias("n_cases"), *[n(c) for c in ("exact", "derived", "link", "family", "link_family")]
    )


def compare(scores: DataFrame, first: str, second: str) -> DataFrame:
    """Rows gained, lost and kept between two arms, and those of which the link
    turned from exact to derived or back."""
    side = lambda arm, t: scores.where(F.col("arm") == arm).select(
        "extractor", "case_id", F.col("link_family").alias(f"full{t}"), F.col("exact").alias(f"exact{t}"), F.col("derived").alias(f"derived{t}")
    )
    flags = [f"{c}{t}" for c in ("full", "exact", "derived") for t in "ab"]
    both = side(first, "a").join(side(second, "b"), ["extractor", "case_id"], "full_outer").na.fill(False, flags)
    turned = (F.col("exacta") & F.col("derivedb")) | (F.col("deriveda") & F.col("exactb"))
    return both.groupBy("extractor").agg(
        F.count_if(F.col("fullb") & ~F.col("fulla")).alias("gained"), F.count_if(F.col("fulla") & ~F.col("fullb")).alias("lost"),
        F.count_if(F.col("fulla") & F.col("fullb")).alias("kept"), F.count_if(turned).alias("changed"),
    )


def miss_kinds(scores: DataFrame) -> DataFrame:
    return scores.where("NOT link_family").groupBy("arm", "extractor", F.col("miss").alias("kind")).agg(F.count("*").alias("n"))
