"""Records of the analyses that a table of documents reports: each document is
one deposit with a file of four variables and one analysis, of the kind of one
of the fixture's four by the length of its text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import fixture
from .store import stored
from .tables import table

#: Columns that name a record; they carry the document's id as well.
IDS = {"analysis_id", "assertion_id", "variable_id", "profile_id", "alert_id", "use_id", "decision_id", "target_id", "evidence_id", "file_key", "supersedes"}
#: Records that every document has; the others go with the analysis of one kind.
EVERY = ("file", "variable", "profile")
_KIND = {r[0]: i for i, r in enumerate(fixture.ANALYSIS[1])}
_OF = {r[0]: _KIND[r[1]] for s in (fixture.ROLE, fixture.USE, fixture.ESTIMATOR, fixture.ALERT) for r in s[1]}


def _template(name: str) -> list[tuple]:
    """(kind of analysis, the record's fields...)."""
    rows = fixture.ALL[name][1]
    if name in EVERY:
        return [(k, *r) for k in _KIND.values() for r in rows]
    if name == "review":
        return [(0, *r) for r in rows]
    if name == "analysis":
        return [(_KIND[r[0]], *r) for r in rows]
    return [(_OF[r[1] if name == "evidence" else r[0]], *r) for r in rows]


def _fields(name: str) -> list[str]:
    return [c.split()[0] for c in fixture.ALL[name][0].split(", ")]


def _literals(name: str) -> str:
    lit = lambda v: "NULL" if v is None else str(v) if isinstance(v, int) else f"'{v}'"
    return ", ".join("(" + ", ".join(map(lit, r)) + ")" for r in _template(name))


def frames(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    # Each query reads the documents, once for all its records.
    kind = F.coalesce(F.length("text"), F.lit(0)) % len(_KIND)
    documents = stored(table(spark, sf_dir, "documents").select("doc_id", "lang", F.md5("text").alias("checksum"), kind.alias("kind")), "reported")
    doc = F.col("doc_id").cast("string")

    def field(c: str) -> F.Column:
        if c in IDS:
            return F.concat(c, F.lit("-"), doc)
        return {"dataset_version": F.concat(F.lit("d"), doc, F.lit("@1")), "file_checksum": F.col("checksum"), "response": F.concat_ws("_", "response", "lang")}.get(c, F.col(c))

    out = {}
    for name, (schema, _) in fixture.ALL.items():
        typed = ", ".join("CAST(`{0}` AS {1}) AS `{0}`".format(*c.split()) for c in f"kind int, {schema}".split(", "))
        names = ", ".join(f"`{c}`" for c in ("kind", *_fields(name)))
        rows = F.broadcast(spark.sql(f"SELECT {typed} FROM VALUES {_literals(name)} AS t({names})"))
        out[name] = documents.join(rows, "kind").select(*[field(c).alias(c) for c in _fields(name)])
    return out


KIND_SQL = f"coalesce(length(text), 0) % {len(_KIND)}"


def values(name: str) -> str:
    """The same rows as a DuckDB subquery."""
    special = {"dataset_version": "'d' || doc_id || '@1'", "file_checksum": "md5(text)", "response": "concat_ws('_', response, lang)"}
    cols = ", ".join((f"t.\"{c}\" || '-' || doc_id" if c in IDS else special.get(c, f't."{c}"')) + f' AS "{c}"' for c in _fields(name))
    names = ", ".join(f'"{c}"' for c in ("kind", *_fields(name)))
    return f"(SELECT {cols} FROM documents JOIN (VALUES {_literals(name)}) t({names}) ON kind = {KIND_SQL})"
