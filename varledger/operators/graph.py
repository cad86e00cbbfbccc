"""The assertion graph as triples: export, text, reading back, shapes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .joins import grown

TRIPLE = "s string, p string, o string, o_kind string"
#: Per record: key column, and the columns that name another node (with its kind).
NODES = {
    "file": ("file_key", {}),
    "variable": ("variable_id", {"file_key": "file"}),
    "analysis": ("analysis_id", {}),
    "role": ("assertion_id", {"analysis_id": "analysis", "supersedes": "role"}),
    "use": ("assertion_id", {"analysis_id": "analysis", "variable_id": "variable", "supersedes": "use"}),
    "estimator": ("assertion_id", {"analysis_id": "analysis", "supersedes": "estimator"}),
    "profile": ("profile_id", {"variable_id": "variable"}),
    "alert": ("alert_id", {"analysis_id": "analysis", "use_id": "use", "profile_id": "profile"}),
    "review": ("decision_id", {"supersedes": "review"}),
    "evidence": ("evidence_id", {}),
    "generation": ("assertion_id", {}),
}
#: Records in the terms of the interchange model; the others are the profile's.
CORE = ("file", "variable")


def _node(kind: str, key: Column) -> Column:
    return F.concat(F.lit(f"{kind}/"), key)


CELL = "array<struct<p:string,o:string,o_kind:string>>"


def _cells(kind: str, kinds: dict[str, str], refs: dict[str, str]) -> Callable[[Column], Column]:
    def cells(row: Column) -> Column:
        own = [
            F.struct(F.lit(c).alias("p"), (_node(refs[c], row[c]) if c in refs else row[c].cast("string")).alias("o"), F.lit(k).alias("o_kind"))
            for c, k in kinds.items()
        ]
        return F.array(F.struct(F.lit("type").alias("p"), F.lit(f"class/{kind}").alias("o"), F.lit("node").alias("o_kind")), *own)

    return cells


def nodes(g: dict[str, DataFrame]) -> DataFrame:
    """s, cells: each node with its triples' p, o and o_kind, as a set; a null
    field has none.  Records meet by their key, so rows travel instead of
    triples, and a node has one type."""
    out = None
    for kind, df in g.items():
        key, refs = NODES[kind]
        kinds = {}
        for c in df.columns:
            if c != key or kind == "generation":
                kinds[c] = "node" if c in refs else "integer" if df.schema[c].dataType.typeName() in ("integer", "long") else "text"

        grouped = df.groupBy(key).agg(F.collect_set(F.struct(*[F.col(c) for c in df.columns])).alias("rows"))
        every = F.array_distinct(F.flatten(F.transform("rows", _cells(kind, kinds, refs))))
        part = grouped.select(_node(kind, F.col(key)).alias("s"), F.filter(every, lambda x: x["o"].isNotNull()).cast(CELL).alias("cells"))
        out = part if out is None else out.unionByName(part)
    return out


def to_triples(g: dict[str, DataFrame]) -> DataFrame:
    """All records as a set of triples."""
    return nodes(g).select("s", F.inline("cells"))


def core_part(triples: DataFrame, *, core: bool = True) -> DataFrame:
    """The triples about nodes of the interchange model, or the others."""
    inside = F.split("s", "/")[0].isin(*CORE)
    return triples.where(inside if core else ~inside)


def _swapped(c: Column, pairs: list[tuple[str, str]]) -> Column:
    for a, b in pairs:
        c = F.replace(c, F.lit(a), F.lit(b))
    return c


#: In this order; undone in the opposite one.  A pair of backslashes is held by
#: a control character meanwhile, which is itself written as an escape.
_ESCAPES = [("\"", '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t"), ("\x01", "\\1")]
_NODE_ESCAPES = [("%", "%25"), ("<", "%3C"), (">", "%3E"), ("\n", "%0A"), ("\r", "%0D")]


def _escaped(c: Column) -> Column:
    return _swapped(c, [("\\", "\\\\"), *_ESCAPES])


def _unescaped(c: Column) -> Column:
    held = F.replace(c, F.lit("\\\\"), F.lit("\x02"))
    return F.replace(_swapped(held, [(b, a) for a, b in reversed(_ESCAPES)]), F.lit("\x02"), F.lit("\\"))


def _as_node(c: Column) -> Column:
    return _swapped(c, _NODE_ESCAPES)


def _from_node(c: Column) -> Column:
    return _swapped(c, [(b, a) for a, b in reversed(_NODE_ESCAPES)])


def _line() -> Column:
    o = F.when(F.col("o_kind") == "node", F.concat(F.lit("<"), _as_node(F.col("o")), F.lit(">"))).otherwise(
        F.concat(F.lit('"'), _escaped(F.col("o")), F.lit('"^^<'), F.col("o_kind"), F.lit(">"))
    )
    return F.concat(F.lit("<"), _as_node(F.col("s")), F.lit("> <"), _as_node(F.col("p")), F.lit("> "), o, F.lit(" ."))


def to_turtle(triples: DataFrame) -> DataFrame:
    """One line a triple: <s> <p> <o> . or a quoted, typed value."""
    return triples.select(_line().alias("value"))


def _of_line() -> Column:
    """The triple of a line, null where it is none."""
    node = r"^<([^>]*)> <([^>]*)> <([^>]*)> \.$"
    text = r'^<([^>]*)> <([^>]*)> "(.*)"\^\^<([^>]*)> \.$'
    is_node = F.col("value").rlike(node)

    def part(i: int) -> Column:
        return F.when(is_node, F.regexp_extract("value", node, i)).otherwise(F.regexp_extract("value", text, i))

    return F.when(is_node | F.col("value").rlike(text), F.struct(
        _from_node(part(1)).alias("s"), _from_node(part(2)).alias("p"),
        F.when(is_node, _from_node(part(3))).otherwise(_unescaped(part(3))).alias("o"),
        F.when(is_node, "node").otherwise(F.regexp_extract("value", text, 4)).alias("o_kind"),
    ))


def from_turtle(lines: DataFrame) -> DataFrame:
    """Triples of the text form; a line that is none is left out."""
    return lines.select(_of_line().alias("t")).where("t IS NOT NULL").select("t.*")


_VALUE = "struct<`@id`:string,`@value`:string,`@type`:string>"
CONTEXT = '{"@vocab":"urn:varledger:terms/","@base":"urn:varledger:"}'


def _document() -> Column:
    """The document of a node with its cells."""

    def value(c: Column) -> Column:
        is_node = c["o_kind"] == "node"
        return F.struct(F.when(is_node, c["o"]).alias("@id"), F.when(~is_node, c["o"]).alias("@value"), F.when(~is_node, c["o_kind"]).alias("@type"))

    def entry(p: Column) -> Column:
        return F.struct(p.alias("p"), F.array_sort(F.transform(F.filter("cells", lambda c: c["p"] == p), value)).alias("v"))

    names = F.array_sort(F.array_distinct(F.transform("cells", lambda c: c["p"])))
    inner = lambda x: F.substring(x, F.lit(2), F.length(x) - 2)
    head, body = F.to_json(F.struct(F.col("s").alias("@id"))), F.to_json(F.map_from_entries(F.transform(names, entry)))
    return F.concat(F.lit(f'{{"@context":{CONTEXT},'), inner(head), F.lit(","), inner(body), F.lit("}"))


def to_jsonld(triples: DataFrame) -> DataFrame:
    """One JSON-LD document a node: context, id, and an array of nodes or typed
    values for each predicate."""
    return triples.groupBy("s").agg(F.collect_list(F.struct("p", "o", "o_kind")).alias("cells")).select(_document().alias("value"))


def _parsed() -> Column:
    return F.from_json("value", "map<string,string>").alias("m")


def _of_document() -> Column:
    """Triples of a parsed document, as an array."""
    m = F.col("m")

    def triple(p: Column) -> Callable[[Column], Column]:
        def one(v: Column) -> Column:
            node = v["@id"].isNotNull()
            return F.struct(
                m["@id"].alias("s"), p.alias("p"), F.when(node, v["@id"]).otherwise(v["@value"]).alias("o"),
                F.when(node, F.lit("node")).otherwise(v["@type"]).alias("o_kind"),
            )

        return one

    fields = F.filter(F.map_entries(m), lambda e: ~e["key"].startswith("@"))
    none = F.array().cast(f"array<{_VALUE}>")
    return F.flatten(F.transform(fields, lambda e: F.transform(F.coalesce(F.from_json(e["value"], f"array<{_VALUE}>"), none), triple(e["key"]))))


def from_jsonld(documents: DataFrame) -> DataFrame:
    """Triples of such documents."""
    return documents.select(_parsed()).select(F.inline(_of_document()))


_T = ("s", "p", "o", "o_kind")


def _signed(t: Column, n: int) -> Column:
    return F.struct(*[t[c].alias(c) for c in _T], F.lit(n).alias("n"))


def _exploded(changes: Column, both: DataFrame) -> DataFrame:
    """Rows of an array, null where nothing changed.  A filter on the columns
    it is made of would be pushed below them and make them twice."""
    return both.select(F.inline_outer(changes)).where("n IS NOT NULL")


def changed_by_text(nodes: DataFrame) -> DataFrame:
    """s, p, o, o_kind, n of each triple that its line does not give back: 1
    for it and -1 for what was read instead."""
    lines = nodes.select("s", F.inline_outer("cells")).select(F.struct(*_T).alias("first"), _line().alias("value"))
    both = lines.select("first", _of_line().alias("second"))
    first, second = F.col("first"), F.col("second")
    own = F.array(_signed(first, 1))
    return _exploded(F.when(second.isNull(), own).when(first != second, F.concat(own, F.array(_signed(second, -1)))), both)


def changed_by_jsonld(nodes: DataFrame) -> DataFrame:
    """The same of each node whose document gives other triples back."""
    made = nodes.select(F.transform("cells", lambda c: F.struct(F.col("s").alias("s"), *[c[x].alias(x) for x in _T[1:]])).alias("first"), _document().alias("value"))
    none = F.array().cast("array<struct<s:string,p:string,o:string,o_kind:string>>")
    both = made.select("first", _parsed()).select(F.array_sort("first").alias("first"), F.array_sort(F.coalesce(_of_document(), none)).alias("second"))
    signed = F.concat(F.transform("first", lambda t: _signed(t, 1)), F.transform("second", lambda t: _signed(t, -1)))
    return _exploded(F.when(F.col("first") != F.col("second"), signed), both)


def n_different(changes: DataFrame) -> DataFrame:
    """Triples that only one side has, as :func:`difference` counts them: what
    a line or node gives back unchanged is on both sides as often, so the rest
    alone is exchanged."""
    net = changes.groupBy(*_T).agg(F.sum("n").alias("n"))
    return net.agg(F.coalesce(F.sum(F.abs("n")), F.lit(0)).cast("long").alias("n_different"))


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Triples that only one side has."""
    return a.exceptAll(b).withColumn("side", F.lit("first")).unionByName(b.exceptAll(a).withColumn("side", F.lit("second")))


#: (class, predicate, min, max, kind of object): closed shapes of the records.
SHAPES = [
    ("analysis", "dataset_version", 1, 1, "text"), ("analysis", "paper_loc", 0, 1, "text"), ("analysis", "code_loc", 0, 1, "text"), ("analysis", "command", 1, 1, "text"),
    ("role", "analysis_id", 1, 1, "node"), ("role", "role", 1, 1, "text"), ("role", "at", 1, 1, "integer"), ("role", "supersedes", 0, 1, "node"),
    ("use", "analysis_id", 1, 1, "node"), ("use", "variable_id", 1, 1, "node"), ("use", "response", 1, 1, "text"), ("use", "use", 1, 1, "text"),
    ("use", "link_kind", 1, 1, "text"), ("use", "at", 1, 1, "integer"), ("use", "supersedes", 0, 1, "node"),
    ("estimator", "analysis_id", 1, 1, "node"), ("estimator", "family", 1, 1, "text"), ("estimator", "at", 1, 1, "integer"), ("estimator", "supersedes", 0, 1, "node"),
    ("profile", "variable_id", 1, 1, "node"), ("profile", "class", 1, 1, "text"), ("profile", "rule_version", 1, 1, "text"), ("profile", "scope", 0, 1, "text"),
    ("profile", "n", 0, 1, "integer"),
    ("alert", "analysis_id", 1, 1, "node"), ("alert", "use_id", 1, 1, "node"), ("alert", "profile_id", 1, 1, "node"), ("alert", "tier", 1, 1, "text"),
    ("review", "target_id", 1, 1, "text"), ("review", "reviewer", 1, 1, "text"), ("review", "state", 1, 1, "text"), ("review", "at", 1, 1, "integer"),
    ("review", "supersedes", 0, 1, "node"),
    ("evidence", "assertion_id", 1, 1, "text"), ("evidence", "source", 1, 1, "text"), ("evidence", "locator", 1, 1, "text"),
    ("generation", "assertion_id", 1, 1, "text"), ("generation", "method", 1, 1, "text"), ("generation", "tool", 1, 1, "text"),
    ("generation", "at", 0, 1, "integer"), ("generation", "time_uncertainty", 0, 1, "text"),
]
#: Shapes of the interchange model's nodes, validated apart.
CORE_SHAPES = [
    ("file", "dataset_version", 1, 1, "text"), ("file", "file_checksum", 1, 1, "text"),
    ("variable", "file_key", 1, 1, "node"), ("variable", "name", 1, 1, "text"), ("variable", "position", 1, 1, "integer"), ("variable", "datatype", 1, 1, "text"),
]


def shapes(spark: SparkSession, rows=SHAPES) -> DataFrame:
    return spark.createDataFrame(rows, "class string, p string, low int, high int, want string")


def core_violations(triples: DataFrame) -> DataFrame:
    """The interchange model's nodes against their own shapes, by themselves."""
    return _cardinalities(core_part(triples), shapes(triples.sparkSession, CORE_SHAPES)).distinct()


def _kind(df: DataFrame, name: str) -> DataFrame:
    return df.select("s", "p", F.lit(name).alias("kind"))


def _typed(triples: DataFrame) -> DataFrame:
    return triples.where("p = 'type'").select("s", F.regexp_replace("o", "^class/", "").alias("class"))


def _cardinalities(triples: DataFrame, rules: DataFrame) -> DataFrame:
    """Cardinality, closedness and object kinds of the classes with rules."""
    ruled = _typed(triples).join(F.broadcast(rules.select("class").distinct()), "class", "left_semi")
    facts = triples.where("p <> 'type'").join(ruled, "s")
    counts = facts.groupBy("s", "p").agg(F.count("*").alias("n"))
    wanted = ruled.join(F.broadcast(rules), "class").join(counts, ["s", "p"], "left").na.fill(0, ["n"])
    out = _kind(wanted.where("n < low OR n > high"), "cardinality")
    out = out.unionByName(_kind(facts.join(F.broadcast(rules), ["class", "p"], "left_anti"), "closed"))
    return out.unionByName(_kind(facts.join(F.broadcast(rules), ["class", "p"]).where("o_kind <> want"), "node_kind"))


def violations(triples: DataFrame, rules: DataFrame) -> DataFrame:
    """Cardinality, closedness, object kinds, evidence, time or its declared
    uncertainty, and agreement of an alert's profile with the variable of its
    use."""
    typed = _typed(triples)
    out = _cardinalities(triples, rules)
    # Nodes that are named but have no record, or one of another class.
    named = triples.where("o_kind = 'node' AND p <> 'type'").select("s", "p", F.col("o").alias("t"))
    out = out.unionByName(_kind(named.join(typed.select(F.col("s").alias("t")), "t", "left_anti"), "dangling"))
    value = lambda p, name: triples.where(F.col("p") == p).select("s", F.col("o").alias(name))
    shown = value("assertion_id", "key").join(typed.where("class = 'evidence'"), "s").select("key")
    asserted = typed.where("class IN ('role', 'use', 'estimator')").withColumn("key", F.regexp_replace("s", "^[a-z]+/", ""))
    out = out.unionByName(_kind(asserted.join(shown, "key", "left_anti").withColumn("p", F.lit("evidence")), "no_evidence"))
    timed = triples.where("p IN ('at', 'time_uncertainty')").select("s")
    out = out.unionByName(_kind(typed.where("class = 'generation'").join(timed, "s", "left_anti").withColumn("p", F.lit("at")), "no_time"))
    alert = typed.where("class = 'alert'").join(value("use_id", "u"), "s").join(value("profile_id", "pr"), "s")
    of_use = value("variable_id", "vu").withColumnRenamed("s", "u")
    of_profile = value("variable_id", "vp").withColumnRenamed("s", "pr")
    odd = alert.join(of_use, "u").join(of_profile, "pr").where("vu <> vp").withColumn("p", F.lit("profile_id"))
    return out.unionByName(_kind(odd, "other_variable")).distinct()


_HEX = r"[0-9a-f]{64}\z"


def _packed(c: Column) -> Column:
    """A text as bytes, equal where the texts are: a digest at its end takes
    half the room, and the first byte says whether there is one."""
    head = F.encode(F.concat(F.lit("h"), F.substring(c, F.lit(1), F.length(c) - 64)), "UTF-8")
    return F.when(c.rlike(_HEX), F.concat(head, F.unhex(F.right(c, F.lit(64))))).otherwise(F.encode(F.concat(F.lit("t"), c), "UTF-8"))


def _unpacked(c: Column) -> Column:
    n = F.length(c)
    digest = F.concat(F.decode(F.substring(c, F.lit(2), n - 33), "UTF-8"), F.lower(F.hex(F.substring(c, n - 31, F.lit(32)))))
    return F.when(F.substring(c, F.lit(1), F.lit(1)) == F.lit(b"h"), digest).otherwise(F.decode(F.substring(c, F.lit(2), n), "UTF-8"))


def _of_nodes(nodes: DataFrame, rules: DataFrame) -> DataFrame:
    """s, p, kind of what a node breaks by its own triples: cardinality,
    closedness and kinds of objects, for classes with rules."""
    shape = rules.groupBy("class").agg(F.collect_list(F.struct("p", "low", "high", "want")).alias("shape"))
    typed = F.filter("cells", lambda c: c["p"] == "type")[0]["o"]
    ruled = nodes.select("s", F.regexp_replace(typed, "^class/", "").alias("class"), F.filter("cells", lambda c: c["p"] != "type").alias("facts")).join(F.broadcast(shape), "class")
    kind = lambda name: lambda x: F.struct(x["p"].alias("p"), F.lit(name).alias("kind"))
    n = lambda r: F.size(F.filter("facts", lambda c: c["p"] == r["p"]))
    wrong = [
        F.transform(F.filter("shape", lambda r: (n(r) < r["low"]) | (n(r) > r["high"])), kind("cardinality")),
        F.transform(F.filter("facts", lambda c: ~F.exists("shape", lambda r: r["p"] == c["p"])), kind("closed")),
        F.transform(F.filter("facts", lambda c: F.exists("shape", lambda r: (r["p"] == c["p"]) & (r["want"] != c["o_kind"]))), kind("node_kind")),
    ]
    return ruled.select("s", F.inline(F.array_distinct(F.concat(*wrong))))


def core_record_violations(g: dict[str, DataFrame]) -> DataFrame:
    """:func:`core_violations` of the export of records, from their nodes."""
    core = nodes({kind: g[kind] for kind in CORE})
    return _of_nodes(core, shapes(core.sparkSession, CORE_SHAPES))


def record_violations(g: dict[str, DataFrame], rules: DataFrame) -> DataFrame:
    """:func:`violations` of the export of records, without its triples: what a
    node breaks by itself is found in place, and only the keys of references,
    assertions and alerts are exchanged, as bytes.  A reference names its
    target's class, so only nodes of such classes can be meant."""
    part = lambda *kinds: nodes({k: g[k] for k in g if k in kinds})
    out = _of_nodes(nodes(g), rules)

    def values(df: DataFrame, p: str, name: str) -> DataFrame:
        own = F.explode_outer(F.filter("cells", lambda c: c["p"] == p))
        return df.select(_packed(F.col("s")).alias("s"), own.alias("c")).where("c IS NOT NULL").select("s", _packed(F.col("c.o")).alias(name))

    def unpacked(df: DataFrame, p: Column, kind: str) -> DataFrame:
        return df.select(_unpacked(F.col("s")).alias("s"), p.alias("p"), F.lit(kind).alias("kind"))

    targets = {t for kind in g for t in NODES[kind][1].values()}
    named = part(*[kind for kind in g if NODES[kind][1]]).select(
        _packed(F.col("s")).alias("s"), F.explode_outer(F.filter("cells", lambda c: (c["o_kind"] == "node") & (c["p"] != "type"))).alias("c")
    ).where("c IS NOT NULL").select("s", "c.p", _packed(F.col("c.o")).alias("t"))
    held = part(*targets).select(_packed(F.col("s")).alias("t"))
    out = out.unionByName(unpacked(named.join(grown(held), "t", "left_anti"), F.col("p"), "dangling"))
    asserted = part("role", "use", "estimator").select(_packed(F.col("s")).alias("s"), _packed(F.regexp_replace("s", "^[a-z]+/", "")).alias("key"))
    shown = values(part("evidence"), "assertion_id", "key").select("key")
    out = out.unionByName(unpacked(asserted.join(grown(shown), "key", "left_anti"), F.lit("evidence"), "no_evidence"))
    untimed = part("generation").where(~F.exists("cells", lambda c: c["p"].isin("at", "time_uncertainty")))
    out = out.unionByName(untimed.select("s", F.lit("at").alias("p"), F.lit("no_time").alias("kind")))
    alert = part("alert").select(
        _packed(F.col("s")).alias("s"), F.explode(F.filter("cells", lambda c: c["p"] == "use_id")).alias("u"), F.filter("cells", lambda c: c["p"] == "profile_id").alias("prs")
    ).select("s", _packed(F.col("u.o")).alias("u"), F.explode("prs").alias("pr")).select("s", "u", _packed(F.col("pr.o")).alias("pr"))
    of_use = values(part("use"), "variable_id", "vu").withColumnRenamed("s", "u")
    of_profile = values(part("profile"), "variable_id", "vp").withColumnRenamed("s", "pr")
    odd = alert.join(grown(of_use), "u").join(grown(of_profile), "pr").where("vu <> vp")
    return out.unionByName(unpacked(odd, F.lit("profile_id"), "other_variable")).distinct()


def mutations(g: dict[str, DataFrame]) -> dict[str, dict[str, DataFrame]]:
    """Record sets that are each wrong, or different, in one way: in the record
    that the fixture names so, or in each document's (its name, a dash and the
    document's id)."""
    review = g["review"]
    name = lambda c: F.split_part(F.col(c), F.lit("-"), F.lit(1))
    other = lambda c, to: F.regexp_replace(F.col(c), "^[a-z]+[0-9]+", to)

    def more(reviewer: str, state: str, supersedes: Column) -> DataFrame:
        again = {"decision_id": other("decision_id", "d9"), "reviewer": F.lit(reviewer), "state": F.lit(state), "at": F.lit(5), "supersedes": supersedes}
        return review.unionByName(review.where(name("decision_id") == "d5").select(*[again.get(c, F.col(c)).alias(c) for c in review.columns]))

    return {
        "none": g,
        "no_evidence": g | {"evidence": g["evidence"].where(name("assertion_id") != "u1")},
        "other_profile": g | {"alert": g["alert"].withColumn("profile_id", F.when(name("alert_id") == "al1", other("profile_id", "p2")).otherwise(F.col("profile_id")))},
        "role_on_column": g | {"role": g["role"].withColumn("analysis_id", F.when(name("assertion_id") == "r4", other("analysis_id", "v3")).otherwise(F.col("analysis_id")))},
        "conflicting_review": g | {"review": more("second", "rejected", F.lit(None).cast("string"))},
        "superseded_review": g | {"review": more("first", "unresolved", F.col("decision_id"))},
        "no_alerts": g | {"alert": g["alert"].where("false")},
    }
