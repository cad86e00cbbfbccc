"""Top-k search, WARC archives, contract queries and the pipeline."""

import hashlib
import math

import pytest
from pyspark.sql import functions as F

from varledger.llm import warc
from varledger.llm.topk import top_k

SMALL = "/root/testdata/sf0.001"


def brute_top(rows, k, every):
    ok = [(i, [math.floor(256 * float(x)) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    out = []
    for q, a in ok:
        if q % every == 0:
            best = sorted([(-sum(x * y for x, y in zip(a, b, strict=True)), i) for i, b in ok if i != q])[:k]
            out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(best)]
    return sorted(out)


def test_top_k_with_ties_nulls_and_few(spark):
    rows = [(i, [((i * 37 + j * 11) % 17 - 8) / 8.0 for j in range(6)]) for i in range(120)]
    rows += [(200, rows[3][1]), (201, rows[3][1]), (202, None), (None, rows[0][1]), (203, [1.0, None] * 3), (204, [float("nan")] * 6), (205, [float("inf")] * 6)]
    df = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<float>, score int").repartition(4)
    for block in (16_384, 3):
        got = top_k(df, df.where("vec_id % 10 = 0"), k=5, block=block).collect()
        assert sorted(map(tuple, got)) == brute_top(rows, 5, 10)
    few = df.where("vec_id IN (0, 1, 2)")
    assert sorted(map(tuple, top_k(few, few.where("vec_id % 10 = 0")).collect())) == brute_top(rows[:3], 5, 10)
    assert top_k(df.where("false"), df.where("false")).count() == 0


def test_top_k_of_clusters_drops_pairs_early(spark, monkeypatch):
    """Rows in a few tight clusters, with repeated ids and ties; tiles so small
    that most rows leave after the first slices."""
    import random

    from varledger.llm import topk

    rng = random.Random(4)
    centres = [[rng.uniform(-2, 2) for _ in range(16)] for _ in range(6)]
    rows = [(i, [x + rng.uniform(-0.05, 0.05) for x in centres[i % 6]]) for i in range(400)]
    rows += [(1000 + i, rows[7][1]) for i in range(9)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    for sparse in (0.0, 0.05, 1.1):
        monkeypatch.setattr(topk, "SPARSE", sparse)
        assert sorted(map(tuple, top_k(df, df.where("vec_id % 20 = 0"), slices=8).collect())) == brute_top(rows, 5, 20)


def test_survivors_equal_whole_scores():
    import numpy as np

    from varledger.llm import topk

    rng = np.random.default_rng(3)
    cuts = topk._slices(24, 4)
    for _ in range(50):
        block, vectors = rng.integers(-50, 50, (7, 24)).astype(float), rng.integers(-50, 50, (40, 24)).astype(float)
        parts = np.stack([block[:, a:b] @ vectors[:, a:b].T for a, b in cuts], axis=2)
        whole = parts.sum(2)
        cutoff = np.sort(whole, axis=1)[:, -4]
        low, high = parts.min(1), parts.max(1)
        share = ((cutoff - low.sum(1)) / 4)[:, None] + low
        q, r, score = topk._survivors(block, vectors, cuts, [2, 0, 3, 1], cutoff, share, high)
        assert sorted(zip(q.tolist(), r.tolist(), score.tolist(), strict=True)) == sorted(
            (i, j, whole[i, j]) for i, j in np.argwhere(whole >= cutoff[:, None]).tolist()
        )


def test_top_k_of_every_length_equals_sql(spark):
    """Queries of three lengths; the commonest length of a query is none."""
    import duckdb

    from varledger.llm.oracles import TOP_K

    lengths = {0: 6, 50: 3, 100: 4, 150: 4}
    rows = [(i, [((i * 37 + j * 11) % 17 - 8) / 8.0 for j in range(lengths.get(i, 2 + i % 6))]) for i in range(180)]
    con = duckdb.connect()
    con.execute("CREATE TABLE embeddings (vec_id BIGINT, embedding FLOAT[])")
    con.executemany("INSERT INTO embeddings VALUES (?, ?)", rows)
    want = sorted(con.execute(TOP_K).fetchall())
    assert len(want) == 20
    rows += [(i, []) for i in range(1000, 1500, 50)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(4)
    assert sorted(map(tuple, top_k(df, df.where("vec_id % 50 = 0")).collect())) == want


def brute_pages(rows):
    raw = [(p, (h or "").encode()) for p, h in rows]
    top = {}
    for p, b in raw:
        if p is not None:
            top[b] = max(p, top.get(b, p))
    out = []
    for p, b in raw:
        again = len(b) >= 1000 and b in top and top[b] != p
        out.append((p, len(b), hashlib.sha1(b).hexdigest(), "revisit" if again else "response", top[b] if again else None))
    return out


@pytest.fixture(scope="module")
def page_rows():
    long = "é<p>x</p>\r\n\r\nWARC/1.1\r\n" * 80
    return [(1, long), (2, long), (3, long), (3, long), (4, "short"), (5, "short"), (6, None), (7, ""), (None, long), (8, "y" * 1000), (9, "z" * 999), (10, "z" * 999)]


@pytest.mark.parametrize("compression", ["gzip", "none"])
def test_warc_round_trip(spark, page_rows, tmp_path, compression):
    pages = spark.createDataFrame([(p, f"http://h/{p}\r\nX: y", h, "r") for p, h in page_rows], "page_id long, url string, html string, record_type string")
    path = f"file://{tmp_path}/w"
    warc.write_warc(warc.page_records(pages.repartition(3)), path, compression=compression)
    back = warc.read_warc(spark, path)
    got = back.select(warc.page_of("record_id"), "payload_bytes", "payload_digest", "record_type", warc.page_of("refers_to")).collect()
    key = lambda r: tuple((x is None, str(x)) for x in r)
    assert sorted(map(tuple, got), key=key) == sorted(brute_pages(page_rows), key=key)
    assert {bytes(r.payload).decode() for r in back.where("record_type = 'response'").collect()} == {h or "" for _, h in page_rows}
    some = warc.read_warc(spark, path, payload=False).where("record_type = 'revisit'")
    assert some.count() == 3
    assert "payload" in some.columns


def test_no_pages_and_pages_over_a_megabyte(spark, tmp_path):
    none = spark.createDataFrame([], "page_id long, url string, html string")
    assert warc.archive_pages(none, path=f"file://{tmp_path}/none").count() == 0
    rows = [(1, "é" * 700_000), (2, "é" * 700_000), (3, "x")]
    pages = spark.createDataFrame([(p, "u", h) for p, h in rows], "page_id long, url string, html string")
    got = warc.archive_pages(pages, path=f"file://{tmp_path}/long").collect()
    assert sorted(map(tuple, got)) == sorted(brute_pages(rows))


def test_reader_tests_headers_first(page_rows, spark, tmp_path):
    pages = spark.createDataFrame(page_rows, "page_id long, html string").withColumn("url", F.lit("u"))
    path = f"file://{tmp_path}/w"
    warc.write_warc(warc.page_records(pages.coalesce(1)), path)
    reader = warc.WarcReader({"path": path})
    left = list(reader.pushFilters([warc.EqualTo(("record_type",), "revisit"), warc.EqualTo(("payload_bytes",), 3)]))
    assert len(left) == 1 and reader.wanted == {"record_type": {"revisit"}}
    rows = [r for p in reader.partitions() for b in reader.read(p) for r in b.to_pylist()]
    assert {r["record_type"] for r in rows} == {"revisit"} and len(rows) == 3


def test_foreign_gzip_members_are_read(tmp_path):
    import gzip

    record = warc.record({"record_type": "response", "record_id": "<urn:page:1>", "payload_digest": hashlib.sha1(b"q" * 9000).hexdigest(), "payload_bytes": 9000, "payload": b"q" * 9000})
    (tmp_path / "x.warc.gz").write_bytes(gzip.compress(record) + gzip.compress(record))
    reader = warc.WarcReader({"path": str(tmp_path)})
    rows = [r for p in reader.partitions() for b in reader.read(p) for r in b.to_pylist()]
    assert [r["payload_bytes"] for r in rows] == [9000, 9000]


@pytest.mark.parametrize("name", ["op1_substring_dedup", "op2_quality_rules", "op3_top_k_search", "op4_jaccard_join", "op10_warc_pages"])
def test_contract_queries_match_sql(same, name):
    same(name)


def test_pipeline_stages_equal_brute_force(spark):
    import corpus_pipeline
    from brute import components, substring

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language_id", "quality_rules", "jaccard_join", "substring_dedup", "packing"]
    first = stages["language_id"](spark, docs, SMALL).cache()
    assert first.columns == docs.columns and 0 < first.count() <= docs.count()
    second = stages["quality_rules"](spark, first, SMALL).cache()
    assert second.columns == docs.columns
    rows = [(r.doc_id, r.text) for r in second.collect()]
    third = stages["jaccard_join"](spark, second, SMALL).cache()
    assert sorted(r.doc_id for r in third.collect()) == sorted(d for d, _, c in components(rows) if c == d)
    fourth = stages["substring_dedup"](spark, third, SMALL).cache()
    cut = substring([(r.doc_id, r.text) for r in third.collect()])
    want = {d: (n, sha) for d, _, n, sha in cut}
    assert sorted(r.doc_id for r in fourth.select("doc_id").collect()) == sorted(d for d, words, n, _ in cut if not n or n < words)
    before = {r.doc_id: r.text for r in third.collect()}
    for r in fourth.collect():
        removed, sha = want[r.doc_id]
        assert r.text == before[r.doc_id] if removed == 0 else hashlib.sha256(r.text.encode()).hexdigest() == sha
        assert r.n_chars == len(r.text)
    packed = stages["packing"](spark, fourth, SMALL)
    assert {r.doc_id for r in packed.select("doc_id").collect()} == {r.doc_id for r in fourth.collect()}
    # How documents are cut depends on the tasks; what they hold does not.
    whole = lambda df: sorted(map(tuple, df.groupBy("doc_id").agg(F.sum("length"), F.max("doc_tokens")).collect()))
    assert whole(corpus_pipeline.run(spark, SMALL)) == whole(packed)


@pytest.fixture(scope="module")
def stage_rows():
    """Nulls in any column, empty, tied and repeated rows, copies under one id,
    a passage in two documents, a document that loses all its words, a long text."""
    import random

    rng = random.Random(21)
    vocab = [f"{a}{b}{c}" for a in "bdgmst" for b in "aeiou" for c in "lnr"]
    text = lambda n: " ".join(rng.choice(vocab) for _ in range(n)) + "."
    a, b, passage = text(80), text(80), text(60)
    c = f"{text(40)} {passage} {text(40)}"
    rows = [(1, a, "en"), (2, a, "en"), (2, b, None), (2, b, None), (None, a, "fr"), (None, text(50), None), (3, None, "en"), (4, "", "en"), (4, "", "en"), (5, " \n", None)]
    rows += [(6, c, "en"), (7, passage, "en"), (8, f"{text(30)} {passage}", "en"), (9, a.upper(), "en"), (10, text(200_000), "de")]
    return [(*r, "src", len(r[1] or ""), i, "x") for i, r in enumerate(rows)]


def stage_table(spark, rows):
    return spark.createDataFrame(
        rows, "doc_id long, text string, lang string, source string, n_chars long, n_words int, kept_text string"
    ).repartition(3)


def test_stages_on_edge_rows_and_empty_tables(spark, stage_rows):
    """n_words is the row's number here: its name clashes, its values tell rows apart."""
    import corpus_pipeline
    from brute import components, quality, substring

    stages = dict(corpus_pipeline.STAGES)
    docs = stage_table(spark, stage_rows)
    none = docs.where("false")
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, none, SMALL)
        assert got.count() == 0
        assert name == "packing" or got.schema.simpleString() == docs.schema.simpleString()
    at = lambda name: {r.n_words: r for r in stages[name](spark, docs, SMALL).collect()}

    kept = at("language_id")
    assert set(kept) <= {r[5] for r in stage_rows if any(ch.isalpha() for ch in r[1] or "")} and {0, 11} <= set(kept)
    kept = at("quality_rules")
    # The one in capitals passes the base and fails a rule.
    assert set(kept) == {r[5] for r in stage_rows if not quality(r[1])[5] and r[1] != r[1].upper()}

    linked = components([(r[0], r[1]) for r in stage_rows])
    kept = at("jaccard_join")
    by = {}
    for r, (_, n, label) in zip(stage_rows, linked, strict=True):
        by.setdefault(("alone", r[5]) if not n else (label, None if label is not None else r[1]), []).append(r)
    assert len(kept) == len(by)
    for group in by.values():
        stay = [r for r in group if r[5] in kept]
        assert len(stay) == 1 and (stay[0][0] is None) <= all(r[0] is None for r in group)
        assert stay[0][0] == min((r[0] for r in group if r[0] is not None), default=None)
    assert len([r for r in kept.values() if r.doc_id == 2]) == 1  # (2, b) stays, (2, a) goes

    kept = at("substring_dedup")
    for r, (_, words, gone, sha) in zip(stage_rows, substring([(r[0], r[1]) for r in stage_rows]), strict=True):
        if gone and gone == words:
            assert r[5] not in kept
            continue
        row = kept[r[5]]
        if gone:
            assert hashlib.sha256(row.text.encode()).hexdigest() == sha and row.n_chars == len(row.text)
        else:
            assert (row.text, row.n_chars) == (r[1], r[4])
    assert 11 not in kept  # the passage alone

    pieces = stages["packing"](spark, docs, SMALL).collect()
    assert sum(r.start == 0 for r in pieces) == len(stage_rows)
    assert sum(r.length for r in pieces) == sum(r.doc_tokens for r in pieces if r.start == 0)


def test_passages_without_a_column_of_lengths(spark, stage_rows):
    import corpus_pipeline

    docs = stage_table(spark, stage_rows).drop("n_chars")
    assert corpus_pipeline.passage_stage(spark, docs, SMALL).columns == docs.columns
