"""Substring dedup, quality rules, Jaccard join, language ID."""

import itertools
import random

import pytest
from brute import components, quality, substring
from pyspark.sql import functions as F

from varledger.llm import jaccard_join, windows
from varledger.llm.components import connected_components
from varledger.llm.jaccard_join import jaccard_components
from varledger.llm.language_id import fit, held_out, identify
from varledger.llm.quality import RULES, judge, ordered, text_statistics
from varledger.llm.substring_dedup import remove_repeats

KEY = lambda r: tuple((x is None, str(x)) for x in r)


def test_substring_dedup_equals_brute_force(docs, rows):
    got = remove_repeats(docs).select("row.doc_id", "n_words", "n_removed", F.sha2("kept_text", 256)).collect()
    assert sorted(map(tuple, got), key=KEY) == sorted(substring(rows), key=KEY)


@pytest.mark.parametrize("chunk", [200, 1500])
def test_substring_dedup_over_many_chunks(docs, rows, chunk, monkeypatch):
    monkeypatch.setattr("varledger.llm.substring_dedup.CHUNK_WORDS", chunk)
    got = remove_repeats(docs.coalesce(2), width=5, buckets=7).select("row.doc_id", "n_words", "n_removed", F.sha2("kept_text", 256)).collect()
    assert sorted(map(tuple, got), key=KEY) == sorted(substring(rows, 5), key=KEY)


def test_removed_intervals_are_maximal(docs):
    for r in remove_repeats(docs).where("n_removed > 0").collect():
        assert sum(e - s for s, e in zip(r.span_start, r.span_end, strict=True)) == r.n_removed
        assert all(a < b for a, b in zip(r.span_end, r.span_start[1:], strict=False))


def test_word_hashes_do_not_depend_on_steps(monkeypatch):
    import numpy as np

    raw = np.frombuffer(("ab  cde\tf " * 50 + "y" * 400 + " z").encode(), dtype=np.uint8)
    whole = windows.word_hashes(raw)
    monkeypatch.setattr(windows, "_STEP", 16)
    windows._powers.cache_clear()
    small = windows.word_hashes(raw)
    windows._powers.cache_clear()
    assert (whole[0] == small[0]).all() and (whole[1] == small[1]).all()


def test_quality_statistics_equal_brute_force(docs, rows):
    got = judge(docs).select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed").collect()
    assert sorted(map(tuple, got), key=KEY) == sorted([(d, *quality(t)) for d, t in rows], key=KEY)


def test_quality_order_changes_work_only(docs):
    stats = text_statistics(docs)
    assert {r.name for r in ordered(stats, times=1)} == {r.name for r in RULES}
    a = judge(docs).select("row.n_words", "kept").groupBy("kept").count().orderBy("kept").collect()
    b = judge(docs, rules=tuple(reversed(RULES))).select("row.n_words", "kept").groupBy("kept").count().orderBy("kept").collect()
    assert a == b
    plan = judge(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_jaccard_equals_brute_force(docs, rows):
    assert sorted(map(tuple, jaccard_components(docs).collect()), key=KEY) == sorted(components(rows), key=KEY)


def test_components_of_long_chains(spark):
    """Chains whose smaller end is far from most nodes settle, too: 'there and
    back' numbers, a chain in random order, and a random graph beside them."""
    rng = random.Random(3)
    back = [1, *range(1000, 1090), *range(999, 909, -1), 2]
    chain = rng.sample(range(2000, 2400), 400)
    edges = list(zip(back, back[1:])) + list(zip(chain, chain[1:]))
    edges += [(rng.randrange(5000, 5300), rng.randrange(5000, 5300)) for _ in range(200)]
    want = {}
    for a, b in edges:
        both = want.setdefault(a, {a}) | want.setdefault(b, {b})
        want.update(dict.fromkeys(both, both))
    alone = {a for a, b in edges if a == b and len(want[a]) == 1}
    got = connected_components(spark.createDataFrame(edges, "a long, b long")).collect()
    assert sorted(map(tuple, got)) == sorted((n, min(c)) for n, c in want.items() if n not in alone)


def test_jaccard_large_blocks_lose_no_link(spark, monkeypatch):
    """A chain and a family in slices of a few sets, over several chunks."""
    monkeypatch.setattr(jaccard_join, "CHUNK_WORDS", 700)
    rng = random.Random(3)
    chain = [f"w{i}" for i in range(400)]
    rows = [(i, " ".join(chain[i * 4 : i * 4 + 90])) for i in range(60)]
    seed = [f"v{rng.randint(0, 99)}" for _ in range(100)]
    for i in range(100, 150):
        w = list(seed)
        for _ in range(rng.randint(0, 3)):
            w[rng.randrange(100)] = f"n{rng.randint(0, 9999)}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for size in (4, 512):
        assert sorted(map(tuple, jaccard_components(df, slice_sets=size).collect())) == sorted(components(rows))


@pytest.mark.parametrize("leaves", [2, 4])
def test_no_link_is_lost_in_any_order_of_ids(leaves):
    """A path of three and a star: copies of one set that are not copies of each other."""
    import numpy as np

    base = np.arange(100)
    star = [base] + [np.append(np.delete(base, range(8 * i, 8 * i + 8)), 1000 + 8 * i + np.arange(8)) for i in range(leaves)]
    star = [np.sort(s).astype(np.uint64) for s in star]
    for order in itertools.permutations(range(leaves + 1)):
        union = jaccard_join.Union(leaves + 1)
        jaccard_join.link_all([star[i] for i in order], np.full(leaves + 1, 100), 80, [], union)
        assert len(set(union.label.tolist())) == 1, order


def test_jaccard_whole_blocks_lose_no_link(spark):
    """Paths and stars of texts, each a block far below slice_sets."""
    rows = []
    for g in range(24):
        base = [f"g{g}w{i}" for i in range(104)]
        rows.append((10 * g, " ".join(base)))
        for i in range(2 if g % 2 else 4):
            at = 10 + 20 * i
            rows.append((10 * g + i + 1, " ".join(base[:at] + [f"g{g}n{i}x{j}" for j in range(4)] + base[at + 4 :])))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = sorted(components(rows))
    assert {c for _, _, c in want} == {10 * g for g in range(24)}
    assert sorted(map(tuple, jaccard_components(df, slice_sets=512).collect())) == want


@pytest.mark.parametrize("size", [4, 512])
def test_jaccard_many_random_families(spark, size):
    """Families of overlapping cuts of one text; all of them share a few lines,
    which tie families to large blocks."""
    rng = random.Random(size)
    lines = [f"common line {i} of all the families here" for i in range(40)]
    rows = []
    for g in range(150):
        base = [f"g{g}w{i}" for i in range(90)]
        for i in range(12):
            at = rng.randint(0, 40)
            rows.append((len(rows), " ".join(base[at : at + 44])))
    for g in range(20):  # most of the text is shared with other families
        base = " ".join(rng.sample(lines, 9)).split()
        for i in range(10):
            w = list(base)
            for _ in range(rng.randint(0, 2)):
                w[rng.randrange(len(w))] = f"n{rng.randint(0, 30)}"
            rows.append((len(rows), " ".join(w)))
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert sorted(map(tuple, jaccard_components(df, slice_sets=size).collect())) == sorted(components(rows))


def test_link_all_on_random_sets():
    """400 random collections against all pairs, with and without hubs first."""
    import numpy as np

    rng = random.Random(9)
    for case in range(400):
        sets = []
        for _ in range(rng.randint(1, 4)):
            base = rng.sample(range(400), rng.randint(10, 40))
            for _ in range(rng.randint(1, 8)):
                s = set(base)
                for _ in range(rng.randint(0, 6)):
                    s.discard(rng.choice(base))
                    s.add(rng.randrange(400))
                sets.append(frozenset(s))
        sets = list(dict.fromkeys(sets))
        rng.shuffle(sets)
        arrays = [np.array(sorted(s), dtype=np.uint64) for s in sets]
        want = list(range(len(sets)))
        for i, j in itertools.combinations(range(len(sets)), 2):
            if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]) and want[i] != want[j]:
                old, new = want[j], want[i]
                want = [new if x == old else x for x in want]
        union = jaccard_join.Union(len(sets))
        jaccard_join.link_all(arrays, np.array([len(s) for s in sets]), 80, [0] if case % 2 else [], union)
        pairs = {(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if union.label[i] == union.label[j]}
        assert pairs == {(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if want[i] == want[j]}


def test_empty_tables(empty):
    assert remove_repeats(empty).count() == 0
    assert judge(empty).count() == 0
    assert jaccard_components(empty).count() == 0
    assert identify(empty, fit(empty)).count() == 0


def test_language_of_held_out_documents(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    told = identify(df, fit(df)).where(held_out("row.doc_id")).agg(F.avg((F.col("row.lang") == F.col("lang_pred")).cast("double"))).first()[0]
    assert told > 0.97


def test_copies_do_not_fill_the_training_sample(spark, monkeypatch):
    """Thousands of copies of the text that any draw by its hash takes first."""
    from varledger.llm import language_id

    made = spark.range(8000).select(F.concat(F.lit("ala kota numer "), F.col("id").cast("string"), F.lit(" ma dom")).alias("text"))
    spot = F.pmod(F.xxhash64("text", F.lit(7)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    first = made.where(spot < 0.01).orderBy(F.xxhash64("text")).first().text
    rows = [(3 * i, first, "aa") for i in range(6000)]
    rows += [(100_000 + i, f"{lang} beta gamma {i} delta", lang) for lang in ("aa", "bb", "cc", "dd") for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(4)
    got = {}
    monkeypatch.setattr(language_id, "Model", lambda x, langs: got.update(x=x, langs=langs))
    fit(df)
    for lang in ("aa", "bb", "cc", "dd"):
        own = [x.tobytes() for x, of in zip(got["x"], got["langs"], strict=True) if of == lang]
        assert len(own) > 240 and len(set(own)) > 100, lang


@pytest.mark.parametrize("langs", [["en", "de", "nl", "fr", "es"], ["en", "de"], ["xx"], []])
def test_languages_equal_brute_force(spark, docs, rows, langs):
    """Languages, families and scores against plain loops: five languages of
    two families, one family, one language and no label at all."""
    from brute import language

    words = {x: [f"{x}{a}{b}" for a in "aeiou" for b in "lmnrst"] for x in langs}
    rng = random.Random(8)
    train = [(i, " ".join(rng.choice(words[x]) for _ in range(30)), x) for x in langs for i in range(40)]
    model = fit(spark.createDataFrame(train or [(0, "no label", None)], "doc_id long, text string, lang string"))
    assert model.langs == sorted(langs)
    own = [(d, t) for d, t in rows if len(t or "") < 3000] + [(100 + i, t) for i, (_, t, _) in enumerate(train[:60])]
    df = spark.createDataFrame([(i, t) for i, (_, t) in enumerate(own)], "doc_id long, text string")
    got = {r.doc_id: (r.lang_pred, r.score) for r in identify(df, model).select("row.doc_id", "lang_pred", "score").collect()}
    for i, (_, t) in enumerate(own):
        lang, score = language(model, t)
        assert got[i][0] == lang and abs(got[i][1] - score) < 1e-4, (t, got[i], lang, score)


def test_long_texts(spark):
    """Texts over a megabyte beside short ones, against brute force."""
    rng = random.Random(2)
    words = ["".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(5000)]
    long = " ".join(rng.choice(words) for _ in range(200_000))
    cut = " ".join(long.split()[1000:1100])
    rows = [(1, long), (2, f"{cut} {' '.join(rng.choice(words) for _ in range(20))}"), (3, long + " end"), (4, "x" * 1_200_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert len(long) > 1_000_000
    got = remove_repeats(df).select("row.doc_id", "n_words", "n_removed", F.sha2("kept_text", 256)).collect()
    assert sorted(map(tuple, got)) == sorted(substring(rows))
    got = judge(df).select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed").collect()
    assert sorted(map(tuple, got)) == sorted((d, *quality(t)) for d, t in rows)
    assert sorted(map(tuple, jaccard_components(df).collect())) == sorted(components(rows))


def test_language_edges(docs, rows):
    got = {r.at: r for r in identify(docs, fit(docs)).select(F.col("row.n_words").alias("at"), "lang_pred", "score").collect()}
    assert len(got) == len(rows)
    for i, (_, t) in enumerate(rows):
        letters = any(c.isalpha() for c in t or "")
        assert (got[i].lang_pred == "und") == (not letters)
        assert 0 <= got[i].score <= 1


def test_long_text_scores_do_not_depend_on_steps(docs, monkeypatch):
    from varledger.llm import language_id

    model = fit(docs)
    raw = [("ab cde " * 500).encode()]
    whole = model.margins(raw)
    monkeypatch.setattr(language_id, "_STEP", 256)
    assert abs(whole - model.margins(raw)).max() < 1e-6
