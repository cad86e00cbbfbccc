"""Token counts, packing, archives and pieces against the libraries."""

import hashlib
import zlib

import numpy as np
import pytest
import public_tokenizers as P
from brute import merge_one_by_one
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from varledger.llm import common, packing, pieces, token_archive, token_counts

KEY = lambda r: tuple((x is None, str(x)) for x in r)


def library_ids(texts, name):
    tok = Tokenizer.from_file(P.path(name))
    return [e.ids for e in tok.encode_batch([t or "" for t in texts], add_special_tokens=False)]


def crc(ids):
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_rank_engine_equals_the_library(rows):
    encode = common.byte_bpe(P.path("byte_bpe_50k.json"))
    for (_, t), ids in zip(rows, library_ids([t for _, t in rows], "byte_bpe_50k.json"), strict=True):
        assert encode(t or "").tolist() == ids


def test_token_counts_equal_the_library(spark, docs, rows, tmp_path):
    cache = f"file://{tmp_path}/cache"
    n = library_ids([t for _, t in rows], "word_bpe_49k.json")
    want = sorted([(d, len((t or "").encode()), len(i), len(i) > 2048) for (d, t), i in zip(rows, n, strict=True)], key=KEY)
    for again in range(2):
        got = token_counts.count_tokens(docs, tokenizer=P.path("word_bpe_49k.json"), cache_path=cache)
        assert sorted(map(tuple, got.collect()), key=KEY) == want
        stored = spark.read.parquet(cache)
        assert stored.count() == stored.select("content_digest").distinct().count()  # the second call appends nothing
    other = token_counts.count_tokens(docs, tokenizer=P.path("byte_bpe_50k.json"), cache_path=cache)
    assert {r.n_tokens for r in other.where("doc_id = 5").collect()} == {len(library_ids(["a b c d e"], "byte_bpe_50k.json")[0])}


def test_packing_places_every_id_once(docs, rows):
    got = packing.pack_documents(docs, tokenizer=P.path("byte_bpe_50k.json"), window=64, max_open=16, with_ids=True).collect()
    want = sorted(tuple(i + [0]) for i in library_ids([t for _, t in rows], "byte_bpe_50k.json"))
    # Pieces of one document follow each other by start; rows that repeat an id
    # are told apart by their lengths.
    by = {}
    for r in got:
        assert crc(r.ids) == r.ids_crc32 and r.length == len(r.ids) and r.length <= 64
        by.setdefault((r.doc_id, r.doc_tokens, r.start), []).append(tuple(r.ids))
    total = sorted(x for parts in by.values() for p in parts for x in p)
    assert total == sorted(x for w in want for x in w)
    fill = {}
    for r in sorted(got, key=lambda r: (r.sequence_id, r.offset)):
        assert fill.get(r.sequence_id, 0) == r.offset
        fill[r.sequence_id] = r.offset + r.length
    assert max(fill.values()) <= 64
    assert sum(f < 64 for f in fill.values()) <= 5  # one for each task


def test_level_packer_minimises_squares():
    closed = []
    p = packing.LevelPacker(10, 1000, closed.append)
    ids = lambda n: np.arange(n, dtype=np.uint32)
    for n in (6, 6, 4, 4):
        p.add(n, ids(n))
    assert len(closed) == 2 and all(sorted(x[0] for x in c) == [4, 6] for c in closed)
    assert not p.count.any() and p.open == 0
    p.add("long", ids(25))
    assert [len(x[2]) for c in closed[2:] for x in c] == [10, 10]
    p.finish()
    assert sum(len(x[2]) for c in closed for x in c) == 45


def test_archive_round_trip(docs, rows, tmp_path):
    got = token_archive.archive_documents(docs, tokenizer=P.path("byte_bpe_50k.json"), path=f"file://{tmp_path}/a", with_ids=True).orderBy("start").collect()
    ids = library_ids([t for _, t in rows], "byte_bpe_50k.json")
    want = sorted([(d, tuple(i + [2])) for (d, _), i in zip(rows, ids, strict=True)], key=KEY)
    assert sorted([(r.doc_id, tuple(r.ids)) for r in got], key=KEY) == want
    at = 0
    for r in got:
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(r.ids), crc(r.ids))
        at += r.n_tokens
    keys = [r.doc_id for r in got]
    assert keys == sorted(keys, key=lambda k: (k is not None, k or 0))
    segment = next((tmp_path / "a").glob("*.ran"))
    first = token_archive.segment_index(str(segment))
    assert first[0] == 0


@pytest.mark.parametrize("n", [0, 1, 255, 256, 70_000])
def test_numeral_system_round_trip(n):
    rng = np.random.default_rng(n)
    sym = np.minimum(rng.geometric(0.01, n) - 1, 999).astype(np.uint32)
    t = token_archive.Tables.fitted(np.bincount(sym, minlength=1000))
    t = token_archive.Tables.from_bytes(t.to_bytes())
    raw = token_archive.encode_block([5, None], [sym[: n // 2], sym[n // 2 :]], t)
    keys, ids = token_archive.decode_block(raw, t)
    assert keys == [5, None]
    assert (np.concatenate(ids) == sym).all()
    if n > 1000:
        assert len(raw) < 1.2 * n  # about 8.1 bits a symbol
    with pytest.raises(ValueError, match="damaged"):
        token_archive.decode_block(raw[:-1] + bytes([raw[-1] ^ 1]), t)


def test_pieces_equal_the_library(docs, rows):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    want = []
    for d, t in rows:
        ids = sp.encode(t or "") + [2]
        back = sp.decode(ids)
        want.append((d, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(back.encode()).hexdigest()))
    got = pieces.encode_pieces(docs, model_path=P.path("piece_bpe_32k.model"))
    assert sorted(map(tuple, got.collect()), key=KEY) == sorted(want, key=KEY)


def test_rounds_equal_single_merges_and_decode(rows, docs):
    m = pieces.PieceModel(P.path("piece_bpe_32k.model"))
    memo = {}
    words = sorted({w for _, t in rows for w in (t or "").split() if w})
    for w, sym in zip(words, m.merge_rounds(words), strict=True):
        assert sym.tolist() == merge_one_by_one(m, w, memo)
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    odd = [m.byte_id[b] for b in (0xE2, 0x41, 0xF0, 0x9F, 0x98, 0x80, 0xC3)]
    for ids in ([], [1, 2], odd, [0, 300, 0], [259, 259, 400]):
        assert m.decode(ids) == sp.decode(ids)
    enc = pieces.encode_pieces(docs, model_path=P.path("piece_bpe_32k.model"), with_ids=True)
    back = pieces.decode_pieces(enc, model_path=P.path("piece_bpe_32k.model"), key_cols=["doc_id", "decoded_sha256"])
    assert back.where(F.sha2("decoded", 256) != F.col("decoded_sha256")).count() == 0


def test_long_words_equal_the_library():
    """Words of 97 to 200,000 symbols without a space, repeated, random and mixed."""
    import random
    import time

    import sentencepiece

    rng = random.Random(11)
    m = pieces.PieceModel(P.path("piece_bpe_32k.model"))
    sp = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    syllables = ["the", "ing", "tion", "en", "aa", "lle", "pour", "schaft", "a", "e", "ñ", "ss", "0", "11", "abc"]
    texts = ["x" * 3001, "ab" * 2000 + "a", "aaab" * 700, "的一是" * 400, "." * 999, "=-" * 500, "abcabcab" * 300]
    for n in (97, 500, 4000):
        texts.append("".join(rng.choice(syllables) for _ in range(n)))
        texts.append("".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(n)))
        texts.append("".join(rng.choice("ABCXYZabcxyz0123456789+/") for _ in range(n)))
        texts.append("".join(chr(rng.choice([rng.randint(97, 122), rng.randint(0x4E00, 0x9FFF), 0x1F600])) for _ in range(n)))
    for t in texts:
        assert m.encode(t) == sp.encode(t), t[:40]
    long = "".join(rng.choice(syllables) for _ in range(70_000))
    began = time.time()
    assert m.encode(long) == sp.encode(long)
    assert time.time() - began < 60


def test_random_texts_equal_the_library():
    import random

    import sentencepiece

    rng = random.Random(12)
    m = pieces.PieceModel(P.path("piece_bpe_32k.model"))
    sp = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    letters = "aabcdeeefghiiillmnnooprsstu  ABC.,'éñß0129▁\n\t"
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 150))) for _ in range(3000)]
    assert [m.encode(t) for t in texts] == [sp.encode(t) for t in texts]


def test_white_space_counts_where_a_tokenizer_keeps_it(spark, tmp_path):
    """Texts that differ in white space only; one tokenizer keeps it, one drops it."""
    texts = ["a b", "a  b", "a\n\n b", " a b ", "a\tb", "  a     b  "]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    cache = f"file://{tmp_path}/cache"
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        got = token_counts.count_tokens(df, tokenizer=P.path(name), cache_path=cache).orderBy("doc_id").collect()
        assert [r.n_tokens for r in got] == [len(i) for i in library_ids(texts, name)]


def test_rank_engine_equals_the_library_on_random_texts():
    import random

    rng = random.Random(13)
    letters = "aabcdeeefghiiillmnnooprsstu   ABCDé中ñß01299'.,!<|>_\n\t\r\u00a0\u200b\u3000😀"
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 120))) for _ in range(5000)]
    texts += ["'s 'S it's IT'S we'll", "<|endoftext|><|endoftext|>", "a" * 5000, " " * 5000, "\n" * 300 + "x"]
    encode = common.byte_bpe(P.path("byte_bpe_50k.json"))
    for t, ids in zip(texts, library_ids(texts, "byte_bpe_50k.json"), strict=True):
        assert encode(t).tolist() == ids, t


def test_texts_over_a_megabyte(spark):
    """Counts, packing, archive and pieces of long texts against the libraries."""
    import random

    import sentencepiece

    rng = random.Random(6)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 8))) for _ in range(3000)]
    texts = [" ".join(rng.choice(words) for _ in range(250_000)), "ab" * 300_000, "short one"]
    assert len(texts[0]) > 1_000_000
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    n = [len(i) for i in library_ids(texts, "word_bpe_49k.json")]
    assert [r.n_tokens for r in token_counts.count_tokens(df, tokenizer=P.path("word_bpe_49k.json")).orderBy("doc_id").collect()] == n
    ids = library_ids(texts, "byte_bpe_50k.json")
    packed = packing.pack_documents(df, tokenizer=P.path("byte_bpe_50k.json")).groupBy("doc_id").agg(F.sum("length").alias("n")).orderBy("doc_id").collect()
    assert [r.n for r in packed] == [len(i) + 1 for i in ids]
    kept = token_archive.archive_documents(df, tokenizer=P.path("byte_bpe_50k.json")).orderBy("doc_id").collect()
    assert [(r.n_tokens, r.ids_crc32) for r in kept] == [(len(i) + 1, crc([*i, 2])) for i in ids]
    sp = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    want = [hashlib.sha256(" ".join(map(str, [*sp.encode(t), 2])).encode()).hexdigest() for t in texts]
    assert [r.ids_sha256 for r in pieces.encode_pieces(df, model_path=P.path("piece_bpe_32k.model")).orderBy("doc_id").collect()] == want


def test_empty_tables(empty):
    assert token_counts.count_tokens(empty, tokenizer=P.path("word_bpe_49k.json")).count() == 0
    assert packing.pack_documents(empty, tokenizer=P.path("byte_bpe_50k.json")).count() == 0
    assert token_archive.archive_documents(empty, tokenizer=P.path("byte_bpe_50k.json")).count() == 0
    assert pieces.encode_pieces(empty, model_path=P.path("piece_bpe_32k.model")).count() == 0
