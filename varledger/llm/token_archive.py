"""Token archives coded by a static range asymmetric numeral system.

Layout of an archive folder:

* ``tables.bin``: the shared frequency table (one for all blocks), with a CRC.
* ``segment-*.ran``: blocks one behind the other, then an index of block
  offsets (the checkpoints from which decoders start) and a trailer.

A block holds whole documents and is decodable by itself: a header, its
documents' ids and lengths, the final states of its interleaved lanes and
their shared word stream, under a CRC.  Symbol i belongs to lane i mod lanes,
so one numpy step codes a symbol of every lane at once.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import byte_bpe, fresh_path, local_fs, remove_path, vocab_size, written

MAGIC, TRAILER = b"RNS1", b"1SNR"
SCALE_BITS = 20
_LOW = np.uint64(1 << 31)
_HEAD = struct.Struct("<4sIIIII")  # magic, documents, symbols, lanes, words, crc of the rest
_TAIL = struct.Struct("<QI4s")  # offset of the index, its crc, trailer

MANIFEST = "part long, first_row long, path string, at long, size long, ids_before long, n_ids long"


# -- coding a block -------------------------------------------------------


class Tables:
    """Frequencies that sum to 2**SCALE_BITS, their running sums and, for
    decoding, the symbol of each slot."""

    def __init__(self, freq: np.ndarray):
        self.freq = freq.astype(np.uint64)
        self.cum = np.concatenate([[0], np.cumsum(self.freq)[:-1]]).astype(np.uint64)
        self._slot: np.ndarray | None = None

    @property
    def slot(self) -> np.ndarray:
        if self._slot is None:
            self._slot = np.repeat(np.arange(len(self.freq), dtype=np.uint32), self.freq.astype(np.int64))
        return self._slot

    @classmethod
    def fitted(cls, counts: np.ndarray) -> Tables:
        """Scaled counts; each symbol that occurs keeps at least one slot."""
        total, m = int(counts.sum()), 1 << SCALE_BITS
        if np.count_nonzero(counts) > m // 2:
            raise ValueError("the vocabulary is too large for this table")
        freq = np.zeros(len(counts), dtype=np.int64)
        if total:
            used = counts > 0
            freq[used] = np.maximum(1, np.floor(counts[used] / total * m).astype(np.int64))
            gap = m - int(freq.sum())
            if gap >= 0:
                freq[int(np.argmax(freq))] += gap
            else:  # take back from the largest, which lose least
                for s in np.argsort(-freq, kind="stable"):
                    take = min(-gap, int(freq[s]) // 2)
                    freq[s] -= take
                    gap += take
                    if not gap:
                        break
        return cls(freq)

    def to_bytes(self) -> bytes:
        raw = self.freq.astype("<u4").tobytes()
        return MAGIC + struct.pack("<III", SCALE_BITS, len(self.freq), zlib.crc32(raw)) + raw

    @classmethod
    def from_bytes(cls, raw: bytes) -> Tables:
        bits, n, crc = struct.unpack_from("<III", raw, 4)
        body = raw[16 : 16 + 4 * n]
        if raw[:4] != MAGIC or bits != SCALE_BITS or zlib.crc32(body) != crc:
            raise ValueError("damaged frequency table")
        return cls(np.frombuffer(body, dtype="<u4"))


def lanes_for(n: int) -> int:
    return max(1, min(4096, n // 256))


def encode_symbols(sym: np.ndarray, t: Tables) -> tuple[np.ndarray, np.ndarray]:
    """Final lane states (uint64) and the word stream (uint32) of symbols."""
    n, k = len(sym), lanes_for(len(sym))
    state = np.full(k, _LOW, dtype=np.uint64)
    words: list[np.ndarray] = []
    bits, word = np.uint64(SCALE_BITS), np.uint64(32)
    room = np.uint64(63 - SCALE_BITS)
    freq, cum = t.freq[sym], t.cum[sym]
    for lo in range((n - 1) // k * k, -1, -k):
        f, c = freq[lo : lo + k], cum[lo : lo + k]
        x = state[: len(f)]
        full = np.flatnonzero(x >= (f << room))
        if len(full):
            y = x[full]
            words.append(y.astype(np.uint32))
            x[full] = y >> word
        q = x // f
        state[: len(f)] = (q << bits) + (x - q * f) + c
    return state, np.concatenate(words[::-1]) if words else np.zeros(0, dtype=np.uint32)


def decode_symbols(n: int, state: np.ndarray, words: np.ndarray, t: Tables) -> np.ndarray:
    k, at = len(state), 0
    state = state.copy()
    out = np.empty(n, dtype=np.uint32)
    bits, word, mask = np.uint64(SCALE_BITS), np.uint64(32), np.uint64((1 << SCALE_BITS) - 1)
    for lo in range(0, n, k):
        x = state[: min(k, n - lo)]
        slot = x & mask
        s = t.slot[slot]
        out[lo : lo + len(x)] = s
        x = t.freq[s] * (x >> bits) + slot - t.cum[s]
        low = np.flatnonzero(x < _LOW)
        if len(low):
            x[low] = (x[low] << word) | words[at : at + len(low)]
            at += len(low)
        state[: len(x)] = x
    if at != len(words) or (state != _LOW).any():
        raise ValueError("the word stream does not end where it should")
    return out


def encode_block(keys: list[int | None], ids: list[np.ndarray], t: Tables) -> bytes:
    lengths = np.array([len(x) for x in ids], dtype="<u4")
    null = np.array([k is None for k in keys])
    key = np.array([0 if k is None else k for k in keys], dtype="<i8")
    sym = np.concatenate(ids) if ids else np.zeros(0, dtype=np.uint32)
    state, words = encode_symbols(sym, t) if len(sym) else (np.zeros(0, np.uint64), np.zeros(0, np.uint32))
    body = key.tobytes() + np.packbits(null).tobytes() + lengths.tobytes()
    body += state.astype("<u8").tobytes() + words.astype("<u4").tobytes()
    return _HEAD.pack(MAGIC, len(keys), len(sym), len(state), len(words), zlib.crc32(body)) + body


def decode_block(raw: bytes, t: Tables) -> tuple[list[int | None], list[np.ndarray]]:
    magic, docs, n, lanes, n_words, crc = _HEAD.unpack_from(raw)
    body = raw[_HEAD.size :]
    if magic != MAGIC or zlib.crc32(body) != crc:
        raise ValueError("damaged block")
    at = 8 * docs
    key = np.frombuffer(body, "<i8", docs).tolist()
    null = np.unpackbits(np.frombuffer(body, np.uint8, (docs + 7) // 8, at))[:docs]
    at += (docs + 7) // 8
    lengths = np.frombuffer(body, "<u4", docs, at).astype(np.int64)
    at += 4 * docs
    state = np.frombuffer(body, "<u8", lanes, at)
    words = np.frombuffer(body, "<u4", n_words, at + 8 * lanes)
    sym = decode_symbols(n, state, words, t) if n else np.zeros(0, np.uint32)
    ends = np.cumsum(lengths)
    return (
        [None if z else k for k, z in zip(key, null, strict=True)],
        [sym[e - m : e] for e, m in zip(ends.tolist(), lengths.tolist(), strict=True)],
    )


def segment_tail(index: list[int], at: int) -> bytes:
    raw = np.array(index, dtype="<u8").tobytes()
    return raw + _TAIL.pack(at, zlib.crc32(raw), TRAILER)


# -- archives in Spark ----------------------------------------------------


def token_rows(docs: DataFrame, *, tokenizer: str, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, part, row, ids (little-endian, two bytes where the vocabulary
    allows) in ascending (doc_id, mark) order of (part, row).

    The mark (a text hash) only spreads rows that repeat one id; null ids come
    first, equal rows stay beside each other.
    """
    kind = "<u2" if max(vocab_size(tokenizer), end_id + 1) <= 1 << 16 else "<u4"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, row = byte_bpe(tokenizer), TaskContext.get().partitionId(), 0
        end = np.array([end_id], dtype=kind).tobytes()
        for whole in batches:
            for lo in range(0, whole.num_rows, 1024):
                batch = whole.slice(lo, 1024)
                ids = [encode(t.as_py() or "").astype(kind).tobytes() + end for t in batch.column(1)]
                yield pa.RecordBatch.from_pydict(
                    {
                        "doc_id": batch.column(0),
                        "part": pa.array([part] * len(ids), pa.int64()),
                        "row": pa.array(range(row, row + len(ids)), pa.int64()),
                        "ids": pa.array(ids, pa.binary()),
                    }
                )
                row += len(ids)

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text").asc()]
    parts = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    placed = rows.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    return placed.mapInArrow(run, "doc_id long, part long, row long, ids binary")


def token_counts(tokens: DataFrame, *, width: int, size: int) -> np.ndarray:
    """How often each id occurs in all documents: at most ``size`` numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, dtype=np.int64)
        for batch in batches:
            total += np.bincount(np.frombuffer(b"".join(batch.column(0).to_pylist()), dtype=f"<u{width}"), minlength=size)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_pydict({"id": pa.array(used, pa.int64()), "n": pa.array(total[used], pa.int64())})

    found = tokens.select("ids").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    counts = np.zeros(size, dtype=np.int64)
    for row in found.toLocalIterator():
        counts[row.id] = row.n
    return counts


def write_archive(tokens: DataFrame, path: str, *, width: int, size: int, block_ids: int = 1 << 20) -> DataFrame:
    """Write ``tokens`` (from token_rows, already stored) and return the
    manifest of blocks: segment order (part, first_row), file, byte range, ids
    in the segment before the block and ids in it."""
    spark = tokens.sparkSession
    tables = Tables.fitted(token_counts(tokens, width=width, size=size))
    fs, where = local_fs(path)
    fs.create_dir(where, recursive=True)
    with fs.open_output_stream(f"{where}/tables.bin") as f:
        f.write(tables.to_bytes())
    shared = spark.sparkContext.broadcast(tables.freq.astype(np.uint32))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = Tables(shared.value)
        fs, where = local_fs(path)
        context = TaskContext.get()
        keys: list = []
        ids: list[np.ndarray] = []
        blocks: list[tuple] = []
        index: list[int] = []
        out = name = None
        part = first = held = before = at = 0

        def close_block() -> None:
            nonlocal held, before, at
            if keys:
                raw = encode_block(keys, ids, t)
                out.write(raw)
                index.append(at)
                blocks.append((part, first, f"{path}/{name}", at, len(raw), before, held))
                at, before, held = at + len(raw), before + held, 0
                keys.clear()
                ids.clear()

        def close_segment() -> None:
            nonlocal out, at, before
            close_block()
            out.write(segment_tail(index, at))
            out.close()
            index.clear()
            out, at, before = None, 0, 0

        expected = None
        for batch in batches:
            for key, p, row, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if out is not None and (p, row) != expected:  # another stretch of the order begins
                    close_segment()
                if out is None:
                    part, first = p, row
                    # A repeated attempt writes files of its own; only the
                    # manifest of the attempt that counts names its files.
                    name = f"segment-{p:06d}-{row:012d}-{context.taskAttemptId()}.ran"
                    out = fs.open_output_stream(f"{where}/{name}")
                expected = (p, row + 1)
                keys.append(key)
                ids.append(np.frombuffer(raw, dtype=f"<u{width}"))
                held += len(ids[-1])
                if held >= block_ids:
                    close_block()
        if out is not None:
            close_segment()
        cols = list(zip(*blocks, strict=True)) or [()] * 7
        kinds = [pa.int64(), pa.int64(), pa.string(), *[pa.int64()] * 4]
        names = [f.split()[0] for f in MANIFEST.split(", ")]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)

    return written(tokens.select("doc_id", "part", "row", "ids").mapInArrow(run, MANIFEST), "token-manifest")


def read_archive(spark: SparkSession, path: str, manifest: DataFrame, *, with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of every document, each
    block read and decoded by itself from its checkpoint."""
    segments = manifest.groupBy("part", "first_row").agg(F.sum("n_ids").alias("n_ids"))
    ahead = Window.orderBy("part", "first_row").rowsBetween(Window.unboundedPreceding, -1)
    segments = segments.select("part", "first_row", F.coalesce(F.sum("n_ids").over(ahead), F.lit(0)).alias("base"))
    blocks = manifest.join(segments, ["part", "first_row"]).select(
        "path", "at", "size", (F.col("base") + F.col("ids_before")).alias("start")
    )
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids array<long>" if with_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = _tables(path)
        for batch in batches:
            for name, at, size, start in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                fs, where = local_fs(name)
                with fs.open_input_file(where) as f:
                    f.seek(at)
                    keys, ids = decode_block(f.read(size), t)
                n = np.array([len(x) for x in ids], dtype=np.int64)
                out = {
                    "doc_id": pa.array(keys, pa.int64()),
                    "start": pa.array(start + np.cumsum(n) - n, pa.int64()),
                    "n_tokens": pa.array(n, pa.int64()),
                    "ids_crc32": pa.array([zlib.crc32(x.astype("<u4", copy=False).tobytes()) for x in ids], pa.int64()),
                }
                if with_ids:
                    out["ids"] = pa.array([x.astype(np.int64) for x in ids], pa.list_(pa.int64()))
                yield pa.RecordBatch.from_pydict(out)

    spread = max(1, min(manifest.count(), 4 * spark.sparkContext.defaultParallelism * 8))
    return blocks.repartition(spread).mapInArrow(run, schema)


@lru_cache(maxsize=1)
def _tables(path: str) -> Tables:
    fs, where = local_fs(path)
    with fs.open_input_stream(f"{where}/tables.bin") as f:
        return Tables.from_bytes(f.read())


def segment_index(path: str) -> list[int]:
    """Checkpoints of one segment file, from its trailer."""
    fs, where = local_fs(path)
    with fs.open_input_file(where) as f:
        total = f.size()
        f.seek(total - _TAIL.size)
        at, crc, mark = _TAIL.unpack(f.read(_TAIL.size))
        f.seek(at)
        raw = f.read(total - _TAIL.size - at)
    if mark != TRAILER or zlib.crc32(raw) != crc:
        raise ValueError("damaged index")
    return np.frombuffer(raw, "<u8").tolist()


def archive_documents(
    docs: DataFrame,
    *,
    tokenizer: str,
    path: str | None = None,
    end_id: int = 2,
    id_col: str = "doc_id",
    text_col: str = "text",
    with_ids: bool = False,
) -> DataFrame:
    """Encode, write in ascending id order, read back: one row per document.

    Null text counts as empty (the end id alone).  Null ids come first, rows
    that repeat an id stand together by their text's hash, equal rows in either
    order; an empty table gives no rows; other columns are not read.
    """
    spark = docs.sparkSession
    path = path or fresh_path(spark, "token-archive")
    size = max(vocab_size(tokenizer), end_id + 1)
    tokens = written(
        token_rows(docs, tokenizer=tokenizer, end_id=end_id, id_col=id_col, text_col=text_col), "token-rows"
    )
    manifest = write_archive(tokens, path, width=2 if size <= 1 << 16 else 4, size=size)
    for f in {p.rsplit("/", 1)[0] for p in tokens.inputFiles()}:
        remove_path(spark, f)
    return read_archive(spark, path, manifest, with_ids=with_ids)
