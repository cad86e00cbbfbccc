"""Removal of word windows that start in an earlier document, too.

1. Each task hashes every window of its documents.  Repeats inside the task's
   chunk are settled there and merge into intervals at once; of each distinct
   window only its earliest document goes on.
2. One exchange by hash range counts windows over all tasks: the earliest
   document keeps a window, the others get it as a removed key.
3. Documents meet their intervals and keys by a hash of the id, the windows
   merge into maximal intervals and the words outside stay.

A window that a third of all documents hold reaches step 2 once a chunk, and
all work is by hash ranges, never by a group of copies.  Ranges, homes and
tasks grow with the bytes of the texts, so what one of them holds does not.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import exchange_size
from .windows import (
    bucket_edges,
    cover,
    document_windows,
    groups,
    hashed,
    packed,
    spans,
    unpacked,
    window_hashes,
)

#: Words that a task gathers before it settles a chunk (six bytes each).
CHUNK_WORDS = 400_000
NULL_ID = (1 << 63) - 1
_SIGN = np.uint64(1 << 63)


def _mark(raw: bytes) -> int:
    return xxhash.xxh3_64_intdigest(raw)


def _unsigned(ids: np.ndarray) -> np.ndarray:
    """Order-preserving uint64 of signed ids."""
    return ids.astype(np.int64).view(np.uint64) ^ _SIGN


def _homes(ids: np.ndarray, homes: int) -> np.ndarray:
    x = ids.astype(np.int64).view(np.uint64)
    return (x ^ (x >> np.uint64(17))).view(np.int64) % homes


class _Chunk:
    """Windows of some documents: what is settled here and what goes on."""

    def __init__(self, ids: list[int], texts: list[bytes], width: int):
        order = np.argsort(np.array(ids, dtype=np.int64), kind="stable")
        self.ids = np.array(ids, dtype=np.int64)[order]
        self.texts = [texts[i] for i in order]
        h, self.counts = hashed(self.texts)
        at, doc = document_windows(self.counts, width)
        key = window_hashes(h, width)[at]
        by = np.argsort(key)
        first = groups(key[by])
        self.keys = key[by][first]
        self.owner = np.minimum.reduceat(doc[by], first) if len(first) else doc
        settled = np.zeros(len(key), dtype=bool)
        if len(first):
            earliest = np.repeat(self.ids[self.owner], np.diff(np.append(first, len(key))))
            settled[by] = self.ids[doc[by]] > earliest
        self.at, self.doc, self.settled, self.width = at, doc, settled, width

    def intervals(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Document number, first word and end of what is settled here."""
        covered = cover(int(self.counts.sum()), self.at[self.settled], self.width)
        begin, end = spans(covered)
        offset = np.cumsum(self.counts) - self.counts
        doc = np.searchsorted(offset, begin, side="right") - 1
        # A run may go on into the next document: cut it there.
        last = np.searchsorted(offset, end - 1, side="right") - 1
        out = []
        for b, e, d, z in zip(begin.tolist(), end.tolist(), doc.tolist(), last.tolist(), strict=True):
            while d < z:
                stop = int(offset[d] + self.counts[d])
                if stop > b:
                    out.append((d, b - int(offset[d]), stop - int(offset[d])))
                b, d = max(b, stop), d + 1
            out.append((d, b - int(offset[d]), e - int(offset[d])))
        cols = np.array(out, dtype=np.int64).reshape(-1, 3)
        return cols[:, 0], cols[:, 1], cols[:, 2]


def _postings(width: int, buckets: int, homes: int):
    """Rows (place, data): places below ``buckets`` hold keys and their
    earliest documents, the others intervals for one home each."""

    def emit(ids: list[int], texts: list[bytes]) -> Iterator[tuple[int, bytes]]:
        chunk = _Chunk(ids, texts, width)
        edges = bucket_edges(chunk.keys, buckets)
        for b in range(buckets):
            lo, hi = edges[b], edges[b + 1]
            if hi > lo:
                used, number = np.unique(chunk.owner[lo:hi], return_inverse=True)
                table = _unsigned(chunk.ids[used])
                yield b, packed([chunk.keys[lo:hi], number]) + packed([table])
        doc, begin, end = chunk.intervals()
        if len(doc):
            home = _homes(chunk.ids[doc], homes)
            marks = {d: _mark(chunk.texts[d]) for d in set(doc.tolist())}
            mark = np.array([marks[d] for d in doc.tolist()], dtype=np.uint64)
            for h in np.unique(home).tolist():
                own = home == h
                table = _unsigned(chunk.ids[doc[own]])
                yield buckets + h, packed([table, mark[own], begin[own], end[own]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids: list[int] = []
        texts: list[bytes] = []
        size = 0

        def settle() -> pa.RecordBatch:
            rows = list(emit(ids, texts))
            ids.clear()
            texts.clear()
            return pa.RecordBatch.from_pydict(
                {"place": pa.array([r[0] for r in rows], pa.int64()), "data": pa.array([r[1] for r in rows], pa.binary())}
            )

        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), strict=True):
                ids.append(NULL_ID if key is None else key)
                texts.append(text or b"")
                size += len(texts[-1]) // 6 + 1
                if size >= CHUNK_WORDS:
                    yield settle()
                    size = 0
        if ids:
            yield settle()

    return run


def _count(buckets: int, homes: int):
    def run(table: pa.Table) -> pa.Table:
        place = table.column("place")[0].as_py()
        rows = table.column("data").to_pylist()
        if place >= buckets:
            return pa.table({"home": pa.array([place - buckets] * len(rows), pa.int64()), "kind": pa.array([1] * len(rows), pa.int32()), "data": pa.array(rows, pa.binary())})
        keys, ids = [], []
        while rows:
            # steps of the second sorted column begin after the first two
            key, number, steps = unpacked(rows.pop())
            keys.append(key)
            ids.append(np.cumsum(steps, dtype=np.uint64)[number.astype(np.int64)])
        key, owner = np.concatenate(keys), np.concatenate(ids)
        del keys, ids
        by = np.argsort(key)
        key, owner = key[by], owner[by]
        del by
        first = groups(key)
        earliest = np.repeat(np.minimum.reduceat(owner, first), np.diff(np.append(first, len(key))))
        late = owner > earliest
        key, owner = key[late], owner[late]
        home = _homes((owner ^ _SIGN).view(np.int64), homes)
        by = np.lexsort((owner, home))
        key, owner, home = key[by], owner[by], home[by]
        edges = np.append(groups(home), len(home))
        out = [(int(home[lo]), packed([owner[lo:hi], key[lo:hi]])) for lo, hi in zip(edges[:-1], edges[1:], strict=True)]
        return pa.table({"home": pa.array([o[0] for o in out], pa.int64()), "kind": pa.array([0] * len(out), pa.int32()), "data": pa.array([o[1] for o in out], pa.binary())})

    return run


def _removal(width: int, names: list[str], id_at: int, text_at: int):
    def run(docs: pa.Table, removed: pa.Table) -> pa.Table:
        keys: dict[int, list[np.ndarray]] = defaultdict(list)
        intervals: dict[tuple[int, int], list[tuple[int, int]]] = defaultdict(list)
        for kind, raw in zip(removed.column("kind").to_pylist(), removed.column("data").to_pylist(), strict=True):
            cols = unpacked(raw)
            owner = (cols[0] ^ _SIGN).view(np.int64)
            if kind == 0:
                edges = np.append(groups(owner), len(owner))
                for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                    keys[int(owner[lo])].append(cols[1][lo:hi])
            else:
                for o, m, b, e in zip(owner.tolist(), *(c.tolist() for c in cols[1:]), strict=True):
                    intervals[o, m].append((b, e))
        n_words, n_removed, kept, first, last = [], [], [], [], []
        row = docs.column("row").combine_chunks()
        ids = row.field(id_at).to_pylist()
        for key, raw in zip(ids, row.field(text_at).cast(pa.binary()).to_pylist(), strict=True):
            raw = raw or b""
            key = NULL_ID if key is None else key
            words = raw.split()
            begin = end = np.zeros(0, np.int64)
            own = intervals.get((key, _mark(raw))) if intervals else None
            if own or key in keys:
                gone = np.zeros(len(words), dtype=bool)
                if key in keys:
                    at = np.flatnonzero(np.isin(window_hashes(hashed([raw])[0], width), np.concatenate(keys[key])))
                    gone |= cover(len(words), at, width)
                for b, e in own or ():
                    gone[b:e] = True
                begin, end = spans(gone)
                n_removed.append(int(gone.sum()))
                kept.append(b" ".join([w for w, g in zip(words, gone.tolist(), strict=True) if not g]))
            else:
                n_removed.append(0)
                kept.append(b" ".join(words))
            n_words.append(len(words))
            first.append(begin.tolist())
            last.append(end.tolist())
        return pa.table(
            {
                "row": row,
                "kept_text": pa.array(kept, pa.binary()).cast(pa.string()),
                "n_words": pa.array(n_words, pa.int64()),
                "n_removed": pa.array(n_removed, pa.int64()),
                "span_start": pa.array(first, pa.list_(pa.int64())),
                "span_end": pa.array(last, pa.list_(pa.int64())),
            }
        )

    return run


def remove_repeats(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 13, buckets: int | None = None
) -> DataFrame:
    """Each input row as ``row`` with kept_text, n_words, n_removed and the
    maximal removed intervals (span_start, span_end in words).

    A word goes if a window of ``width`` words covers it whose words also start
    in a row with a smaller id.  Rows of one id never remove each other's
    words; a null id counts as larger than all.  Null text has no words; texts
    shorter than a window lose nothing.  Input columns keep their names inside
    ``row``, so none can clash.  An empty table gives no rows.
    """
    ranges, tasks = exchange_size(docs.agg(F.sum(F.octet_length(F.col(text_col).cast("string")))))
    buckets = buckets or ranges
    homes = ranges
    columns = docs.columns
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("row"))
    key = F.coalesce(F.col(f"row.`{id_col}`").cast("long"), F.lit(NULL_ID))
    posts = docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string")).mapInArrow(
        _postings(width, buckets, homes), "place long, data binary"
    )
    removed = posts.repartition(tasks, "place").groupBy("place").applyInArrow(_count(buckets, homes), "home long, kind int, data binary")
    # The home of an id, as _homes() has it, in SQL.
    home = F.pmod(key.bitwiseXOR(F.shiftrightunsigned(key, 17)), F.lit(homes)).cast("long")
    schema = (
        f"row {rows.schema['row'].dataType.simpleString()}, kept_text string, n_words long, n_removed long, "
        "span_start array<long>, span_end array<long>"
    )
    placed = rows.withColumn("home", home)
    return (
        placed.repartition(tasks, "home")
        .groupBy("home")
        .cogroup(removed.repartition(tasks, "home").groupBy("home"))
        .applyInArrow(_removal(width, columns, columns.index(id_col), columns.index(text_col)), schema)
    )
