"""Sum-of-squares online packing of token streams into fixed windows.

Each task packs its own documents as they arrive, so there is no shuffle and
no state beyond the level array and the windows still open.  A document gives
as many whole windows as it fills; what is left goes to the fill level that
makes the sum over levels of (windows at that level) squared smallest.  When a
task ends, or holds ``max_open`` partial windows, their contents are poured
into full windows, which cuts documents there, so at most one window of a task
is padded.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_bpe

PIECES = (
    "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
)


class LevelPacker:
    """Partial windows by fill level; ``closed`` takes each finished window as a
    list of (key, start, ids, doc_tokens)."""

    def __init__(self, window: int, max_open: int, closed):
        self.window, self.max_open, self.closed = window, max_open, closed
        self.count = np.zeros(window + 1, dtype=np.int64)
        self.at: list[list[list]] = [[] for _ in range(window + 1)]
        self.open = 0

    def add(self, key, ids: np.ndarray) -> None:
        n, w = len(ids), self.window
        for lo in range(0, n - n % w, w):
            self.closed([(key, lo, ids[lo : lo + w], n)])
        if n % w:
            self._place((key, n - n % w, ids[n - n % w :], n))

    def _place(self, piece) -> None:
        size, w, count = len(piece[2]), self.window, self.count
        # Growth of the sum of squares for a move from level h to h + size: two
        # times (windows there - windows here) plus two; a new window only adds.
        here = count[1 : w - size + 1]
        there = count[1 + size : w + 1].copy()
        if len(there):
            there[-1] = -1  # a filled window leaves the tally: -2 N + 1 in all
        best, level = 2 * count[size] + 1, 0
        if len(here):
            growth = 2 * (there - here) + 2
            growth[-1] = -2 * here[-1] + 1
            growth[here == 0] = np.iinfo(np.int64).max
            k = len(growth) - 1 - int(np.argmin(growth[::-1]))  # of equals the fullest
            if growth[k] <= best:
                level = k + 1
        if level:
            content = self.at[level].pop()
            count[level] -= 1
            self.open -= 1
        else:
            content = []
        content.append(piece)
        if level + size == w:
            self.closed(content)
            return
        self.at[level + size].append(content)
        count[level + size] += 1
        self.open += 1
        if self.open >= self.max_open:
            self._pour()

    def _pour(self) -> None:
        """Empty all partial windows into full ones; one partial one may stay."""
        content, fill = [], 0
        for level in range(self.window - 1, 0, -1):
            for old in self.at[level]:
                for key, start, ids, n in old:
                    while len(ids):
                        part = ids[: self.window - fill]
                        content.append((key, start, part, n))
                        start, ids, fill = start + len(part), ids[len(part) :], fill + len(part)
                        if fill == self.window:
                            self.closed(content)
                            content, fill = [], 0
            self.at[level] = []
        self.count[:] = 0
        self.open = 0
        if content:
            self.at[fill].append(content)
            self.count[fill] = 1
            self.open = 1

    def finish(self) -> None:
        self._pour()
        for level in self.at:
            for content in level:
                self.closed(content)
            level.clear()


def pack_documents(
    docs: DataFrame,
    *,
    tokenizer: str,
    id_col: str = "doc_id",
    text_col: str = "text",
    window: int = 1024,
    end_id: int = 0,
    max_open: int = 4096,
    with_ids: bool = False,
) -> DataFrame:
    """Pieces of every document, each in one window of at most ``window`` ids.

    Null or empty text is one document of the end id alone.  A null id stays
    null and a repeated row is packed again; an empty table gives no pieces.
    Other columns are not read.  ``with_ids`` adds the ids themselves.
    ``sequence_id`` is the task's number times 2**33 plus its own count, so it
    is the same when a lost task runs again.
    """
    names = [f.split()[0] for f in PIECES.split(", ")]
    schema = PIECES + (", ids array<long>" if with_ids else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_bpe(tokenizer)
        end = np.array([end_id], dtype=np.uint32)
        base, made = TaskContext.get().partitionId() << 33, 0
        rows: list[tuple] = []
        kept: list[np.ndarray] = []

        def closed(content) -> None:
            nonlocal made
            at = 0
            for key, start, ids, n in content:
                raw = ids.astype("<u4", copy=False).tobytes()
                rows.append((key, start, len(ids), zlib.crc32(raw), n, base + made, at))
                if with_ids:
                    kept.append(ids)
                at += len(ids)
            made += 1

        def flush() -> pa.RecordBatch:
            cols = [pa.array(c, type=pa.int64()) for c in zip(*rows, strict=True)]
            out = dict(zip(names, cols, strict=True))
            if with_ids:
                out["ids"] = pa.array([k.astype(np.int64) for k in kept], type=pa.list_(pa.int64()))
            rows.clear()
            kept.clear()
            return pa.RecordBatch.from_pydict(out)

        packer = LevelPacker(window, max_open, closed)
        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                packer.add(key, np.concatenate([encode(text.as_py() or ""), end]))
                if len(rows) >= 4096:
                    yield flush()
        packer.finish()
        if rows:
            yield flush()

    return docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string")).mapInArrow(run, schema)
