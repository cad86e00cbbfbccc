"""Word and window hashes of whole texts, and the packed exchange that counts
them.

Words are runs of bytes other than space and 9 to 13.  A word's hash is a
polynomial over its bytes, a window's a polynomial over its words' hashes
(Rabin-Karp), both modulo 2**64 by running sums, so each costs a few numpy
operations whatever the width; a mixing step follows each.  Two different
windows share a hash with a chance of 2**-64.

The exchange moves hashes sorted, as differences of fixed width, with the
number of the owner in a small table, instead of one row each.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_STEP = 1 << 19
_BYTE_BASE, _WORD_BASE = 0x9E3779B97F4A7C15, 0xD1B54A32D192ED03  # odd multipliers


def mixed(x: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit values (a bijection)."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x81DADEF4BC2DD44D)
    x ^= x >> np.uint64(33)
    return x


@lru_cache(maxsize=4)
def _powers(base: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i below size."""

    def run(b: int) -> np.ndarray:
        out = np.full(size, b, dtype=np.uint64)
        out[:1] = 1
        with np.errstate(over="ignore"):
            return np.multiply.accumulate(out)

    return run(base), run(pow(base, -1, 1 << 64))


def word_hashes(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and start bytes of the words in a byte array.  The array is taken
    in steps cut at white space, so that memory does not follow long texts."""
    starts_all, hashes_all, at, n = [], [], 0, len(raw)
    while at < n:
        stop = min(n, at + _STEP)
        if stop < n:
            gaps = np.flatnonzero(_SPACE[raw[at:stop]])
            if len(gaps):
                stop = at + int(gaps[-1]) + 1
            else:  # one word longer than a step
                rest = raw[stop:]
                far = 0
                while far < len(rest) and not (hit := _SPACE[rest[far : far + _STEP]]).any():
                    far += _STEP
                stop = n if far >= len(rest) else stop + far + int(np.argmax(hit)) + 1
        part = raw[at:stop]
        word = np.concatenate([[False], ~_SPACE[part], [False]])
        edge = np.flatnonzero(word[1:] != word[:-1])
        begin, end = edge[::2], edge[1::2]
        size = _STEP
        while size < len(part):
            size *= 2
        power, inverse = _powers(_BYTE_BASE, size)
        total = np.zeros(len(part) + 1, dtype=np.uint64)
        np.cumsum((part.astype(np.uint64) + np.uint64(1)) * power[: len(part)], out=total[1:])
        h = (total[end] - total[begin]) * inverse[begin]
        hashes_all.append(mixed(h + (end - begin).astype(np.uint64)))
        starts_all.append(begin + at)
        at = stop
    if not hashes_all:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(hashes_all), np.concatenate(starts_all)


def hashed(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts one behind the other, and words per text."""
    sizes = np.array([len(t) + 1 for t in texts], dtype=np.int64)
    h, starts = word_hashes(np.frombuffer(b" ".join(texts), dtype=np.uint8))
    ends = np.cumsum(sizes)
    return h, np.diff(np.searchsorted(starts, ends, side="left"), prepend=0)


def window_hashes(h: np.ndarray, width: int) -> np.ndarray:
    """Hash of the ``width`` words from each place on (where so many remain)."""
    if len(h) < width:
        return np.zeros(0, dtype=np.uint64)
    size = 1 << max(16, int(len(h)).bit_length())
    power, inverse = _powers(_WORD_BASE, size)
    total = np.zeros(len(h) + 1, dtype=np.uint64)
    np.cumsum(h * power[: len(h)], out=total[1:])
    n = len(h) - width + 1
    return mixed((total[width:] - total[:n]) * inverse[:n])


def document_windows(counts: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of windows that stay inside their text, and the texts' numbers."""
    of = np.repeat(np.arange(len(counts)), counts)
    n = len(of) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.flatnonzero(of[:n] == of[width - 1 :])
    return at, of[at]


# -- packed exchange ------------------------------------------------------


def bucket_edges(keys: np.ndarray, buckets: int, bits: int = 64) -> np.ndarray:
    """Bounds in sorted ``keys`` of equal ranges of the key space."""
    edges = [min((b << bits) // buckets, (1 << bits) - 1) for b in range(1, buckets)]
    inner = np.searchsorted(keys, np.array(edges, dtype=np.uint64), side="left")
    return np.concatenate([[0], inner, [len(keys)]])


def _narrow(x: np.ndarray) -> np.ndarray:
    """Bytes (rows) of unsigned values without the leading ones that are zero
    in all of them, by byte planes so that block compression finds them."""
    width = max(1, (int(x.max()).bit_length() + 7) // 8) if len(x) else 1
    return x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T.copy()


def _wide(raw: bytes, at: int, n: int, width: int) -> np.ndarray:
    out = np.zeros((n, 8), dtype=np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n).T
    return out.view("<u8").ravel()


def packed(columns: list[np.ndarray]) -> bytes:
    """Unsigned columns as one value; the first ascends and is kept as steps."""
    parts = []
    for i, col in enumerate(columns):
        col = col.astype(np.uint64, copy=False)
        planes = _narrow(np.diff(col, prepend=np.uint64(0)) if i == 0 else col)
        parts.append(np.array([len(col), planes.shape[0]], dtype="<u4").tobytes() + planes.tobytes())
    return b"".join(parts)


def unpacked(raw: bytes) -> list[np.ndarray]:
    out, at = [], 0
    while at < len(raw):
        n, width = np.frombuffer(raw, "<u4", 2, at).tolist()
        col = _wide(raw, at + 8, n, width)
        out.append(np.cumsum(col, dtype=np.uint64) if not out else col)
        at += 8 + n * width
    return out


def groups(sorted_keys: np.ndarray) -> np.ndarray:
    """Start of each run of equal keys."""
    if not len(sorted_keys):
        return np.zeros(0, dtype=np.int64)
    return np.flatnonzero(np.concatenate([[True], sorted_keys[1:] != sorted_keys[:-1]]))


def spans(covered: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of True: starts and ends."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], covered.view(np.int8), [0]])))
    return edge[::2], edge[1::2]


def cover(n_words: int, windows: np.ndarray, width: int) -> np.ndarray:
    """Which of n words a window starting at one of ``windows`` covers."""
    step = np.zeros(n_words + 1, dtype=np.int32)
    np.add.at(step, windows, 1)
    np.add.at(step, windows + width, -1)
    return np.cumsum(step[:-1]) > 0
