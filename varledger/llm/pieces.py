"""Encoding and decoding with a SentencePiece BPE model by vectorised merges.

A text is cut where a space follows something else; no piece of such a model
crosses that place, so each cut word merges by itself and distinct words are
encoded once per worker.  All new words of a batch lie in one flat symbol
array.  Every round finds the best pair of each word (segmented minimum of
pair ranks), merges its leftmost occurrences in all words at once and compacts
the arrays, until no word has a pair left.

A round takes every occurrence of a word's best pair that does not overlap one
further left.  That is the order of one merge at a time as long as no pair
that a merge makes is at least as good as the merge itself; the model's few
pieces of which this is not so are merged one occurrence a round.  Words of
over ``LONG`` symbols are first cut between characters that no piece holds
side by side, where no merge can cross.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"
LONG = 96
MEMO_ENTRIES, MEMO_CHARS = 250_000, 64
_NONE = np.iinfo(np.int32).max


class PieceModel:
    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        with open(path, "rb") as f:
            proto.ParseFromString(f.read())
        norm, trained = proto.normalizer_spec, proto.trainer_spec
        kinds = pb.ModelProto.SentencePiece
        if trained.model_type != trained.BPE or not trained.byte_fallback or trained.treat_whitespace_as_suffix:
            raise ValueError("a BPE model with byte fallback and leading space marks is needed")
        if norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.escape_whitespaces:
            raise ValueError("only the identity normaliser is supported")
        if any(p.type in (kinds.USER_DEFINED, kinds.UNUSED) for p in proto.pieces):
            raise ValueError("user-defined and unused pieces are not supported")
        self.dummy = norm.add_dummy_prefix
        self.end_id = trained.eos_id
        self.text = [p.piece for p in proto.pieces]
        self.kind = [p.type for p in proto.pieces]
        self.is_byte = np.array([k == kinds.BYTE for k in self.kind])
        self.byte_id = {int(p.piece[1:-1], 16): i for i, p in enumerate(proto.pieces) if p.type == kinds.BYTE}
        self.byte_of = {i: b for b, i in self.byte_id.items()}
        self.silent = {i for i, k in enumerate(self.kind) if k == kinds.CONTROL}
        self.unknown = {i for i, k in enumerate(self.kind) if k == kinds.UNKNOWN}
        self.unk_surface = trained.unk_surface
        self.id = {p.piece: i for i, p in enumerate(proto.pieces) if p.type == kinds.NORMAL}
        if any(SPACE in p.lstrip(SPACE) for p in self.id):
            raise ValueError("a piece holds a space mark after other characters")
        # Rank of a merge: place of its score, best first; equal scores tie and
        # then the leftmost pair goes first.
        scores = np.array([p.score for p in proto.pieces], dtype=np.float32)
        rank = np.unique(-scores, return_inverse=True)[1].astype(np.int32)
        v = self.size = len(self.text)
        pairs = {}
        for piece, i in self.id.items():
            for cut in range(1, len(piece)):
                left, right = self.id.get(piece[:cut]), self.id.get(piece[cut:])
                if left is not None and right is not None:
                    pairs[left * v + right] = i
                elif (cut == 1 and left is None) or (cut == len(piece) - 1 and right is None):
                    raise ValueError("a character of a piece is no piece itself")
        self.pair_key = np.array(sorted(pairs), dtype=np.int64)
        self.pair_id = np.array([pairs[k] for k in self.pair_key.tolist()], dtype=np.int32)
        self.pair_rank = rank[self.pair_id]
        # Pieces that some pair as good as their own merge can take up.
        self.eager = np.zeros(v, dtype=bool)
        for side in (self.pair_key // v, self.pair_key % v):
            self.eager[side[self.pair_rank <= rank[side]]] = True
        beside = {(ord(a) << 32) | ord(b) for p in self.id for a, b in zip(p, p[1:], strict=False)}
        self.beside = np.array(sorted(beside), dtype=np.int64)
        top = max((ord(p) for p in self.id if len(p) == 1), default=0)
        self.char_id = np.full(top + 2, -1, dtype=np.int32)
        for p, i in self.id.items():
            if len(p) == 1:
                self.char_id[ord(p)] = i
        self.memo: dict[str, str] = {}
        self.odd: dict[str, str] = {}  # words whose ids do not decode to themselves

    # -- encoding ---------------------------------------------------------

    def _symbols(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Codes, ids (unknown characters: -1 - code) and lengths of words."""
        code = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.int64)
        known = self.char_id[np.minimum(code, len(self.char_id) - 1)].astype(np.int64)
        return np.where(known >= 0, known, -1 - code), np.array([len(w) for w in words])

    def _look_up(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = left * self.size + right
        at = np.minimum(np.searchsorted(self.pair_key, key), len(self.pair_key) - 1)
        hit = (self.pair_key[at] == key) & (left >= 0) & (right >= 0)
        return np.where(hit, self.pair_rank[at], _NONE), np.where(hit, self.pair_id[at], -1)

    def merge_rounds(self, words: list[str]) -> list[np.ndarray]:
        """Final symbols of each word (none empty), by rounds over all words."""
        sym, length = self._symbols(words)
        out: list[np.ndarray] = [None] * len(words)  # type: ignore[list-item]
        owner = np.arange(len(words))
        start = np.concatenate([[0], np.cumsum(length)[:-1]])
        rank = np.full(len(sym), _NONE, dtype=np.int32)
        made = np.full(len(sym), -1, dtype=np.int64)
        if len(sym) > 1:
            rank[:-1], made[:-1] = self._look_up(sym[:-1], sym[1:])
        rank[start + length - 1] = _NONE
        while len(owner):
            best = np.minimum.reduceat(rank, start)
            done = best == _NONE
            if done.any():
                for k in np.flatnonzero(done):
                    out[owner[k]] = sym[start[k] : start[k] + length[k]]
                stay = np.repeat(~done, length)
                sym, rank, made = sym[stay], rank[stay], made[stay]
                owner, length, best = owner[~done], length[~done], best[~done]
                if not len(owner):
                    break
                start = np.concatenate([[0], np.cumsum(length)[:-1]])
            hit = np.flatnonzero(rank == np.repeat(best, length))
            seg = np.searchsorted(start, hit, side="right") - 1
            head = np.concatenate([[True], seg[1:] != seg[:-1]])
            # Of hits side by side every other one, from the left.
            run = np.concatenate([[True], hit[1:] != hit[:-1] + 1]) | head
            place = np.arange(len(hit))
            free = (place - np.maximum.accumulate(np.where(run, place, 0))) % 2 == 0
            lone = np.bincount(seg, self.eager[made[hit]], minlength=len(owner)) > 0
            first = free & (head | ~lone[seg])
            hit, seg = hit[first], seg[first]
            sym[hit] = made[hit]
            keep = np.ones(len(sym), dtype=bool)
            keep[hit + 1] = False
            at = hit - np.arange(len(hit))  # places of the merged symbols after compaction
            sym, rank, made = sym[keep], rank[keep], made[keep]
            length = length - np.bincount(seg, minlength=len(length))
            start = np.concatenate([[0], np.cumsum(length)[:-1]])
            begin, last = start[seg], start[seg] + length[seg] - 1
            rank[at], made[at] = _NONE, -1
            for changed in (at[at != last], at[at != begin] - 1):
                rank[changed], made[changed] = self._look_up(sym[changed], sym[changed + 1])
        return out

    def cuts(self, word: str) -> list[str]:
        """Parts of a word between which no piece can lie."""
        code = np.frombuffer(word.encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.int64)
        key = (code[:-1] << 32) | code[1:]
        at = np.minimum(np.searchsorted(self.beside, key), len(self.beside) - 1)
        edges = [0, *(np.flatnonzero(self.beside[at] != key) + 1).tolist(), len(word)]
        return [word[lo:hi] for lo, hi in zip(edges, edges[1:], strict=False)]

    def _ids(self, sym: np.ndarray) -> list[int]:
        if (sym >= 0).all():
            return sym.tolist()
        out: list[int] = []
        for s in sym.tolist():
            if s >= 0:
                out.append(s)
            else:
                out += [self.byte_id[b] for b in chr(-1 - s).encode("utf-8", "replace")]
        return out

    def split(self, text: str) -> list[str]:
        """Words with their space marks written as spaces."""
        if not text:
            return []
        marked = (" " if self.dummy else "") + text.replace(SPACE, " ")
        parts = marked.split(" ")
        words = [parts[0]] if parts[0] else []
        if "" not in parts[1:]:
            return words + [" " + p for p in parts[1:]]
        marks = 0
        for p in parts[1:]:
            marks += 1
            if p:
                words.append(" " * marks + p)
                marks = 0
        return words + [" " * marks] if marks else words

    def learn(self, words: set[str]) -> dict[str, str]:
        """Encode new words; those too long for the memo are returned."""
        own: dict[str, str] = {}
        many = list(words)
        for lo in range(0, len(many), 50_000):
            part = many[lo : lo + 50_000]
            marked = [w.replace(" ", SPACE) for w in part]
            split = {k: self.cuts(w) for k, w in enumerate(marked) if len(w) > LONG}
            merged = iter(self.merge_rounds([x for k, w in enumerate(marked) for x in split.get(k, (w,))]))
            for k, w in enumerate(part):
                sym = next(merged) if k not in split else np.concatenate([next(merged) for _ in split[k]])
                self._store(w, self._ids(sym), own)
        return own

    def _store(self, word: str, ids: list[int], own: dict[str, str]) -> None:
        (self.memo if len(word) <= MEMO_CHARS else own)[word] = " ".join(map(str, ids))
        back = self.surface(ids)
        if back != word:
            self.odd[word] = back

    def encode_strings(self, texts: list[str]) -> list[tuple[str, str]]:
        """For each text its ids in decimal, joined by spaces, and its decoding."""
        if len(self.memo) > MEMO_ENTRIES:
            self.memo.clear()
            self.odd.clear()
        split = [self.split(t) for t in texts]
        own = self.learn({w for words in split for w in words if w not in self.memo})
        out = []
        for words in split:
            ids = " ".join([self.memo[w] if w in self.memo else own[w] for w in words])
            back = "".join([self.odd.get(w, w) for w in words]) if self.odd else "".join(words)
            out.append((ids, back[1:] if self.dummy and back[:1] == " " else back))
        return out

    def encode(self, text: str) -> list[int]:
        return [int(x) for x in self.encode_strings([text])[0][0].split()]

    # -- decoding ---------------------------------------------------------

    def surface(self, ids: list[int]) -> str:
        """Text of ids with space marks as spaces and nothing stripped.  Runs of
        byte pieces decode together; an invalid byte is one U+FFFD each."""
        out, run = [], bytearray()
        for i in ids:
            if i in self.byte_of:
                run.append(self.byte_of[i])
                continue
            if run:
                out.append(_utf8(bytes(run)))
                run.clear()
            if i in self.unknown:
                out.append(self.unk_surface)
            elif i not in self.silent:
                out.append(self.text[i].replace(SPACE, " "))
        if run:
            out.append(_utf8(bytes(run)))
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        """Text of ids; the space mark that encoding puts in front goes, and only
        if the first piece carries it."""
        back = self.surface(ids)
        first = next((i for i in ids if i not in self.silent), None)
        marked = first is not None and first not in self.unknown and self.text[first].startswith(SPACE)
        return back[1:] if self.dummy and marked else back


def _utf8(raw: bytes) -> str:
    try:
        return raw.decode("utf-8")
    except UnicodeDecodeError:
        out, at = [], 0
        while at < len(raw):
            for n in (1, 2, 3, 4):
                try:
                    out.append(raw[at : at + n].decode("utf-8"))
                    at += n
                    break
                except UnicodeDecodeError:
                    continue
            else:
                out.append("�")
                at += 1
        return "".join(out)


@lru_cache(maxsize=2)
def model(path: str) -> PieceModel:
    return PieceModel(path)


def encode_pieces(
    docs: DataFrame, *, model_path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False
) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids, decoded) of each row.

    The end id closes every document and decodes to nothing.  Null or empty
    text has that id alone.  Null ids and repeated rows pass through, an empty
    table gives no rows and other columns are not read.
    """
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    if with_ids:
        schema += ", ids array<int>, decoded string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(model_path)
        for whole in batches:
            for lo in range(0, whole.num_rows, 1024):
                batch = whole.slice(lo, 1024)
                n, sha, back_sha, all_ids, backs = [], [], [], [], []
                for ids, back in m.encode_strings([t or "" for t in batch.column(1).to_pylist()]):
                    line = f"{ids} {m.end_id}" if ids else str(m.end_id)
                    n.append(line.count(" ") + 1)
                    sha.append(hashlib.sha256(line.encode()).hexdigest())
                    back_sha.append(hashlib.sha256(back.encode("utf-8", "surrogatepass")).hexdigest())
                    if with_ids:
                        all_ids.append([int(x) for x in line.split(" ")])
                        backs.append(back)
                cols = {"doc_id": batch.column(0), "n_tokens": pa.array(n, pa.int64()), "ids_sha256": sha, "decoded_sha256": back_sha}
                if with_ids:
                    cols |= {"ids": pa.array(all_ids, pa.list_(pa.int32())), "decoded": backs}
                yield pa.RecordBatch.from_pydict(cols)

    return docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string")).mapInArrow(run, schema)


def decode_pieces(df: DataFrame, *, model_path: str, ids_col: str = "ids", key_cols: list[str]) -> DataFrame:
    """``key_cols`` and ``decoded``: the text of an array of ids (null: null)."""
    schema = ", ".join(f"{c} {df.schema[c].dataType.simpleString()}" for c in key_cols) + ", decoded string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(model_path)
        for batch in batches:
            back = [None if ids is None else m.decode(ids) for ids in batch.column(len(key_cols)).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:-1], pa.array(back, pa.string())], names=[*key_cols, "decoded"]
            )

    return df.select(*key_cols, ids_col).mapInArrow(run, schema)
