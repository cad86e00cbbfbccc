"""Hierarchical language identification: family first, then one-versus-one
linear support vector machines between the languages of that family.

Features are relative frequencies of byte n-grams, hashed.  All classifiers
are linear in the counts, so a text's scores are sums over its n-grams of rows
of one weight table: whole texts are scored in bounded steps.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: ISO 639-1 codes by family.  Others are families by themselves.
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af lb fy yi",
    "romance": "fr es it pt ro ca gl oc",
    "slavic": "ru uk be bg mk sr hr bs sl cs sk pl",
    "baltic": "lt lv",
    "uralic": "fi et hu",
    "celtic": "ga gd cy br",
    "turkic": "tr az kk ky uz tk tt",
    "semitic": "ar he mt am",
    "iranian": "fa ps ku tg",
    "indic": "hi ur bn pa mr gu ne si",
    "dravidian": "ta te kn ml",
    "austronesian": "id ms tl jv su mg",
    "sinitic": "zh",
}
_FAMILY = {code: name for name, codes in FAMILIES.items() for code in codes.split()}
ORDERS = (1, 2, 3)
BITS = 12
_LETTER = re.compile(r"[^\W\d_]")
_STEP = 1 << 18


def _has_letter(text: str | None) -> bool:
    return bool(text) and _LETTER.search(text) is not None


def family_of(lang: str) -> str:
    return _FAMILY.get(lang.lower().split("-")[0], lang)


def gram_places(raw: np.ndarray) -> list[np.ndarray]:
    """Feature numbers of the n-grams that start at each byte (A-Z as a-z)."""
    low = raw.astype(np.uint32)
    low = np.where((low >= 65) & (low <= 90), low + 32, low).astype(np.uint32)
    code, out = np.zeros(len(low), dtype=np.uint32), []
    for n in ORDERS:
        m = len(low) - n + 1
        if m <= 0:
            break
        code = (code[:m] << np.uint32(8)) | low[n - 1 :]
        out.append(((code + np.uint32(n)) * np.uint32(2654435761)) >> np.uint32(32 - BITS))
    return out


def frequencies(raw: bytes) -> np.ndarray:
    x = np.zeros(1 << BITS, dtype=np.float32)
    for place in gram_places(np.frombuffer(b" " + raw + b" ", dtype=np.uint8)):
        x += np.bincount(place, minlength=1 << BITS) / len(place)
    return x


def fit_svm(x: np.ndarray, y: np.ndarray, *, c: float = 20.0, steps: int = 150) -> tuple[np.ndarray, float]:
    """Linear machine with squared hinge loss, by accelerated gradient steps.
    ``y`` is 1 or -1; both classes weigh the same."""
    n, d = x.shape
    weight = np.where(y > 0, 0.5 / max((y > 0).sum(), 1), 0.5 / max((y < 0).sum(), 1)).astype(np.float32)
    w, b = np.zeros(d, np.float32), 0.0
    v, vb = w.copy(), b
    rate = 1.0 / (1.0 / c + 2.0 * float((weight * ((x * x).sum(1) + 1)).sum()))
    for k in range(steps):
        slack = np.maximum(0, 1 - y * (x @ v + vb))
        g = -2 * weight * slack * y
        new = v - rate * (x.T @ g + v / c)
        new_b = vb - rate * float(g.sum())
        m = k / (k + 3)
        v, vb = new + m * (new - w), new_b + m * (new_b - b)
        w, b = new, new_b
    return w, b


class Model:
    """One weight table for all machines: families one against the rest, pairs
    of languages inside each family."""

    def __init__(self, x: np.ndarray, langs: list[str]):
        """``x``: n-gram frequencies of the examples, a row each."""
        self.langs = sorted(set(langs))
        self.families = sorted({family_of(x) for x in self.langs})
        members = {f: [x for x in self.langs if family_of(x) == f] for f in self.families}
        lang = np.array(langs)
        fam = np.array([family_of(a) for a in langs])
        scale = 1 / np.sqrt(x.mean(0) + 1e-5) if len(x) else np.ones(1 << BITS, np.float32)
        x = (x * scale).astype(np.float32)
        columns, bias = [], []
        self.family_at: list[int] = []
        self.pairs: dict[str, list[tuple[int, int, int]]] = {}

        def add(rows: np.ndarray, positive: np.ndarray) -> int:
            w, b = fit_svm(x[rows], np.where(positive, 1.0, -1.0).astype(np.float32))
            columns.append(w * scale)
            bias.append(b)
            return len(columns) - 1

        if len(self.families) == 2:
            at = add(np.arange(len(x)), fam == self.families[0])
            columns.append(-columns[at])
            bias.append(-bias[at])
            self.family_at = [at, at + 1]
        elif len(self.families) > 2:
            self.family_at = [add(np.arange(len(x)), fam == f) for f in self.families]
        self.members = members
        for f, names in members.items():
            self.pairs[f] = [
                (i, j, add(rows := np.flatnonzero((lang == a) | (lang == b)), lang[rows] == a))
                for (i, a), (j, b) in combinations(enumerate(names), 2)
            ]
        self.table = np.stack(columns, axis=1).astype(np.float32) if columns else np.zeros((1 << BITS, 1), np.float32)
        self.bias = np.array(bias or [0.0], dtype=np.float32)

    def margins(self, texts: list[bytes]) -> np.ndarray:
        """Scores of all machines for each text."""
        total = np.zeros((len(texts), self.table.shape[1]), dtype=np.float64)
        at = 0
        while at < len(texts):
            part, size = [], 0
            first = at
            while at < len(texts) and (not part or size + len(texts[at]) < _STEP):
                part.append(b" " + texts[at] + b" ")
                size += len(texts[at])
                at += 1
            if len(part) == 1 and size > _STEP:
                total[first] = self._long(part[0])
                continue
            raw = np.frombuffer(b"".join(part), dtype=np.uint8)
            ends = np.cumsum([len(p) for p in part])
            begins = ends - [len(p) for p in part]
            for k, place in enumerate(gram_places(raw)):
                n = ORDERS[k]
                last = np.maximum(ends - n + 1, begins)
                # Sums from each begin to its last gram; the grams between two
                # texts are sums of their own and go unused.
                edges = np.stack([begins, last], axis=1).ravel()
                some = np.flatnonzero(last > begins)
                for m in range(self.table.shape[1]):
                    of = np.append(self.table[:, m][place], np.float32(0))
                    total[first:at][some, m] += np.add.reduceat(of, edges, dtype=np.float64)[::2][some] / (last - begins)[some]
        return total + self.bias

    def _long(self, raw: bytes) -> np.ndarray:
        """The same sums for one long text, in steps that overlap by a gram."""
        arr = np.frombuffer(raw, dtype=np.uint8)
        sums = [np.zeros(self.table.shape[1]) for _ in ORDERS]
        for lo in range(0, len(arr), _STEP):
            for k, n in enumerate(ORDERS):
                places = gram_places(arr[lo : lo + _STEP + n - 1])
                if k < len(places):
                    sums[k] += np.bincount(places[k], minlength=1 << BITS) @ self.table
        return sum(s / max(len(arr) - n + 1, 1) for s, n in zip(sums, ORDERS, strict=True))

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        """Language and score (0 to 1) of each text; ``und`` without a letter."""
        known = [i for i, t in enumerate(texts) if _has_letter(t)]
        lang, score = ["und"] * len(texts), [0.0] * len(texts)
        if not known or not self.langs:
            return lang, score
        margin = self.margins([texts[i].encode("utf-8", "replace") for i in known])
        family = margin[:, self.family_at].argmax(1) if self.family_at else np.zeros(len(known), int)
        sure = 1 / (1 + np.exp(-4 * margin[:, self.family_at].max(1))) if self.family_at else np.ones(len(known))
        for row, (i, f) in enumerate(zip(known, family.tolist(), strict=True)):
            name = self.families[f]
            votes = np.zeros((len(self.members[name]), 2))
            for a, b, m in self.pairs[name]:
                z = margin[row, m]
                votes[a if z > 0 else b, 0] += 1
                votes[a, 1] += z
                votes[b, 1] -= z
            best = max(range(len(votes)), key=lambda k: (votes[k, 0], votes[k, 1]))
            own = min([abs(margin[row, m]) for a, b, m in self.pairs[name] if best in (a, b)], default=None)
            lang[i] = self.members[name][best]
            score[i] = float(sure[row] if own is None else sure[row] / (1 + np.exp(-4 * own)))
        return lang, score


def held_out(id_col: str = "doc_id") -> Column:
    """The fold that training leaves out (a null id: in it)."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(True))


def fit(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_class: int = 120, most: int = 480) -> Model:
    """Fit on a sample of labelled rows outside the held-out fold: about
    ``per_class`` of each language, ``most`` in all but one at least of each.
    Copies of a text count once.  Which texts are in it depends on a hash of
    the text alone, so it is the same on every run.  Each text is an example,
    and so are two cuts of it, since short texts must be told, too.  The driver
    gets the frequencies that are not zero, no texts."""
    labelled = docs.select(
        F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"), held_out(id_col).alias("held_out")
    ).where(r"lang IS NOT NULL AND text RLIKE '\\p{L}' AND NOT held_out").select("lang", "text", F.xxhash64("text").alias("h"))
    # Distinct texts a language, by a small sketch: how deep the draw must go.
    n_texts = {r.lang: r.n for r in labelled.groupBy("lang").agg(F.approx_count_distinct("h").alias("n")).toLocalIterator()}
    langs_seen = len(n_texts)
    each = min(per_class, max(1, most // max(1, langs_seen)))
    # More than are used, since a short text has fewer cuts.
    drawn = each + (each + 1) // 2
    # Only texts under a hash threshold, twice as deep as the draw and 40 texts
    # more, are ranked, so a language of a third of all texts is never in one
    # task, and the smallest draw finds its texts, too.
    spot = F.shiftrightunsigned("h", 11).cast("double") / float(1 << 53)
    depth = [x for lang, n in n_texts.items() for x in (F.lit(lang), F.lit((2.0 * drawn + 40) / max(n, 1)))]
    near = labelled.where(spot < F.create_map(*depth)[F.col("lang")]) if depth else labelled
    place = F.row_number().over(Window.partitionBy("lang").orderBy("h"))
    chosen = near.select("lang", "h").distinct().withColumn("r", place).where(F.col("r") <= drawn).select("lang", "h")
    one = labelled.join(F.broadcast(chosen), ["lang", "h"], "left_semi").dropDuplicates(["lang", "h"])
    # The limit drops nothing: it makes one sorted task of what was drawn.
    rows = one.orderBy("h", "lang").limit(max(1, drawn * langs_seen)).select("lang", "text")
    taken: dict[str, list[np.ndarray]] = {}
    for r in rows.mapInArrow(_examples, "lang string, places binary, x binary").toLocalIterator():
        own = taken.setdefault(r.lang, [])
        if len(own) < 3 * each:
            full = np.zeros(1 << BITS, dtype=np.float32)
            full[np.frombuffer(r.places, dtype=np.uint16)] = np.frombuffer(r.x, dtype=np.float32)
            own.append(full)
    langs = [lang for lang in sorted(taken) for _ in taken[lang]]
    x = [v for lang in sorted(taken) for v in taken[lang]]
    return Model(np.stack(x) if x else np.zeros((0, 1 << BITS), np.float32), langs)


def _examples(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Frequencies of whole texts and of two short cuts of each."""
    for batch in batches:
        langs, places, out = [], [], []
        for i, (lang, text) in enumerate(zip(*(c.to_pylist() for c in batch.columns), strict=True)):
            if not _has_letter(text):
                continue
            words = text.encode("utf-8", "replace").split()
            for lo, hi in ((0, len(words)), (i % 7, i % 7 + 4), (len(words) // 2, len(words) // 2 + 25)):
                if piece := b" ".join(words[lo:hi]):
                    x = frequencies(piece)
                    some = np.flatnonzero(x)
                    langs.append(lang)
                    places.append(some.astype(np.uint16).tobytes())
                    out.append(x[some].tobytes())
        yield pa.RecordBatch.from_pydict(
            {"lang": pa.array(langs, pa.string()), "places": pa.array(places, pa.binary()), "x": pa.array(out, pa.binary())}
        )


def identify(docs: DataFrame, model: Model, *, text_col: str = "text") -> DataFrame:
    """``row`` (all input columns) with lang_pred and score.  Only the text is
    looked at.  Null texts and texts without a letter are ``und`` with score
    0; null ids and repeated rows pass through; an empty table gives none."""
    spark, columns = docs.sparkSession, docs.columns
    shared = spark.sparkContext.broadcast(model)
    at = columns.index(text_col)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("row"))
    schema = f"row {rows.schema['row'].dataType.simpleString()}, lang_pred string, score double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for whole in batches:
            for lo in range(0, whole.num_rows, 1024):
                row = whole.column(0).slice(lo, 1024)
                lang, score = m.predict(row.field(at).cast(pa.string()).to_pylist())
                yield pa.RecordBatch.from_pydict({"row": row, "lang_pred": lang, "score": pa.array(score, pa.float64())})

    return rows.mapInArrow(run, schema)
