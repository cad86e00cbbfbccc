"""Exact n-gram Jaccard join and its components, by T-occurrence search.

1. Documents become sets of shingle hashes; equal sets are one set from here
   on (its id is a hash of the sorted set).
2. One packed exchange counts in how many sets each shingle occurs (equal sets
   of different tasks count apart, which only adds candidates); sets get back
   the shingles that some other set has, with those counts.  A set of
   which less than the threshold is shared has no partner and leaves.
3. Of the others, the rarest shingles that any partner must touch (prefix in
   the global order of count, then hash) tie sets to blocks; no link leaves a
   block.  The smaller set of a link has such a shingle in a shorter prefix,
   so a shingle ties only sets whose sizes fit one that holds it there.
4. Inside blocks the DivideSkip search finds the links: short inverted lists
   are merged and counted, the long ones are probed by binary search for the
   candidates only, and candidates of the searcher's component are left out,
   so a family of copies costs few searches.
5. Blocks beyond ``slice_sets`` are dealt in slices of sets with a common
   smallest hash, so copies mostly meet, and all slices share a few central
   sets (hubs).  Sets that the first hub reaches are settled; each of the
   others is a query against those slices of its block that hold one of its
   prefix shingles, which keeps all links.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import exchange_size, written
from .components import connected_components
from .windows import bucket_edges, document_windows, groups, hashed, mixed, packed, unpacked, window_hashes

#: Bits of a shingle's hash that travel.  Two shingles of one pair of documents
#: that differ agree in them with a chance of 2**-48.
BITS = 48
CHUNK_WORDS = 400_000
_MASK = np.uint64((1 << BITS) - 1)
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def shingle_sets(texts: list[bytes], width: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text (A-Z taken as a-z)."""
    h, counts = hashed([t.translate(_LOWER) for t in texts])
    at, doc = document_windows(counts, width)
    key = window_hashes(h, width)[at] & _MASK
    edges = np.searchsorted(doc, np.arange(len(texts) + 1))
    offset = np.cumsum(counts) - counts
    out = []
    for i, n in enumerate(counts.tolist()):
        if n >= width:
            out.append(np.unique(key[edges[i] : edges[i + 1]]))
        elif n:  # the whole sequence is the one shingle; its length is part of it
            short = window_hashes(h[offset[i] : offset[i] + n], n) + np.uint64(n)
            out.append(mixed(short) & _MASK)
        else:
            out.append(np.zeros(0, dtype=np.uint64))
    return out


def set_id(keys: np.ndarray) -> int:
    """Signed 64-bit id of a set."""
    return xxhash.xxh3_64_intdigest(keys.tobytes()) - (1 << 63)


def required(n: int, percent: int) -> int:
    """Least overlap of a set of n with any partner: ceil(n * percent / 100)."""
    return -(-n * percent // 100)


def required_of_smaller(n: int, percent: int) -> int:
    """Least overlap of a set of n with a partner that is not smaller."""
    return -(-2 * n * percent // (100 + percent))


def document_sets(docs: DataFrame, *, id_col: str, text_col: str, width: int) -> DataFrame:
    """doc_id, n_shingles, sid (null for an empty set) and mark (a hash of the
    text) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 512):
                batch = whole.slice(lo, 512)
                sets = shingle_sets([t or b"" for t in batch.column(1).cast(pa.binary()).to_pylist()], width)
                yield pa.RecordBatch.from_pydict(
                    {
                        "doc_id": batch.column(0),
                        "n_shingles": pa.array([len(s) for s in sets], pa.int64()),
                        "sid": pa.array([set_id(s) if len(s) else None for s in sets], pa.int64()),
                        "mark": batch.column(2),
                    }
                )

    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).cast("long"), text, F.xxhash64(text))
    return rows.mapInArrow(run, "doc_id long, n_shingles long, sid long, mark long")


def _postings(width: int, buckets: int, spread: int):
    """Rows (place, chunk, data).  Places below ``buckets`` hold the shingles of
    a hash range with the number of their set in the chunk; the others, one a
    chunk, the ids and sizes behind the numbers.  Equal sets of a chunk are one.
    """

    def emit(chunk: int, sets: dict[int, np.ndarray]) -> pa.RecordBatch:
        sids = np.array(list(sets), dtype=np.int64)
        size = np.array([len(s) for s in sets.values()])
        key = np.concatenate(list(sets.values()))
        own = np.repeat(np.arange(len(sids)), size)
        by = np.argsort(key)
        key, own = key[by], own[by]
        edges = bucket_edges(key, buckets, BITS)
        places, data = [buckets + chunk % spread], [packed([np.arange(len(sids)), sids.view(np.uint64), size])]
        for b in np.flatnonzero(np.diff(edges)).tolist():
            places.append(b)
            data.append(packed([key[edges[b] : edges[b + 1]], own[edges[b] : edges[b + 1]]]))
        return pa.RecordBatch.from_pydict(
            {
                "place": pa.array(places, pa.int64()),
                "chunk": pa.array([chunk] * len(places), pa.int64()),
                "data": pa.array(data, pa.binary()),
            }
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets: dict[int, np.ndarray] = {}
        held, chunk = 0, TaskContext.get().partitionId() << 24
        for whole in batches:
            for lo in range(0, whole.num_rows, 512):
                texts = [t or b"" for t in whole.column(0).slice(lo, 512).cast(pa.binary()).to_pylist()]
                for s in shingle_sets(texts, width):
                    if len(s) and (sid := set_id(s)) not in sets:
                        sets[sid] = s
                        held += len(s)
                if held >= CHUNK_WORDS:
                    yield emit(chunk, sets)
                    sets, held, chunk = {}, 0, chunk + 1
        if sets:
            yield emit(chunk, sets)

    return run


def _share(buckets: int):
    """Of one hash range: the shingles in two sets or more, for their chunks."""

    def run(table: pa.Table) -> pa.Table:
        chunks, data = table.column("chunk").to_pylist(), table.column("data").to_pylist()
        if table.column("place")[0].as_py() >= buckets:
            return pa.table({"chunk": pa.array(chunks, pa.int64()), "ids": pa.array(data, pa.binary()), "shared": pa.array([None] * len(data), pa.binary())})
        cols = [unpacked(raw) for raw in data]
        del data
        key = np.concatenate([c[0] for c in cols])
        own = np.concatenate([c[1] for c in cols])
        of = np.repeat(np.arange(len(cols)), [len(c[0]) for c in cols])
        del cols
        by = np.argsort(key)
        key, own, of = key[by], own[by], of[by]
        n = np.diff(np.append(groups(key), len(key)))
        df = np.repeat(n, n)
        more = df > 1
        key, own, of, df = key[more], own[more], of[more], df[more]
        by = np.lexsort((own, of))
        key, own, of, df = key[by], own[by], of[by], df[by]
        edges = np.append(groups(of), len(of)).tolist()
        out = [(chunks[of[lo]], packed([own[lo:hi], key[lo:hi], df[lo:hi]])) for lo, hi in zip(edges[:-1], edges[1:], strict=True)]
        return pa.table(
            {
                "chunk": pa.array([o[0] for o in out], pa.int64()),
                "ids": pa.array([None] * len(out), pa.binary()),
                "shared": pa.array([o[1] for o in out], pa.binary()),
            }
        )

    return run


def _candidates(percent: int):
    """Of one chunk: sets that may have a partner, with their shared shingles
    sorted, their prefix, how many of it are in the shorter prefix, their
    smallest hash and how common their shingles are."""

    def run(table: pa.Table) -> pa.Table:
        _, ids, n_of = unpacked(next(x for x in table.column("ids").to_pylist() if x is not None))
        parts = [unpacked(x) for x in table.column("shared").to_pylist() if x is not None]
        own, key, df = (np.concatenate(c) for c in zip(*parts, strict=True)) if parts else (np.zeros(0, np.uint64),) * 3
        by = np.lexsort((key, df, own))
        own, key, df = own[by].astype(np.int64), key[by], df[by].astype(np.int64)
        edges = np.append(groups(own), len(own))
        sids, sizes, keys, prefixes, shorter, lowest, common = [], [], [], [], [], [], []
        for lo, hi in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
            n = int(n_of[own[lo]])
            least = required(n, percent)
            if hi - lo < least:
                continue
            sids.append(int(ids[own[lo]].astype(np.int64)))
            sizes.append(n)
            # Shingles that no other set has come first in the order; they use
            # up the prefix before the shared ones.
            touch = n - least + 1 - (n - (hi - lo))
            prefixes.append(key[lo : lo + touch].astype(np.int64).tolist())
            shorter.append(touch + least - required_of_smaller(n, percent))
            lowest.append(int(key[lo:hi].min()))
            keys.append(np.sort(key[lo:hi]).astype("<u8").tobytes())
            common.append(float(np.log1p(df[lo:hi]).sum() / n))
        return pa.table(
            {
                "sid": pa.array(sids, pa.int64()),
                "n": pa.array(sizes, pa.int64()),
                "keys": pa.array(keys, pa.binary()),
                "prefix": pa.array(prefixes, pa.list_(pa.int64())),
                "shorter": pa.array(shorter, pa.int64()),
                "lowest": pa.array(lowest, pa.int64()),
                "common": pa.array(common, pa.float64()),
            }
        )

    return run


# -- search inside a block ------------------------------------------------


class SetIndex:
    """Inverted lists over sets of keys, and T-occurrence search in them."""

    #: Weight of a probe against a merge step in the choice of long lists.
    PROBE = 0.01

    def __init__(self, sets: list[np.ndarray]):
        size = np.array([len(s) for s in sets])
        key = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
        own = np.repeat(np.arange(len(sets)), size)
        by = np.lexsort((own, key))
        self.own = own[by]
        key = key[by]
        first = groups(key)
        self.key, self.at = key[first], np.append(first, len(key))
        self.count = len(sets)

    def search(self, keys: np.ndarray, least: int, allowed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Allowed sets with at least ``least`` of ``keys``, and their overlaps."""
        place = np.searchsorted(self.key, keys)
        inside = place < len(self.key)
        place, keys = place[inside], keys[inside]
        lists = place[self.key[place] == keys]
        if len(lists) < least:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        length = self.at[lists + 1] - self.at[lists]
        by = np.argsort(-length, kind="stable")
        lists, length = lists[by], length[by]
        longest = int(length[0])
        long = min(least - 1, int(least / (self.PROBE * math.log2(longest + 1) + 1)))
        # Short lists: one counted merge.  A result is in least - long of them.
        short = [self.own[self.at[i] : self.at[i + 1]] for i in lists[long:].tolist()]
        seen = np.bincount(np.concatenate(short), minlength=self.count) if short else np.zeros(self.count, np.int64)
        found = np.flatnonzero((seen >= least - long) & allowed)
        overlap = seen[found]
        # Long lists: binary probes, dropping what can no longer get there.
        left = long
        for i in lists[:long].tolist():
            if not len(found):
                break
            one = self.own[self.at[i] : self.at[i + 1]]
            spot = np.minimum(np.searchsorted(one, found), len(one) - 1)
            overlap = overlap + (one[spot] == found)
            left -= 1
            stay = overlap + left >= least
            found, overlap = found[stay], overlap[stay]
        return found, overlap


class Union:
    def __init__(self, n: int):
        self.label = np.arange(n)

    def join(self, a: int, others: np.ndarray) -> None:
        old = np.unique(np.append(self.label[others], self.label[a]))
        self.label[np.isin(self.label, old)] = old[0]


def link_all(sets: list[np.ndarray], n: np.ndarray, percent: int, first: list[int], union: Union, queries=None) -> None:
    """Join in ``union`` the sets that are linked.  A set is put off while it is
    in the largest component, and its turn comes again until all sets without a
    search are in one component: a link between components then has a searched
    end.  Those in ``first`` are not put off and go before the others;
    ``queries`` restricts searches to its sets, all of which are made."""
    index = SetIndex(sets)
    ahead = set(first)
    todo = first + [i for i in (range(len(sets)) if queries is None else queries) if i not in ahead]
    at_once = len(first) if queries is None else len(todo)
    while len(np.unique(union.label[todo])) > 1 or at_once:
        later = []
        for done, q in enumerate(todo):
            label, size = np.unique(union.label, return_counts=True)
            if len(label) == 1:
                return
            if done >= at_once and union.label[q] == label[np.argmax(size)]:
                later.append(q)
                continue
            least = required(int(n[q]), percent)
            near = (n * 100 >= n[q] * percent) & (n * percent <= n[q] * 100) & (union.label != union.label[q])
            if not near.any():
                continue
            found, overlap = index.search(sets[q], least, near)
            hit = found[100 * overlap >= percent * (n[q] + n[found] - overlap)]
            if len(hit):
                union.join(q, hit)
        todo, at_once = later, 0


def _block(percent: int):
    """Of one slice: sid, label (the smallest sid it reaches here), and whether
    the block's first hub reaches it.  Only one component may count as settled,
    since sets that are settled are not asked about each other again."""

    def run(table: pa.Table) -> pa.Table:
        sid = np.array(table.column("sid").to_pylist(), dtype=np.int64)
        hub = np.array(table.column("hub").to_pylist(), dtype=np.int64)
        by = np.lexsort((sid, np.where(hub > 0, hub, 1 << 30)))
        n = np.array(table.column("n").to_pylist(), dtype=np.int64)[by]
        keys = table.column("keys").to_pylist()
        sets = [np.frombuffer(keys[i], dtype="<u8") for i in by.tolist()]
        sid, hub = sid[by], hub[by]
        union = Union(len(sid))
        link_all(sets, n, percent, list(range(int((hub > 0).sum()))), union)
        low: dict[int, int] = {}
        for s, c in zip(sid.tolist(), union.label.tolist(), strict=True):
            low[c] = min(s, low.get(c, s))
        reached = union.label == union.label[0] if hub[0] == 1 else np.ones(len(sid), bool)
        block = table.column("block")[0].as_py()
        return pa.table(
            {
                "sid": pa.array(sid),
                "label": pa.array([low[c] for c in union.label.tolist()], pa.int64()),
                "block": pa.array([block] * len(sid), pa.int64()),
                "settled": pa.array(reached),
            }
        )

    return run


def _tile(percent: int):
    """Queries of one part of a block against one slice of it: linked pairs."""

    def run(table: pa.Table) -> pa.Table:
        sid = np.array(table.column("sid").to_pylist(), dtype=np.int64)
        asks = np.array(table.column("asks").to_pylist(), dtype=bool)
        n = np.array(table.column("n").to_pylist(), dtype=np.int64)
        label = np.unique(np.array(table.column("label").to_pylist(), dtype=np.int64), return_inverse=True)[1]
        sets = [np.frombuffer(k, dtype="<u8") for k in table.column("keys").to_pylist()]
        union = Union(len(sid))
        for i in np.unique(label):  # what the first pass has linked is linked
            same = np.flatnonzero(label == i)
            union.join(int(same[0]), same)
        link_all(sets, n, percent, [], union, queries=np.flatnonzero(asks).tolist())
        first = {}
        for s, c in zip(sid.tolist(), union.label.tolist(), strict=True):
            first.setdefault(c, s)
        return pa.table({"a": pa.array(sid), "b": pa.array([first[c] for c in union.label.tolist()], pa.int64())})

    return run


def _tokens(sets: DataFrame) -> DataFrame:
    """sid, n, token, short of every prefix shingle; ``short`` where it is in
    the prefix that a partner of at least the set's size must touch."""
    return sets.select("sid", "n", "shorter", F.posexplode("prefix").alias("at", "token")).select(
        "sid", "n", "token", (F.col("at") < F.col("shorter")).alias("short")
    )


def _ties(sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that connect the sets of each prefix shingle, where sizes fit."""
    token = _tokens(sets)
    held = token.groupBy("token").agg(
        F.min(F.when(F.col("short"), F.col("sid"))).alias("low"),
        F.min(F.when(F.col("short"), F.col("n"))).alias("least"),
        F.max(F.when(F.col("short"), F.col("n"))).alias("most"),
        F.count("*").alias("count"),
    ).where("count > 1 AND low IS NOT NULL")
    fits = F.col("short") | ((F.col("n") >= F.col("least")) & (F.col("n") * percent <= F.col("most") * 100))
    return (
        token.join(held, "token").where((F.col("sid") != F.col("low")) & fits)
        .select(F.col("sid").alias("a"), F.col("low").alias("b")).distinct()
    )


def _hubs(big: DataFrame, hubs: int) -> DataFrame:
    """hub_sid, block, hub (from 1): of a block the sets with the commonest
    shingles, each the best of an equal share, found by partial aggregates."""
    share = F.pmod(F.xxhash64("sid", F.lit(2)), F.lit(hubs))
    best = big.groupBy("block", share.alias("share")).agg(F.max(F.struct("common", "sid")).alias("top"))
    rank = F.row_number().over(Window.partitionBy("block").orderBy(F.desc("top.common"), F.desc("top.sid")))
    return best.select(F.col("top.sid").alias("hub_sid"), "block", rank.alias("hub"))


def set_links(sets: DataFrame, *, percent: int, slice_sets: int = 256, hubs: int = 4) -> DataFrame:
    """Edges (a, b) of set ids whose components are those of all links, from
    candidate sets (sid, n, keys, prefix, shorter, lowest, common)."""
    blocks = connected_components(_ties(sets, percent)).select(F.col("node").alias("sid"), F.col("component").alias("block"))
    members = written(sets.select("sid", "n", "keys", "lowest", "common").join(blocks, "sid"), "jaccard-blocks")
    size = members.groupBy("block").agg(F.count("*").alias("size"))
    large = written(
        size.where(F.col("size") > slice_sets).withColumn("slices", F.ceil(F.col("size") / slice_sets).cast("long")),
        "jaccard-large",
    )
    nothing = F.lit(0).cast("long")
    whole = members.join(large.select("block"), "block", "left_anti").select(
        "sid", "n", "keys", "block", nothing.alias("slice"), F.lit(0).alias("hub")
    )
    schema = "sid long, label long, block long, settled boolean"
    if large.isEmpty():
        found = whole.groupBy("block", "slice").applyInArrow(_block(percent), schema)
        return written(found.select(F.col("sid").alias("a"), F.col("label").alias("b")).where("a <> b"), "jaccard-links")

    # Slices of a large block: by the smallest hash, and a hash of the id where
    # too many sets share one.
    kind = F.pmod(F.xxhash64("lowest"), F.col("slices"))
    dealt = members.join(large, "block").withColumn("kind", kind)
    crowd = dealt.groupBy("block", "kind").agg(F.ceil(F.count("*") / slice_sets).cast("long").alias("ways"))
    big = written(
        dealt.join(crowd, ["block", "kind"]).withColumn(
            "slice", F.col("kind") * F.lit(1 << 24) + F.pmod(F.xxhash64("sid"), F.col("ways"))
        ).drop("kind", "ways", "slices", "size"),
        "jaccard-slices",
    )
    best = written(_hubs(big, hubs), "jaccard-hubs")
    hub_rows = (
        big.join(best.withColumnRenamed("block", "hub_block"), F.col("sid") == F.col("hub_sid"))
        .select("sid", "n", "keys", "block", "hub")
        .join(big.select("block", "slice").distinct(), "block")
        .select("sid", "n", "keys", "block", "slice", "hub")
    )
    sliced = big.join(best.select(F.col("hub_sid").alias("sid")), "sid", "left_anti").select(
        "sid", "n", "keys", "block", "slice", F.lit(0).alias("hub")
    )
    first = written(
        # Dealt by slice: rows that come together by block would stay together.
        whole.union(sliced).union(hub_rows).repartition("block", "slice").groupBy("block", "slice").applyInArrow(
            _block(percent), schema
        ),
        "jaccard-labels",
    )
    edges = first.select(F.col("sid").alias("a"), F.col("label").alias("b")).where("a <> b")

    # Second pass, for large blocks only: queries that the first hub does not reach.
    asking = written(first.where("NOT settled").select("sid").distinct(), "jaccard-asking")
    if asking.isEmpty():
        return written(edges, "jaccard-links")
    token = _tokens(sets).join(big.select("sid", "block", "slice"), "sid")
    held = token.groupBy("block", "token", "slice").agg(F.bool_or("short").alias("held_short"))
    visits = written(
        token.join(asking, "sid", "left_semi")
        .select("sid", "block", "token", "short", F.col("slice").alias("own"))
        .join(held, ["block", "token"])
        .where("slice <> own AND (short OR held_short)")
        .select("sid", "block", "slice")
        .distinct(),
        "jaccard-visits",
    )
    parts = visits.groupBy("block", "slice").agg(F.ceil(F.count("*") / slice_sets).cast("long").alias("parts"))
    labelled = big.join(first.groupBy("sid").agg(F.min("label").alias("label")), "sid").select(
        "sid", "n", "keys", "block", "slice", "label"
    )
    cols = ["sid", "n", "keys", "block", "label", "part", "slice", "asks"]
    asked = labelled.join(parts, ["block", "slice"]).withColumn(
        "part", F.explode(F.sequence(nothing, F.col("parts") - 1))
    ).withColumn("asks", F.lit(False)).select(cols)
    asks = (
        visits.join(labelled.drop("block", "slice"), "sid").join(parts, ["block", "slice"])
        .withColumn("part", F.pmod(F.xxhash64("sid", F.lit(1)), F.col("parts")).cast("long"))
        .withColumn("asks", F.lit(True)).select(cols)
    )
    more = asked.union(asks).repartition("block", "part", "slice").groupBy("block", "part", "slice").applyInArrow(_tile(percent), "a long, b long")
    return written(edges.union(more.where("a <> b")), "jaccard-links")


def _placed(docs: DataFrame, *, id_col: str, text_col: str, width: int, percent: int, buckets: int | None, slice_sets: int) -> DataFrame:
    """doc_id, mark, n_shingles and component (null for an empty set) of every row."""
    rows = written(document_sets(docs, id_col=id_col, text_col=text_col, width=width), "jaccard-sets")
    # About six bytes of text to a shingle.
    ranges, tasks = exchange_size(rows.agg(F.sum("n_shingles") * 6))
    buckets = buckets or ranges
    posts = docs.select(F.col(text_col).cast("string")).mapInArrow(
        _postings(width, buckets, tasks), "place long, chunk long, data binary"
    )
    shared = posts.repartition(tasks, "place").groupBy("place").applyInArrow(
        _share(buckets), "chunk long, ids binary, shared binary"
    )
    found = shared.repartition(tasks, "chunk").groupBy("chunk").applyInArrow(
        _candidates(percent),
        "sid long, n long, keys binary, prefix array<long>, shorter long, lowest long, common double",
    )
    # Equal sets of different chunks are one set.
    candidates = written(found.dropDuplicates(["sid"]), "jaccard-candidates")
    links = set_links(candidates, percent=percent, slice_sets=slice_sets)
    labels = connected_components(links).select(F.col("node").alias("sid"), "component")
    return written(
        rows.join(labels, "sid", "left").select("doc_id", "mark", "n_shingles", F.coalesce("component", "sid").alias("component")),
        "jaccard-placed",
    )


def jaccard_components(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    width: int = 5,
    percent: int = 80,
    buckets: int | None = None,
    slice_sets: int = 256,
) -> DataFrame:
    """doc_id, n_shingles, component_id of every row.

    Two rows link if 100 * overlap >= percent * union of their sets of distinct
    ``width``-word shingles (a shorter text is one shingle; equal texts of one
    set always link).  component_id is the smallest non-null id that links
    reach.  A row without words has an empty set and links with nothing, not
    even its like.  Null ids take part and are named by their component; a
    repeated row is in its like's component.  Other columns are not read; an
    empty table gives no rows.
    """
    placed = _placed(
        docs, id_col=id_col, text_col=text_col, width=width, percent=percent, buckets=buckets, slice_sets=slice_sets
    )
    # Written, so that the last join has plain exchanges on both sides and a
    # component of a third of all rows is split.
    least = written(
        placed.where("component IS NOT NULL").groupBy("component").agg(F.min("doc_id").alias("component_id")),
        "jaccard-least",
    )
    return placed.join(least, "component", "left").select(
        "doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id")
    )


def one_of_each(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, slice_sets: int = 256
) -> DataFrame:
    """The input without its near copies, with its columns.

    Of each component of links one row stays: that with the smallest id (a null
    id comes after all others); of several rows with that id that with the
    smallest hash of its text, and of repeated rows one.  The decision is by
    row, so a row that shares its id with another's copy stays unless it is a
    copy itself.  Rows without words link with nothing and all stay.  An empty
    table stays empty; columns may have any names.
    """
    placed = _placed(docs, id_col=id_col, text_col=text_col, width=width, percent=percent, buckets=None, slice_sets=slice_sets)
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("mark").alias("m"))
    first = written(
        placed.where("component IS NOT NULL").groupBy("component").agg(F.min(order).alias("stays")), "jaccard-first"
    )
    # Rows that go are distinct (id, mark) pairs, so a text that a third of all
    # rows repeat under one id meets one pair.
    gone = (
        placed.join(first, "component")
        .where(~(F.col("doc_id").eqNullSafe(F.col("stays.id")) & (F.col("mark") == F.col("stays.m"))))
        .select("doc_id", "mark").distinct()
    )
    text = F.col(f"row.`{text_col}`").cast("string")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")).withColumn("wordless", ~F.coalesce(text.rlike(r"[^ \t\n\x0B\f\r]"), F.lit(False)))
    keyed = rows.where("NOT wordless").select("row", F.col(f"row.`{id_col}`").cast("long").alias("of"), F.xxhash64(text).alias("as"))
    stay = keyed.join(gone, F.col("of").eqNullSafe(F.col("doc_id")) & (F.col("as") == F.col("mark")), "left_anti")
    return stay.dropDuplicates(["of", "as"]).select("row.*").union(rows.where("wordless").select("row.*"))
