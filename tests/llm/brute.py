"""Plain Python versions of the contracts, for small fixtures."""

import hashlib
import heapq
import re
from collections import defaultdict

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return WORDS.findall(text or "")


def substring(rows, width=13):
    """(doc_id, n_words, n_removed, sha256) of (doc_id, text) rows."""
    first = {}
    big = float("inf")
    for d, t in rows:
        w = words(t)
        for i in range(len(w) - width + 1):
            k = tuple(w[i : i + width])
            first[k] = min(first.get(k, big), big if d is None else d)
    out = []
    for d, t in rows:
        w = words(t)
        gone = set()
        for i in range(len(w) - width + 1):
            if first[tuple(w[i : i + width])] < (big if d is None else d):
                gone.update(range(i, i + width))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((d, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def quality(text):
    w, t = words(text), text or ""
    wins = defaultdict(list)
    for i in range(len(w) - 7):
        wins[tuple(w[i : i + 8])].append(i)
    rep = {p for at in wins.values() if len(at) > 1 for i in at for p in range(i, i + 8)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORDS.search(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(rep), len(w) < 20 or 100 * len(rep) > 30 * len(w)


def shingles(text):
    w = words(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return frozenset()
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)])


def components(rows, percent=80):
    """[(doc_id, size, component)] in row order."""
    sets = [shingles(t) for _, t in rows]
    label = list(range(len(rows)))

    def root(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            o = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * o >= percent * len(sets[i] | sets[j]):
                label[root(i)] = root(j)
    low = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            low[root(i)] = min(d, low.get(root(i), d))
    return [(d, len(sets[i]), low.get(root(i))) for i, (d, _) in enumerate(rows)]


def merge_one_by_one(m, word, memo):
    """Symbols of a word by a piece model's merges: best rank first, then leftmost."""
    if not memo:
        memo.update((int(k), (int(r), int(i))) for k, r, i in zip(m.pair_key, m.pair_rank, m.pair_id, strict=True))
    sym = m._symbols([word])[0].tolist()
    after, before = list(range(1, len(sym) + 1)), list(range(-1, len(sym) - 1))
    heap = []

    def push(i):
        j = after[i]
        if j < len(sym) and sym[i] >= 0 and sym[j] >= 0:
            found = memo.get(sym[i] * m.size + sym[j])
            if found:
                heapq.heappush(heap, (found[0], i, sym[i], sym[j], found[1]))

    for i in range(len(sym) - 1):
        push(i)
    gone = [False] * len(sym)
    while heap:
        _, i, left, right, new = heapq.heappop(heap)
        j = after[i]
        if gone[i] or j >= len(sym) or sym[i] != left or sym[j] != right:
            continue
        sym[i], gone[j], after[i] = new, True, after[j]
        if after[j] < len(sym):
            before[after[j]] = i
        push(i)
        if before[i] >= 0:
            push(before[i])
    return [s for s, g in zip(sym, gone, strict=True) if not g]


def language(model, text):
    """(language, score) by plain loops over n-grams, families and votes."""
    import math

    if not text or not any(c.isalpha() for c in text) or not model.langs:
        return "und", 0.0
    raw = b" " + bytes(b + 32 if 65 <= b <= 90 else b for b in text.encode("utf-8", "replace")) + b" "
    margin = [float(b) for b in model.bias]
    for n in (1, 2, 3):
        grams = [raw[i : i + n] for i in range(len(raw) - n + 1)]
        for g in grams:
            place = (((int.from_bytes(g, "big") + n) & 0xFFFFFFFF) * 2654435761 & 0xFFFFFFFF) >> 20
            for m, w in enumerate(model.table[place].tolist()):
                margin[m] += w / len(grams)
    sure, name = 1.0, model.families[0]
    if model.family_at:
        best = max(range(len(model.families)), key=lambda f: margin[model.family_at[f]])
        name, sure = model.families[best], 1 / (1 + math.exp(-4 * margin[model.family_at[best]]))
    votes = {i: [0, 0.0] for i in range(len(model.members[name]))}
    for a, b, m in model.pairs[name]:
        votes[a if margin[m] > 0 else b][0] += 1
        votes[a][1] += margin[m]
        votes[b][1] -= margin[m]
    top = max(votes, key=lambda k: tuple(votes[k]))
    near = [abs(margin[m]) for a, b, m in model.pairs[name] if top in (a, b)]
    return model.members[name][top], sure / (1 + math.exp(-4 * min(near))) if near else sure
