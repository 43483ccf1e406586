"""Plain-Python versions of the operators, for small tables."""

import hashlib
from collections import Counter, defaultdict

LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def words(text):
    return (text or "").encode().split()


def digest(data):
    return hashlib.sha256(data).hexdigest()


def substring(docs, window=13):
    """[(doc_id, n_words, n_removed, kept_sha256)] of a list of (doc_id, text)."""
    first = {}
    for k, t in docs:
        w = words(t)
        for i in range(len(w) - window + 1):
            if k is not None:
                first[tuple(w[i : i + window])] = min(k, first.get(tuple(w[i : i + window]), k))
    out = []
    for k, t in docs:
        w, gone = words(t), set()
        for i in range(len(w) - window + 1):
            if k is not None and first[tuple(w[i : i + window])] < k:
                gone.update(range(i, i + window))
        out.append((k, len(w), len(gone), digest(b" ".join(x for i, x in enumerate(w) if i not in gone))))
    return out


def cut_bytes(docs, length=400, min_words=0, sure=400):
    """[(kept bytes, n_spans)] of a list of (doc_id, text); runs under ``sure`` bytes need ``min_words`` words."""
    seen = Counter()
    for _, t in docs:
        raw = (t or "").encode()
        seen.update(raw[i : i + length] for i in range(len(raw) - length + 1))
    out = []
    for _, t in docs:
        raw, runs = (t or "").encode(), []
        for i in range(len(raw) - length + 1):
            if seen[raw[i : i + length]] > 1:
                if runs and i <= runs[-1][1]:
                    runs[-1][1] = i + length
                else:
                    runs.append([i, i + length])
        runs = [(a, b) for a, b in runs if b - a >= sure or len(raw[a:b].split()) >= min_words]
        kept, at = b"", 0
        for a, b in runs:
            kept, at = kept + raw[at:a], b
        out.append((kept + raw[at:], len(runs)))
    return out


def shingles(text, width=5):
    w = (text or "").encode().translate(LOWER).split()
    if len(w) >= width:
        return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)}
    return {tuple(w)} if w else set()


def components(nodes, edges):
    parent = {n: n for n in nodes}

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def jaccard(docs):
    """{doc_id: (n_shingles, component_id)}"""
    sets = {k: shingles(t) for k, t in docs.items()}
    lists = defaultdict(list)
    for k, s in sets.items():
        for t in s:
            lists[t].append(k)
    edges = []
    for k, s in sets.items():
        common = Counter()
        for t in s:
            common.update(lists[t])
        edges += [(k, j) for j, o in common.items() if j > k and 100 * o >= 75 * (len(s) + len(sets[j]) - o)]
    comp = components(sets, edges)
    return {k: (len(s), comp[k]) for k, s in sets.items()}


def quality(text):
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed)"""
    text = text or ""
    w = [x.decode() for x in words(text)]
    lines = [x for x in text.split("\n") if words(x)]
    grams = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    rep = {i + j for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for j in range(5)}
    base = len(w) < 10 or 100 * len(rep) > 20 * len(w)
    return len(w), sum(map(len, w)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(rep), base
