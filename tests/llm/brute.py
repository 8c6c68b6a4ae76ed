"""Plain versions of the operators, for small tables."""

from __future__ import annotations

import re


def words5(text):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def shingle_set(text, n=5):
    w = words5(text)
    return {tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


def similar_components(docs):
    """[(doc_id, text)] to {doc_id: component}; ids may repeat."""
    sets = [(d, shingle_set(t)) for d, t in docs if d is not None]
    root = {d: d for d, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (a, x) in enumerate(sets):
        for b, y in sets[:i]:
            if a != b and x and y and 100 * len(x & y) >= 80 * len(x | y):
                lo, hi = sorted((find(a), find(b)))
                root[hi] = lo
    return {d: find(d) for d in root}


def line_dedup(docs, min_words=10):
    """{doc_id: text}, ids distinct: deletes what lies in a later copy of a run of min_words words or more."""
    rows = []
    for d, text in sorted(docs, key=lambda r: r[0]):
        lines = (text or "").split("\n")
        seq = [(i, x, len(re.findall(r"[^\x20\x09-\x0D]+", x))) for i, x in enumerate(lines)]
        rows.append((d, text, lines, [r for r in seq if r[2]]))
    first, out = {}, {}
    runs = {}
    for d, _, _, seq in rows:
        for i in range(len(seq)):
            for j in range(i, len(seq)):
                if sum(r[2] for r in seq[i : j + 1]) >= min_words:
                    key = tuple(r[1] for r in seq[i : j + 1])
                    first.setdefault(key, (d, i))
                    runs.setdefault(d, []).append((i, j, key))
    for d, text, lines, seq in rows:
        gone = {seq[k][0] for i, j, key in runs.get(d, []) if first[key] != (d, i) for k in range(i, j + 1)}
        out[d] = None if text is None else "\n".join(x for i, x in enumerate(lines) if i not in gone)
    return out


def phrase_words(text):
    lowered = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lowered)


def contaminated(text, items, width=10):
    """(n_words, n_hit, item ids) of one document."""
    w = phrase_words(text)
    hit, found = set(), set()
    for item, t in items:
        q = phrase_words(t)
        n = min(width, len(q))
        for s in range(len(q) - n + 1) if q else ():
            for i in range(len(w) - n + 1):
                if w[i : i + n] == q[s : s + n]:
                    hit.update(range(i, i + n))
                    found.add(str(item))
    return len(w), len(hit), sorted(found)
