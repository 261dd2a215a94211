"""Plain forms of the operators, for small inputs."""

import hashlib
from collections import Counter


def words(text):
    return (text or "").encode().split()


def kept_words(docs, width=50):
    """doc -> (n_words, n_removed, digest) from (doc_id, text)."""
    first = {}
    for doc, text in docs:
        w = words(text)
        for i in range(len(w) - width + 1):
            key = tuple(w[i : i + width])
            if doc is not None:
                first[key] = min(first.get(key, doc), doc)
    out = []
    for doc, text in docs:
        w, gone = words(text), set()
        for i in range(len(w) - width + 1):
            if doc is not None and first[tuple(w[i : i + width])] < doc:
                gone.update(range(i, i + width))
        kept = [x for i, x in enumerate(w) if i not in gone]
        out.append((doc, len(w), len(gone), hashlib.sha256(b" ".join(kept)).hexdigest()))
    return out


def shingle_set(text, n=5):
    w = words(text)
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()


def near_classes(docs, threshold=0.8):
    """doc -> (class, links)."""
    sets = {d: shingle_set(t) for d, t in docs}
    root, links = {d: d for d in sets}, Counter()

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] and sets[b] and len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b]) - 1e-9:
                links[a] += 1
                links[b] += 1
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (find(d), links[d]) for d in ids}
