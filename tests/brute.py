"""The whole method in plain loops, for small corpora: network, verdicts, scores, advances, clusters, forest."""

import math
from collections import Counter, defaultdict


def links_of(lines):
    """(src, dst) -> relevance from {doc: set of lines}: cite the holder before and the first."""
    held, out = defaultdict(list), Counter()
    for doc in sorted(lines):
        for line in lines[doc]:
            for cited in {held[line][-1], held[line][0]} if held[line] else ():
                out[doc, cited] += 1
            held[line].append(doc)
    return out


def network_of(links, target, depth=2, cap=50):
    """item -> (layer, relation) around a target."""
    found = {}
    for relation, here, there in (("reference", 0, 1), ("citation", 1, 0)):
        front = {target}
        for layer in range(1, depth + 1):
            reached = set()
            for item in front:
                near = sorted((-r, pair[there]) for pair, r in links.items() if pair[here] == item)
                reached |= {x for _, x in (near if relation == "reference" else near[:cap]) if x != target}
            for x in reached:
                found[x] = min(found.get(x, (9, "")), (layer, relation), key=lambda v: (v[0], v[1] == "citation"))
            front = reached
    return found


def verdict(kind, direction, mine, theirs):
    if mine is None or theirs is None:
        return None
    if kind == "categorical":
        return 0 if mine == theirs else 1
    return 0 if mine == theirs else 1 if (mine - theirs) * direction > 0 else -1


def omega(verdicts, alpha=0.5):
    """Score from {axis: [verdicts]}."""
    rows = []
    for values in verdicts.values():
        n = Counter(v for v in values if v is not None)
        total = sum(n.values())
        rows.append((n[1] / total, (n[1] + alpha * n[0] - n[-1]) / total) if total else (0.0, 0.0))
    weight = sum(w for w, _ in rows)
    return round(sum(w * s for w, s in rows) / weight if weight else sum(s for _, s in rows) / len(rows), 6)


def advances(series, kind, direction):
    """Verdicts of values in order against the best so far, or against all values so far."""
    best, seen, out = None, set(), []
    for v in series:
        if v is None:
            out.append(None)
        elif kind == "categorical":
            out.append(0 if v in seen else 1)
            seen.add(v)
        else:
            lead = 1 if best is None else (v - best) * direction
            out.append(1 if lead > 0 else 0 if lead == 0 else -1)
            best = v if lead > 0 else best
    return out


def trigram_vector(text, size=64):
    codes = [ord(c) for c in f"  {text} "]
    out = [0.0] * size
    for a, b, c in zip(codes, codes[1:], codes[2:]):
        h = (a * 7919 + b * 104729 + c * 1299709) % 1000003
        out[h % size] += 1.0 if h // size % 2 == 0 else -1.0
    return out


def cosine(x, y):
    n = sum(a * a for a in x) * sum(b * b for b in y)
    return round(sum(a * b for a, b in zip(x, y)) / math.sqrt(n), 6) if n else None


def edit_similarity(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return round(1 - row[-1] / max(len(a), len(b)), 6)


def forest_of(winners):
    """Edges (i, j) among winners [(year, normalised value)] of one axis in order of time."""
    n = len(winners)
    vectors, tokens = [trigram_vector(v) for _, v in winners], [set(v.split()) for _, v in winners]
    pairs = [(i, j) for i in range(n) for j in range(i + 1, n)]
    sim = {p: cosine(vectors[p[0]], vectors[p[1]]) for p in pairs}
    label = list(range(n))
    for i, j in pairs:  # two neighbours are enough for a core
        if sim[i, j] is not None and sim[i, j] >= 0.5 and label[i] != label[j]:
            low, high = sorted((label[i], label[j]))
            label = [low if x == high else x for x in label]
    alone = {x for x, k in Counter(label).items() if k == 1}
    edges = []
    for i, j in pairs:
        same = label[i] == label[j]
        near = sim[i, j] is not None and sim[i, j] >= 0.2 and edit_similarity(winners[i][1], winners[j][1]) >= 0.5
        noisy = (label[i] in alone) + (label[j] in alone)
        overlap = len(tokens[i] & tokens[j]) / len(tokens[i] | tokens[j])
        conf = (5 if round(overlap, 6) >= 0.5 else 4) if same else 3 - noisy if near else 0
        if conf:
            edges.append((-round(conf / (winners[j][0] - winners[i][0] + 1), 6), j - i, i, j))
    root, out = list(range(n)), set()
    for _, _, i, j in sorted(edges):
        a, b = root[i], root[j]
        if a != b:
            root = [a if x == b else x for x in root]
            out.add((i, j))
    return out
