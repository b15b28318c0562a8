"""Brute-force versions of the operators, for small tables."""

import hashlib
from collections import Counter, defaultdict

import numpy as np
import regex

DOC = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def shingles(text, width=5):
    w = (text or "").lower().split()
    k = min(width, len(w))
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if k else frozenset()


def jaccard_classes(docs):
    """{row index: (class id, links)} of (doc_id, text) rows."""
    sets = [shingles(t) for _, t in docs]
    met = defaultdict(int)
    by = defaultdict(list)
    for i, s in enumerate(sets):
        for x in s:
            by[x].append(i)
    for rows in by.values():
        for a in range(len(rows)):
            for b in range(a):
                met[rows[b], rows[a]] += 1
    edges = {(a, b) for (a, b), n in met.items() if 5 * n >= 4 * (len(sets[a]) + len(sets[b]) - n)}
    for a in range(len(docs)):
        for b in range(a):
            if (docs[a][1] or "") == (docs[b][1] or ""):
                edges.add((b, a))
    root, links = list(range(len(docs))), [0] * len(docs)

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        links[a] += 1
        links[b] += 1
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    least = {}
    for i, (k, _) in enumerate(docs):
        r = find(i)
        least[r] = min(x for x in (least.get(r), k) if x is not None) if (least.get(r) is not None or k is not None) else None
    return [(docs[i][0], least[find(i)], links[i]) for i in range(len(docs))]


def removed_strings(docs, length=400):
    data = [(k, (t or "").encode()) for k, t in docs]
    seen = Counter(b[p : p + length] for _, b in data for p in range(len(b) - length + 1))
    out = []
    for k, b in data:
        m = np.zeros(len(b) + 1, int)
        for p in range(len(b) - length + 1):
            if seen[b[p : p + length]] > 1:
                m[p] += 1
                m[p + length] -= 1
        g = np.cumsum(m[:-1]) > 0
        out.append((k, len(b), int(g.sum()), int(g[:1].sum() + (g[1:] & ~g[:-1]).sum()), hashlib.sha256(np.frombuffer(b, np.uint8)[~g].tobytes()).hexdigest()))
    return out


def contaminated(docs, items):
    words = lambda t: [w for w in regex.split(r"[^\p{L}\p{N}]+", (t or "").lower()) if w]
    bags = lambda w: Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    known = [(i, len(words(t)), bags(words(t))) for i, t in items if len(words(t)) >= 5]
    found = set()
    for k, t in docs:
        w = words(t)
        every = set(bags(w))
        for i, n, bag in known:
            if not every & set(bag):
                continue
            for s in range(max(1, len(w) - n + 1)):  # a text of fewer words is one window
                own = bags(w[s : s + n])
                both = sum((own & bag).values())
                if both and both * 5 >= 4 * (sum(own.values()) + n - 4 - both):
                    found.add((k, i))
                    break
    return found


def text_features(text, lexicon, second, strip, stand_ins):
    """The toxicity features of a text, one definition after another, from lists of words."""
    words = [w.strip(strip) for w in text.lower().split()]
    n, d = len(words), max(1, len(words))
    hits, begins, you, masked, masked_hits = {}, [], [], 0, 0
    for i, w in enumerate(words):
        if w in second:
            you.append(i)
        plain = "".join(c for c in "".join(stand_ins.get(c, c) for c in w) if c.isalpha() or (c.isalnum() and not c.isdecimal()))
        if f"w:{w}" in lexicon:
            hits[i] = lexicon[f"w:{w}"]
        elif len(w) > 5 and f"b:{w[:5]}" in lexicon:
            begins.append(i)
        elif w and not w.isalpha() and not w.isnumeric() and any(c.isalpha() for c in w):
            masked += 1
            if f"w:{plain}" in lexicon:
                hits[i] = lexicon[f"w:{plain}"]
                masked_hits += 1
    both = sorted([*hits, *begins])
    near = [any(abs(i - j) <= 5 for j in you) for i in both] if you else []
    data = text.encode()
    letters = max(1, sum(chr(c).isalpha() and c < 128 or c == 0xC3 for c in data))
    weights = [int(min(x, 30.0) * 64) / 64 for x in hits.values()]
    chars = max(1, len(data))
    ascii_punct = [chr(c) for c in data if 33 <= c < 127 and not chr(c).isalnum()]
    return [
        len(hits) / d, np.log1p(len(hits)), sum(weights) / d, max(weights, default=0.0), len({text.lower().split()[i] for i in hits}),
        len(begins) / d, np.log1p(len(begins)), sum(near) / len(near) if near else 0.0, len(you) / d,
        sum(65 <= c <= 90 for c in data) / letters, len(ascii_punct) / chars, sum(c in "!?" for c in ascii_punct) / chars,
        masked / d, masked_hits, sum(48 <= c <= 57 for c in data) / chars, np.log1p(n), chars / d, np.log1p(data.count(b"\n")),
        max((sum(i <= j < i + 50 for j in both) for i in both), default=0), both[0] / d if both else 1.0,
    ]


def boosted(x, y, rounds, depth, rate, bins, l2):
    """Scores of second-order boosting, every split of every node tried in turn."""
    cuts = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    p = y.mean()
    raw = np.full(len(y), np.log(p / (1 - p)))
    least = max(3, len(y) // 1000)
    for _ in range(rounds):
        prob = 1 / (1 + np.exp(-raw))
        g, h = prob - y, np.maximum(prob * (1 - prob), 1e-6)
        parts = [np.arange(len(y))]
        add = np.zeros(len(y))
        for _ in range(depth):
            grown = []
            for own in parts:
                best = (1e-6, None)
                for j, cut in enumerate(cuts):
                    for c in cut:
                        a, b = own[x[own, j] <= c], own[x[own, j] > c]
                        if len(a) < least or len(b) < least:
                            continue
                        gain = sum(g[z].sum() ** 2 / (h[z].sum() + l2) for z in (a, b)) - g[own].sum() ** 2 / (h[own].sum() + l2)
                        if gain > best[0] + 1e-9:
                            best = (gain, (a, b))
                if best[1]:
                    for z in best[1]:
                        add[z] = -rate * g[z].sum() / (h[z].sum() + l2)
                        grown.append(z)
            parts = grown
        raw = raw + add
    return raw


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=str)
