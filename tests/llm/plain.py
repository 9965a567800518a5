"""Operators in plain Python, one document or pair after another, as far as tests compare with them."""

import collections
import hashlib
import re

from minlabel.llm import personal_data
from tests.helpers import union_find

LOW = {c: c + 32 for c in range(65, 91)}


def contamination(docs, bench):
    """id -> n_words, n_hit, n_items, items_sha256, contaminated, for (id, text) of documents and items."""
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOW))
    windows, out = {}, {}
    for i, t in bench:
        w = words(t)
        for j in range(len(w) - min(13, len(w)) + 1):
            windows.setdefault(tuple(w[j : j + 13]), set()).add(str(i))
    for i, t in docs:
        w = words(t)
        hit, items = set(), set()
        for n in {len(k) for k in windows} - {0}:
            for j in range(len(w) - n + 1):
                if found := windows.get(tuple(w[j : j + n])):
                    hit |= set(range(j, j + n))
                    items |= found
        out[i] = (len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w))
    return out


def near_classes(docs):
    """id -> smallest id of the component of pairs whose sets of five words have a Jaccard index of at least 0.8."""
    sets = {}
    for i, t in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))
        if w:
            sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    inverted, common = collections.defaultdict(list), collections.Counter()
    for i, s in sets.items():
        for x in s:
            inverted[x].append(i)
    for own in inverted.values():
        for a in range(len(own)):
            for b in range(a):
                common[tuple(sorted((own[a], own[b])))] += 1
    links = [(a, b) for (a, b), n in common.items() if n / (len(sets[a]) + len(sets[b]) - n) >= 0.8]
    return union_find([i for i, _ in docs], links)


def personal_spans(t, chooser):
    """Base spans, and further ones: the likeliest candidate that is left, again and again; of equals the first, the longest."""
    base = [("email", m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    base += [("ip", m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = [int(c) for c in m[0] if c.isdigit()][::-1]
        if 16 <= len(d) <= 19 and (sum(d[::2]) + sum(2 * x - 9 * (x > 4) for x in d[1::2])) % 10 == 0:
            base.append(("card", m.start(), m.end()))
    base += [("phone", m.start(), m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 8 <= sum(c.isdigit() for c in m[0]) <= 15]
    likely = [(chooser.probability(t, g, a, b), kind, a, b) for g, kind, a, b in personal_data.candidates(t)]
    likely = [x for x in likely if x[0] >= chooser.thresholds[x[1]]]
    held, more = {i for _, a, b in base for i in range(a, b)}, []
    while likely:
        best = min(likely, key=lambda x: (-x[0], x[2], -x[3], x[1]))
        likely.remove(best)
        if not held & set(range(best[2], best[3])):
            held |= set(range(best[2], best[3]))
            more.append(best[1:])
    return base, sorted(more)


def redacted(t, chooser):
    """The text with each run of overlapping spans as the kind of its first, from the last run to the first."""
    if t is None:
        return None
    base, more = personal_spans(t, chooser)
    runs = []
    for a, b, kind in sorted((a, b, kind) for kind, a, b in base + more):
        if runs and a < runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], b)
        else:
            runs.append([a, b, kind])
    for a, b, kind in reversed(runs):
        t = f"{t[:a]}[{kind.upper()}]{t[b:]}"
    return t
