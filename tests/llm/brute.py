"""The operators' results by plain loops over small inputs."""

import hashlib
import math
import re
from collections import Counter, defaultdict

ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)


def words(text):
    return (text or "").encode().split()


def sha(data):
    return hashlib.sha256(data).hexdigest()


def secrets(text):
    t = text or ""
    spans = [(m.start(), 0, m.end(), "assign") for m in ASSIGN.finditer(t) if len(m.group(2)) >= 8]
    spans += [(m.start(), 1, m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m.group()) >= 16]
    spans += [(m.start(), 2, m.end(), "hex") for m in re.finditer("[0-9a-f]+", t) if len(m.group()) >= 32]
    spans.sort()
    kinds = [s[3] for s in spans]
    return kinds.count("assign"), kinds.count("access"), kinds.count("hex"), sha(",".join(f"{k}:{a}:{b}" for a, _, b, k in spans).encode())


def lines(rows, run=2, long=50):
    """rows: distinct (doc_id, text). Result by row."""
    seen, out = set(), {}
    for d, t in sorted(rows, key=lambda r: (r[0] is None, r[0] or 0)):
        each = (t or "").split("\n")
        full = [i for i, x in enumerate(each) if x.encode().split()]
        gone, here = set(), []
        for a in range(len(full) - run + 1):
            k = tuple(each[i] for i in full[a : a + run])
            if k in seen:
                gone |= set(full[a : a + run])
            seen.add(k)
        for i in full:
            if len(each[i].encode().split()) >= long:
                k = ("long", each[i])
                if k in seen:
                    gone.add(i)
                seen.add(k)
        assert not here
        out[d, t] = "\n".join(x for i, x in enumerate(each) if i not in gone), len(gone)
    return out


def quality(text):
    w = words(text)
    counts = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = set()
    for i in range(len(w) - 4):
        if counts[tuple(w[i : i + 5])] > 1:
            covered |= set(range(i, i + 5))
    t = text or ""
    seen, dup = set(), 0
    for x in t.split("\n"):
        if x.encode().split():
            dup += x in seen
            seen.add(x)
    return len(w), sum(len(x.decode()) for x in w), sum(t.count(c) for c in "#*$%&|<>"), dup, len(covered), len(w) < 10 or 100 * len(covered) > 20 * len(w)


def byte_repeats(texts, length):
    docs = [(t or "").encode() for t in texts]
    counts = Counter(d[i : i + length] for d in docs for i in range(len(d) - length + 1))
    out = []
    for d in docs:
        gone = bytearray(len(d))
        for i in range(len(d) - length + 1):
            if counts[d[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        spans = sum(1 for i in range(len(d)) if gone[i] and (i == 0 or not gone[i - 1]))
        out.append((len(d), sum(gone), spans, sha(bytes(x for x, g in zip(d, gone) if not g))))
    return out


def word_repeats(texts, window):
    docs = [words(t) for t in texts]
    counts = Counter(tuple(d[i : i + window]) for d in docs for i in range(len(d) - window + 1))
    out = []
    for d in docs:
        gone = [False] * len(d)
        for i in range(len(d) - window + 1):
            if counts[tuple(d[i : i + window])] > 1:
                gone[i : i + window] = [True] * window
        out.append((len(d), sum(gone), sha(b" ".join(x for x, g in zip(d, gone) if not g))))
    return out


def components(rows, n, num, den):
    """rows: (doc_id, text). (size, least doc_id of the component, name of the component) of each."""
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set()))
    root = list(range(len(rows)))

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    inverted = defaultdict(list)
    for i, s in enumerate(sets):
        common = Counter(j for x in s for j in inverted[x])
        for x in s:
            inverted[x].append(i)
        for j, k in common.items():
            if den * k >= num * (len(s) + len(sets[j]) - k):
                root[top(i)] = top(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[top(i)] = min(d, least.get(top(i), d))
    return [(len(sets[i]), least.get(top(i)) if sets[i] else rows[i][0], top(i)) for i in range(len(rows))]


def bm25(docs, queries, k, k1=1.2, b=0.75):
    terms = [(d, Counter((t or "").encode().lower().split())) for d, t in docs]
    n, mean = len(terms), sum(sum(c.values()) for _, c in terms) / max(1, len(terms))
    out = set()
    for q, text in queries:
        scores = []
        asked = Counter((text or "").encode().lower().split())
        df = {t: sum(t in c for _, c in terms) for t in asked}
        for d, c in terms:
            s = sum(m * math.log(1 + (n - df[t] + 0.5) / (df[t] + 0.5)) * c[t] * (k1 + 1) / (c[t] + k1 * (1 - b + b * sum(c.values()) / mean)) for t, m in sorted(asked.items()) if t in c)
            if s > 0:
                scores.append((-round(s, 6), d is None, d or 0))
        out |= {(q, r, None if x[1] else x[2], -x[0]) for r, x in enumerate(sorted(scores)[:k], 1)}
    return out
