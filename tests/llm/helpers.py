"""Brute-force forms of the operators, and awkward tables."""

from __future__ import annotations

import hashlib
import random
import re

WHITE = re.compile(r"[\x20\x09-\x0D]+")


def words(text):
    return [w for w in WHITE.split(text or "") if w]


def sha(data):
    return hashlib.sha256(data if isinstance(data, bytes) else data.encode()).hexdigest()


def awkward(seed=0, n=60):
    """(doc_id, text) with nulls, empty and long texts, copies, near copies, shared passages, odd characters."""
    r = random.Random(seed)
    vocabulary = ["".join(r.choice("abcdeéßñ漢") for _ in range(r.randrange(1, 8))) for _ in range(300)]
    prose = lambda k: " ".join(r.choice(vocabulary) for _ in range(k))
    passage = prose(60)
    rows = [(0, None), (1, ""), (2, " \n\t "), (3, "one"), (4, "one  two"), (5, "one\ttwo"), (6, "😀 \x1c\x00 a b"), (7, prose(4000)), (8, "a" * 700), (9, "a " * 400)]
    for i in range(10, n):
        kind = r.randrange(5)
        if kind == 0:
            text = r.choice(rows)[1]
        elif kind == 1:
            ws = (r.choice(rows)[1] or "x").split(" ")
            ws[r.randrange(len(ws))] = "changed"
            text = " ".join(ws)
        elif kind == 2:
            text = prose(r.randrange(0, 40)) + " " + passage + "\n" + prose(r.randrange(0, 40))
        else:
            text = prose(r.randrange(1, 200))
        rows.append((i, text))
    r.shuffle(rows)
    return rows


def frame(spark, rows, parts=3):
    """documents with further columns whose names clash with inner ones."""
    names = ["id", "anchor", "key", "rank", "spans", "n", "component", "bucket", "length", "m", "e"]
    wide = [(d, t, "en", "src", len(t or ""), *["x"] * len(names)) for d, t in rows]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in names)
    return spark.createDataFrame(wide, schema).repartition(parts)


def repeat_words(ws):
    grams = [tuple(ws[i : i + 3]) for i in range(len(ws) - 2)]
    seen = {}
    for g in grams:
        seen[g] = seen.get(g, 0) + 1
    return len({i + k for i, g in enumerate(grams) if seen[g] > 1 for k in range(3)})


def removed_bytes(rows, width=100):
    """doc_id -> (n_bytes, n_removed, n_spans, kept digest)."""
    seen, out = set(), {}
    for d, text in sorted(rows):
        b = (text or "").encode()
        covered = bytearray(len(b))
        for i in range(len(b) - width + 1):
            w = b[i : i + width]
            if w in seen:
                covered[i : i + width] = b"\1" * width
            seen.add(w)
        spans = sum(1 for i, c in enumerate(covered) if c and not (i and covered[i - 1]))
        out[d] = (len(b), sum(covered), spans, sha(bytes(x for x, c in zip(b, covered, strict=True) if not c)))
    return out


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def _digits(hit):
    return re.sub("[^0-9]", "", hit)


PII = [
    ("email", re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), lambda h: True),
    ("ip", re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), lambda h: all(int(x) <= 255 for x in h.split("."))),
    ("card", re.compile(r"[0-9]([\x20-]?[0-9])+"), lambda h: 12 <= len(_digits(h)) <= 19 and luhn(_digits(h))),
    ("phone", re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"), lambda h: 9 <= len(_digits(h)) <= 15),
]


def base_spans(text):
    found = [(m.start(), k, m.end(), kind) for k, (kind, pattern, ok) in enumerate(PII) for m in pattern.finditer(text or "") if ok(m[0])]
    return ",".join(f"{kind}:{a}:{b}" for a, _, b, kind in sorted(found))


def shingles(text, k):
    ws = (text or "").encode().lower().split()
    if len(ws) < k:
        return frozenset([tuple(ws)]) if ws else frozenset()
    return frozenset(tuple(ws[i : i + k]) for i in range(len(ws) - k + 1))


def near_components(rows, k, percent=80):
    sets = {d: shingles(t, k) for d, t in rows}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(d for d in sets if sets[d])
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d)) for d in sets}
