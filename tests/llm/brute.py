"""Plain Python versions of what the operators return, row by row."""

import hashlib
import re
from collections import Counter, defaultdict

from xxhash import xxh64_intdigest

LONG = " ".join(f"w{i % 977}x{i % 13}" for i in range(30_000))
EDGE = [
    (1, None, None, None), (2, "", "en", "a"), (3, " \t\n\x0b\x0c\r ", "en", "a"), (4, "one", "en", None), (5, "one two", "en", "b"), (6, "ONE TWO", "de", "b"),
    (7, "a b c d e f g h i j k l m n o p q r s t u v w x y z", "en", "a"), (8, "a b c d e f g h i j k l m n o p q r s t u v w x y z", "en", "a"),
    (9, "abc defghijklmnopqrstuvwxyz", "fr", "c"), (10, LONG, "en", "a"), (11, LONG + " tail", "en", "a"), (12, "x " * 5000, "en", "a"),
    (13, "Grüße\nGrüße\n\nGrüße #*$ %&|<> a\x00b", "de", "d"), (14, "日本語 テキスト 😀 😀", None, "d"), (15, "mail a.b@c-d.org, +49 (30) 1234-5678 1.2.3.4 1.2.3.999 4111 1111 1111 1111 @x.y a@b token = \"abcdef0123456789abcd\" 9" + "9" * 400, "en", "e"),
    (16, "e\u0301\u00a0nbsp\u2028line", "fr", "e"), (16, "e\u0301\u00a0nbsp\u2028line", "fr", "e"), (17, "p q r " + "a b c d e f g h i j k l m n o p q r s t u v w x y z" + " end", "en", "a"), (None, "a b c d e f g h i j k l m n o p q r s t u v w x y z", "en", "a"),
    (18, "password=b7db7aa4a5fcc78305 here and <|endoftext|> " * 3, "en", "a"), (19, "1 2 3 4 5 6 7 8 " * 40, "es", "f"),
]
FIELDS = "doc_id long, text string, lang string, source string"


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def quality(t):
    w, t = words(t), t or ""
    seen = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = set()
    for i in range(len(w) - 7):
        if seen[tuple(w[i : i + 8])] > 1:
            covered.update(range(i, i + 8))
    lines = [x for x in t.split("\n") if words(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered)


def squeezed(t):
    return re.sub(r"[\x20\x09-\x0D]", "", t or "")


def exact(rows):
    groups = defaultdict(list)
    for d, t in rows:
        groups[squeezed(t)].append((-len(t or ""), d is None, d))
    out = []
    for d, t in rows:
        g = groups[squeezed(t)]
        out.append((d, min(g, key=lambda x: (x[0], x[1], x[2] or 0))[2], len(g), hashlib.sha256(squeezed(t).encode()).hexdigest()))
    return out


def fingerprint(t):
    w = words(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
    h = [xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def closure(nodes, linked):
    """node -> least node reachable; linked(a, b) over all pairs."""
    parent = {n: n for n in nodes}

    def find(n):
        while parent[n] != n:
            n = parent[n]
        return n

    nodes = sorted(nodes)
    for i, a in enumerate(nodes):
        for b in nodes[:i]:
            if linked(a, b):
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    return {n: find(n) for n in nodes}


def repeats(rows, k=13):
    """doc -> (n_words, n_removed, sha of kept words)."""
    first = {}
    for d, t in rows:
        w = words(t)
        for i in range(len(w) - k + 1):
            if d is not None:
                first[tuple(w[i : i + k])] = min(first.get(tuple(w[i : i + k]), d), d)
    out = []
    for d, t in rows:
        w, gone = words(t), set()
        for i in range(len(w) - k + 1):
            if d is not None and first[tuple(w[i : i + k])] < d:
                gone.update(range(i, i + k))
        out.append((d, len(w), len(gone), hashlib.sha256(" ".join(x for i, x in enumerate(w) if i not in gone).encode()).hexdigest()))
    return out


def personal(t):
    t = t or ""
    out = [("email", m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t):
        if all(int(p) <= 255 for p in m[0].split(".")):
            out.append(("ip", m.start(), m.end()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = [int(c) for c in m[0] if c.isdigit()]
        if 16 <= len(d) <= 19 and sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(reversed(d))) % 10 == 0:
            out.append(("card", m.start(), m.end()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t):
        if 8 <= sum(c.isdigit() for c in m[0]) <= 15:
            out.append(("phone", m.start(), m.end()))
    return out
