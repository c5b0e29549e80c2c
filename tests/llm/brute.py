"""Plain versions of the operators' results, one text at a time."""

import hashlib
import math
import re
import zlib
from collections import Counter

import xxhash

RULES = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(d):
    t = [int(x) * (1 + k % 2) for k, x in enumerate(reversed(d))]
    return sum(x // 10 + x % 10 for x in t) % 10 == 0


def base_spans(text):
    out = []
    for kind, p in RULES.items():
        for m in re.finditer(p, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else 0, "card": 13 <= len(d) <= 19 and luhn(d), "phone": 9 <= len(d) <= 15}[kind]
            if ok:
                out.append((kind, *m.span()))
    return out


def digest(spans):
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()


def simhash(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    g = [" ".join(w[k : k + 4]) for k in range(max(1, len(w) - 3))]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in g]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def components(rows, bits=4):
    """rows: (doc_id, fingerprint)."""
    up = {}

    def top(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    fps = sorted({f for _, f in rows})
    for k, a in enumerate(fps):
        for b in fps[k:]:
            if (a ^ b).bit_count() <= bits:
                up[top(a)] = top(b)
    least = {}
    for d, f in rows:
        t = top(f)
        least[t] = min(least.get(t, d), d)
    return {d: least[top(f)] for d, f in rows}


def words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def contamination(text, items, n=10):
    """items: (id, text)."""
    w = words(text)
    hit, found = set(), set()
    at = {}
    for size in {min(n, len(words(t))) for _, t in items}:
        for k in range(len(w) - size + 1) if size else ():
            at.setdefault(tuple(w[k : k + size]), []).append(k)
    for i, t in items:
        v = words(t)
        size = min(n, len(v))
        for k in range(len(v) - size + 1) if size else ():
            for a in at.get(tuple(v[k : k + size]), ()):
                hit |= set(range(a, a + size))
                found.add(str(i))
    return len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()


def base_scores(rows):
    """rows: (doc_id, text) -> {doc_id: (n_tokens, n_known, N, base)}."""
    toks = {d: [*re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")), ""] for d, t in rows}
    c = Counter(x for d, w in toks.items() if zlib.crc32(str(d).encode()) % 10 for x in w)
    n, v = sum(c.values()), len(c)
    return {d: (len(w), sum(c[x] > 0 for x in w), n, sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w)) for d, w in toks.items()}
