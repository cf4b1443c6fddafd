"""Plain versions of the operators, one document or all pairs at a time."""

import hashlib
import re
from collections import Counter, defaultdict

import xxhash

WORD = re.compile(r"[^\x20\x09-\x0D]+")
UPPER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def base_counts(text):
    text = text or ""
    w = WORD.findall(text)
    windows = Counter(zip(w, w[1:], w[2:], strict=False))
    hit = set()
    for i in range(len(w) - 2):
        if windows[tuple(w[i : i + 3])] > 1:
            hit |= {i, i + 1, i + 2}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(hit)


def base_secrets(text):
    text, out = text or "", []
    key = "(" + "|".join("".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in k) for k in ("password", "passwd", "secret", "token", "api_?key")).replace("[?]", "?") + ")"
    for m in re.finditer(key + r"""["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text):
        if len(m[2]) >= 8:
            out.append((m.start(), 0, "assign", m.end()))
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 32]
    return [(k, a, b) for a, _, k, b in sorted(out)]


def simhash(text):
    w = WORD.findall((text or "").translate(UPPER))
    if not w:
        return 0
    s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << i for i in range(64) if 2 * sum(x >> i & 1 for x in h) > len(h))


def components(ids, prints):
    """Smallest id that each id reaches over prints at two or fewer differing bits."""
    parent = {f: f for f in set(prints)}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    distinct = sorted(parent)
    for i, a in enumerate(distinct):
        for b in distinct[:i]:
            if (a ^ b).bit_count() <= 2:
                parent[find(a)] = find(b)
    least = {}
    for d, f in zip(ids, prints, strict=True):
        if d is not None:
            least[find(f)] = min(d, least.get(find(f), d))
    return [least.get(find(f)) for f in prints]


GRAM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def leaks(docs, items, size=10):
    """Per document: words, hit words, sorted item ids. ``docs`` and ``items`` are (id, text) lists."""
    split = lambda t: GRAM.findall((t or "").translate(UPPER))
    windows = defaultdict(set)
    for i, t in items:
        w = split(t)
        if w and i is not None:
            n = min(size, len(w))
            for k in range(len(w) - n + 1):
                windows[tuple(w[k : k + n])].add(i)
    lengths = {len(k) for k in windows}
    out = []
    for _, t in docs:
        w, hit, found = split(t), set(), set()
        for n in lengths:
            for k in range(len(w) - n + 1):
                if got := windows.get(tuple(w[k : k + n])):
                    hit |= set(range(k, k + n))
                    found |= got
        out.append((len(w), len(hit), sorted(map(str, found))))
    return out


def line_dedup(docs, min_key=20, min_docs=3):
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(UPPER)
    holders = defaultdict(set)
    for d, t in docs:
        for x in (t or "").split("\n"):
            if d is not None and len(key(x)) >= min_key:
                holders[key(x)].add(d)
    out = []
    for d, t in docs:
        lines = (t or "").split("\n")
        left = [x for x in lines if d is None or len(holders.get(key(x), ())) < min_docs or d == max(holders[key(x)])]
        out.append((len(lines), len(lines) - len(left), "\n".join(left)))
    return out


def archive(pages):
    """Per page: bytes, digest, type, referred page."""
    body = [(h or "").encode() for _, _, h in pages]
    best = {}
    for (p, _, _), b in zip(pages, body, strict=True):
        if p is not None:
            best[b] = max(p, best.get(b, p))
    count = Counter(body)
    out = []
    for (p, _, _), b in zip(pages, body, strict=True):
        again = len(b) >= 1000 and count[b] > 1 and b in best and p != best[b]
        out.append((len(b), hashlib.sha1(b).hexdigest(), "revisit" if again else "response", best[b] if again else None))
    return out
