"""Operator 3: secret scan.

One Aho-Corasick pass over a text's bytes finds the keywords of all rules; anchored regular expressions run only at
these hits, leftmost first and without overlap per kind; kinds with an embedded checksum are then validated by it. Runs
of hexadecimal digits have no keyword: they are found by their own run scan.

Spans are ``kind, start, end`` in code points, end exclusive. Edge cases: null and empty texts have no spans; repeated
rows are scanned alike; kept columns that have the name of a result stay, and the result takes a name of its own; an empty
table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from functools import lru_cache

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import free_names, map_texts

# The kinds in their order, keywords and patterns of the base rules.
BASE_KINDS = ("assign", "access", "hex")
ASSIGN_KEYS = ("password", "passwd", "secret", "token", "api_key", "apikey")
_ASSIGN = re.compile(rb"""(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE)
_ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
_HEX = re.compile(rb"[0-9a-f]{32,}")
ASSIGN_MIN, ACCESS_MIN = 8, 16
# Public token formats that end in the CRC-32 of their random part as six base-62 digits.
CHECKED = {"ghp_": "forge", "gho_": "forge", "ghu_": "forge", "ghs_": "forge", "ghr_": "forge", "npm_": "registry"}
CHECKED_KINDS = ("forge", "registry")
_CHECKED = re.compile(rb"(?:gh[pousr]|npm)_([A-Za-z0-9]{30})([A-Za-z0-9]{6})(?![A-Za-z0-9])")
_BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"

KINDS = (*BASE_KINDS, *CHECKED_KINDS)
_RANK = {k: i for i, k in enumerate(KINDS)}


def base62_crc(body: bytes) -> bytes:
    """The checksum digits of a token's random part."""
    n, out = zlib.crc32(body), ""
    for _ in range(6):
        n, r = divmod(n, 62)
        out = _BASE62[r] + out
    return out.encode()


@lru_cache(maxsize=1)
def _automaton():
    import ahocorasick

    found = ahocorasick.Automaton()
    for key in ASSIGN_KEYS:
        found.add_word(key, ("assign", len(key)))
    found.add_word("akia", ("access", 4))
    for key, kind in CHECKED.items():
        found.add_word(key, (kind, len(key)))
    found.make_automaton()
    return found


def _byte_spans(raw: bytes) -> list[tuple[int, int, str]]:
    spans: list[tuple[int, int, str]] = []
    free = dict.fromkeys(KINDS, 0)  # where the next match of a kind may begin
    # one character per byte, so the automaton's places are byte places
    for last, (kind, size) in _automaton().iter(raw.lower().decode("latin-1")):
        at = last + 1 - size
        if at < free[kind]:
            continue
        if kind == "assign":
            if m := _ASSIGN.match(raw, at):
                free[kind] = m.end()
                if m.end(1) - m.start(1) >= ASSIGN_MIN:
                    spans.append((at, m.end(), kind))
        elif kind == "access":
            if m := _ACCESS.match(raw, at):
                free[kind] = m.end()
                if m.end() - at >= ACCESS_MIN:
                    spans.append((at, m.end(), kind))
        elif (m := _CHECKED.match(raw, at)) and base62_crc(m[1]) == m[2]:
            free[kind] = m.end()
            spans.append((at, m.end(), kind))
    spans += [(m.start(), m.end(), "hex") for m in _HEX.finditer(raw)]
    return spans


def find_secrets(text: str | None) -> list[tuple[str, int, int]]:
    """``(kind, start, end)`` of every secret, by start and then in the order of :data:`KINDS`."""
    if not text:
        return []
    raw = text.encode("utf-8", "surrogatepass")
    spans = sorted(_byte_spans(raw), key=lambda s: (s[0], _RANK[s[2]]))
    if len(raw) == len(text):
        return [(k, a, b) for a, b, k in spans]
    out, at, seen = [], 0, 0  # code points are counted once, from span to span
    for a, b, k in spans:
        seen += _points(raw[at:a])
        at = a
        out.append((k, seen, seen + _points(raw[a:b])))
    return out


def _points(raw: bytes) -> int:
    return len(raw) if raw.isascii() else len(raw.decode("utf-8", "surrogatepass"))


def digest(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def _kernel(texts: list) -> list[list]:
    found = [find_secrets(t) for t in texts]
    count = [[sum(k == kind for k, _, _ in s) for s in found] for kind in BASE_KINDS]
    base = [hashlib.sha256(digest([x for x in s if x[0] in BASE_KINDS]).encode()).hexdigest() for s in found]
    return [*count, base, [digest(s) for s in found]]


def scan_secrets(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """``docs`` with ``n_assign``, ``n_access``, ``n_hex``, ``base_sha256`` and ``spans`` as last columns.

    Where a kept column has one of these names (in any case), the new one takes underscores until it is free.
    """
    keep = docs.columns if keep is None else keep
    names = free_names(keep, *(f"n_{k}" for k in BASE_KINDS), "base_sha256", "spans")
    fields = [T.StructField(n, T.LongType() if i < len(BASE_KINDS) else T.StringType()) for i, n in enumerate(names)]
    return map_texts(docs, "text", fields, _kernel, keep)


def mask_secrets(text: str | None, mark: str = "[{kind}]") -> str | None:
    """The text with its secrets replaced; where spans overlap, the earlier one covers."""
    if text is None:
        return None
    out, at = [], 0
    for kind, a, b in find_secrets(text):
        if a >= at:
            out += [text[at:a], mark.format(kind=kind)]
        at = max(at, b)
    return "".join([*out, text[at:]])
