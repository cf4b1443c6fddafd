"""Text helpers: words, labels, urls, html, hashed word vectors, string similarity."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Labels too generic to say which variable a column holds.
VAGUE_LABELS = ("attribute", "variable", "name", "id", "key", "value", "type", "code", "text", "date", "number", "comment", "description", "index", "label", "data", "field", "column")


def words(text: Column) -> Column:
    """Lower-cased runs of letters, two or more characters each."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}]+"), lambda w: F.char_length(w) >= 2)


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags replaced by blanks."""
    out = F.regexp_replace(F.regexp_replace(html, r"(?is)<script[^>]*>.*?</script>", " "), r"(?is)<style[^>]*>.*?</style>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(out, r"(?s)<[^>]*>", " "), r"\s+", " "))


def url_host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1))


def plain_label(name: Column) -> Column:
    """A column's name without its table prefix (letters and an underscore)."""
    return F.regexp_replace(name, r"^[a-z]+_", "")


def tokenize_label(name: Column) -> Column:
    """Words of a label: split at case changes and anything but letters."""
    spaced = F.regexp_replace(name, r"([a-z])([A-Z])", "$1 $2")
    return F.filter(F.split(F.lower(spaced), r"[^a-z]+"), lambda w: F.char_length(w) > 0)


def jaro_winkler_text(a: str | None, b: str | None, scale: float = 0.1) -> float | None:
    """Jaro-Winkler similarity with a common prefix of up to four characters."""
    if a is None or b is None:
        return None
    if a == b:
        return 1.0
    reach = max(len(a), len(b)) // 2 - 1
    free, met = [True] * len(b), []
    for i, x in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if free[j] and b[j] == x:
                free[j] = False
                met.append(x)
                break
    m = len(met)
    if not m:
        return 0.0
    other = [y for j, y in enumerate(b) if not free[j]]
    swaps = sum(x != y for x, y in zip(met, other, strict=True)) // 2
    jaro = (m / len(a) + m / len(b) + (m - swaps) / m) / 3
    prefix = 0
    for x, y in zip(a[:4], b[:4], strict=False):
        if x != y:
            break
        prefix += 1
    return jaro + (prefix * scale * (1 - jaro) if jaro >= 0.7 else 0.0)


def jaro_winkler_udf():
    """The similarity as an Arrow function; made when used, since that needs a session."""

    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([jaro_winkler_text(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

    return F.pandas_udf(run, "double")


def jaro_winkler(a: Column | str, b: Column | str) -> Column:
    return jaro_winkler_udf()(a, b)


# ------------------------------------------------------------------ hashed word vectors


@lru_cache(maxsize=500_000)
def _gram_digest(gram: str, width: int, seed: int) -> bytes:
    return hashlib.shake_128(f"{seed}|{gram}".encode()).digest(width)


@lru_cache(maxsize=200_000)
def hashed_word_vector(word: str, width: int = 300, seed: int = 1) -> np.ndarray:
    """A vector from the word's character 3- to 5-grams and the word itself; needs no training and knows any word."""
    marked = f"<{word}>"
    grams = {marked} | {marked[i : i + n] for n in (3, 4, 5) for i in range(len(marked) - n + 1)}
    raw = np.frombuffer(b"".join([_gram_digest(g, width, seed) for g in grams]), np.int8).reshape(-1, width)
    return raw.sum(axis=0, dtype=np.int64) / (74.0 * np.sqrt(len(grams)))
