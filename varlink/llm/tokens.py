"""Operator 2: token counts, with overlap resynchronisation for huge documents.

Ordinary documents are counted by their white-space pieces through a bounded memo. A document of more than
``chunk_chars`` is encoded in overlapping chunks with offsets; two neighbouring encodings are spliced at a boundary that
both have and that is proven stable. An overlap without such a boundary is widened, and so is one in which the two
encodings do not agree on the tokens between the boundary and the last stable point of the first.

A point of the text is stable when what stands on one side of it cannot change the tokens on the other. For the tokenizer
used here (normal form C, white space squeezed, lower case; words of letters, single digits, runs of other signs and
seven contractions) that holds after ASCII white space, before a digit, and between a letter and punctuation: no
alternative of its pattern matches across them, punctuation and digits never compose with what precedes them, and the
one letter whose lower case ends in a mark (U+0130) is left out, as are points inside a special string. The points are
found in the text before anything is encoded, so every character is encoded about once, whatever the text is made of;
only a run of letters alone is longer in memory than a chunk, since it is one word to the library too.

Edge cases: null and empty texts have 0 tokens and 0 bytes; repeated rows are counted alike; columns of the input that have
the name of a result keep their values, and the result then takes a name of its own (see :func:`token_counts`); an empty
table gives an empty result.
"""

from __future__ import annotations

import re
from functools import lru_cache

import regex
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import free_names, map_texts

#: A text is first cut into pieces at these characters, which every pre-tokenizer used here treats as white space.
_PIECE = re.compile(r"[^ \t\n\r]+")
#: Characters that begin right of a stable point.
_STABLE = regex.compile(r"(?<=[ \t\n\r])[^ \t\n\r]|\p{N}|(?<=[\p{L}--\u0130])\p{P}", regex.V1)
_MEMO_PIECE, _MEMO_SIZE = 48, 400_000


@lru_cache(maxsize=2)
def load_tokenizer(path: str):
    """The tokenizer as its library reads it, without truncation or padding."""
    from tokenizers import Tokenizer

    made = Tokenizer.from_file(path)
    made.no_truncation()
    made.no_padding()
    return made


class TokenCounter:
    """Counts tokens as the library does, in bounded memory for texts of any length."""

    def __init__(self, path: str, chunk_chars: int = 32_768, overlap_chars: int = 512):
        if overlap_chars >= chunk_chars:
            raise ValueError("the overlap must be shorter than the chunk")
        self.tokenizer = load_tokenizer(path)
        self.chunk, self.overlap = chunk_chars, overlap_chars
        self.memo: dict[str, int] = {}
        self.widened = 0
        special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.inside = {t[i : i + 2] for t in special for i in range(len(t) - 1)}

    def encode(self, text: str):
        return self.tokenizer.encode(text, add_special_tokens=False)

    def piece(self, text: str) -> int:
        """Tokens of a piece without white space; pieces are independent of what surrounds them."""
        n = len(self.encode(text).ids)
        if len(text) <= _MEMO_PIECE:
            if len(self.memo) >= _MEMO_SIZE:
                self.memo.clear()
            self.memo[text] = n
        return n

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if len(text) > self.chunk:
            return self.count_long(text)
        memo, total = self.memo, 0
        for p in _PIECE.findall(text):
            n = memo.get(p)
            total += self.piece(p) if n is None else n
        return total

    # ------------------------------------------------------------ huge documents

    def count_long(self, text: str) -> int:
        """Tokens of ``text``, encoded chunk by chunk."""
        return sum(len(ids) for ids, _ in self.spliced(text))

    def stable_points(self, text: str, low: int, high: int) -> list[int]:
        """The stable points ``p`` of ``text`` with ``low < p < high``."""
        found = (m.start() for m in _STABLE.finditer(text, low + 1, high))  # a look behind sees what stands before
        return [p for p in found if text[p - 1 : p + 1] not in self.inside]

    def cover(self, text: str, left: int, size: int) -> int:
        """Where a chunk that begins at ``left`` ends: after ``size`` characters, or as many times two of them as it takes
        to reach a stable point, or with the text."""
        seen, end = left, left + size
        while end < len(text) and not self.stable_points(text, seen, end):
            seen, end = end - 1, left + 2 * (end - left)
        return min(end, len(text))

    def spliced(self, text: str):
        """Yield ``(ids, offsets)`` runs that together are the encoding of ``text``; offsets are into ``text``."""
        start = left = 0  # where the chunk begins; the first offset not yet given out
        end = self.cover(text, left, self.chunk)
        now = self.encode(text[:end])
        while end < len(text):
            found = self.resync(text, now, start, end, left)
            if found is None:  # no agreement in the whole chunk: take a longer one
                start, end = left, self.cover(text, left, 2 * (end - left))
                now = self.encode(text[start:end])
                continue
            at, after, begin, stop = found
            yield self.run(now, start, left, at)
            now, start, left, end = after, begin, at, stop
        yield self.run(now, start, left, len(text))

    def resync(self, text: str, now, start: int, end: int, left: int):
        """The next chunk and the boundary where it is spliced on; the overlap widens until one is found."""
        width = self.overlap
        while True:
            begin = max(left, end - width)
            points = self.stable_points(text, begin, end)
            if points:
                at = points[len(points) // 2]  # leaves text on both sides of it to compare
                stop = self.cover(text, at, self.chunk)
                after = self.encode(text[begin:stop])
                if self.agree(now, start, after, begin, at, points[-1]):
                    return at, after, begin, stop
            if begin == left:
                return None
            self.widened += 1
            width *= 2

    @staticmethod
    def run(encoding, base: int, low: int, high: int):
        """The tokens of ``encoding`` that begin in ``[low, high)`` of the whole text."""
        kept = [(i, (a + base, b + base)) for i, (a, b) in zip(encoding.ids, encoding.offsets, strict=True) if low <= a + base < high]
        return [i for i, _ in kept], [o for _, o in kept]

    def agree(self, now, start: int, after, begin: int, at: int, sure: int) -> bool:
        """Whether both encodings have a boundary at ``at`` and the same tokens from there to ``sure``."""
        for encoding, base in ((now, start), (after, begin)):
            if any(a + base < at < b + base for a, b in encoding.offsets):
                return False
        return self.run(now, start, at, sure) == self.run(after, begin, at, sure)


_COUNTERS: dict[tuple, TokenCounter] = {}


def token_counts(docs: DataFrame, path: str, limit: int = 2048, chunk_chars: int = 32_768, overlap_chars: int = 512, keep: list[str] | None = None) -> DataFrame:
    """``docs`` with ``n_bytes``, ``n_tokens`` and ``over_limit``; ``path`` names the tokenizer file on every machine.

    The three are the last columns. Where a kept column has one of their names (in any case), the new one takes
    underscores at its end until it is free.
    """

    def kernel(texts: list) -> list[list]:
        key = (path, chunk_chars, overlap_chars)
        if key not in _COUNTERS:
            _COUNTERS[key] = TokenCounter(*key)
        counts = [_COUNTERS[key].count(t) for t in texts]
        return [[len((t or "").encode("utf-8", "surrogatepass")) for t in texts], counts, [n > limit for n in counts]]

    keep = docs.columns if keep is None else keep
    names = free_names(keep, "n_bytes", "n_tokens", "over_limit")
    fields = [T.StructField(n, t) for n, t in zip(names, (T.LongType(), T.LongType(), T.BooleanType()), strict=True)]
    return map_texts(docs, "text", fields, kernel, keep)
