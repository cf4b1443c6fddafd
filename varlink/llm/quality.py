"""Operator 1: quality rules with adaptive thresholds.

Every document is measured. The measures of the documents that pass the base rules go into relative-error bucket
sketches (counts of logarithmic buckets), which merge by adding counts in any order: one sketch per measure for each
(language, source), merged upwards per language and for the whole corpus. Fences computed from the sketches replace fixed
cutoffs; they are joined to the documents, which are then filtered.

A fence lies ``reach`` times the distance of the median and an outer decile from the median, on that side. Medians and
distances of a group are weighted means of its own and its language's, which are weighted means of its own and the
corpus's; the corpus's part counts like ``prior`` documents. A document is a sample of what its writer does, so it goes
only when its measure is beyond the fence by more than ``errors`` standard errors of a count. No distance on a measure's
own scale is a parameter.

Edge cases: a null text is an empty one (no words, base rules fail); a null language or source counts as ``''``;
repeated rows are each judged alike and each counts; a group without a document that passes the base rules has no
fences, and none of its documents needs them; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ASCII_SPACE_CHARS, cut, fresh, map_texts

_SYMBOLS = b"#*$%&|<>"
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")


#: The fenced measures: name, count, units that it is divided by, how many a single event adds to the count, fenced below too.
#: The least repeat of a three-word window marks six words.
MEASURES = (
    ("word_length", "word_chars", "n_words", 1, True),
    ("symbol_rate", "n_symbols", "n_words", 1, False),
    ("dup_line_share", "n_dup_lines", "n_lines", 1, False),
    ("repeat_share", "n_repeat_words", "n_words", 6, False),
)


@dataclass(frozen=True)
class QualityRules:
    """Parameters of the base rules and of the adaptive ones (see the module's text)."""

    min_words: int = 50
    max_repeat_percent: int = 50
    accuracy: float = 0.01
    reach: float = 4.0
    prior: float = 50.0
    errors: float = 2.0

    @property
    def gamma(self) -> float:
        return (1 + self.accuracy) / (1 - self.accuracy)


RULES = QualityRules()


def count_repeats(words: list[bytes]) -> int:
    """Words inside 3-word windows that occur at least twice in ``words``."""
    n = len(words)
    if n < 4:
        return 0
    index: dict[bytes, int] = {}
    ids = np.fromiter((index.setdefault(w, len(index)) for w in words), np.int64, n)
    v = len(index)
    pairs = ids[:-1] * v + ids[1:]
    if v >= 1 << 20:  # the triple would not fit in 63 bits
        pairs = np.unique(pairs, return_inverse=True)[1].astype(np.int64)
    keys = pairs[:-1] * v + ids[2:]
    order = np.argsort(keys, kind="stable")
    ranked = keys[order]
    same = ranked[1:] == ranked[:-1]
    if not same.any():
        return 0
    twice = np.zeros(n - 2, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    mark = np.zeros(n, bool)
    for k in range(3):
        mark[k : n - 2 + k] |= twice
    return int(mark.sum())


def measure_text(text: str | None) -> tuple[int, ...]:
    """The counts named in :data:`COUNTS` for one text."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()  # of bytes: exactly the ASCII white space
    spaces = sum(raw.count(c) for c in (b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r"))
    lines = [x for x in text.split("\n") if x.strip(ASCII_SPACE_CHARS)]
    return len(words), len(text) - spaces, sum(raw.count(_SYMBOLS[i : i + 1]) for i in range(len(_SYMBOLS))), len(lines) - len(set(lines)), count_repeats(words), len(lines)


def _kernel(texts: list) -> list[list]:
    return list(map(list, zip(*map(measure_text, texts), strict=True))) if texts else [[] for _ in COUNTS]


def measure(docs: DataFrame, names: list[str], text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``docs`` with the counts of :data:`COUNTS` as columns ``names``."""
    return map_texts(docs, text, [T.StructField(n, T.LongType()) for n in names], _kernel, keep)


def measures(count: dict[str, Column]) -> dict[str, Column]:
    """The fenced measures, from the columns of the counts."""
    return {k: F.when(count[n] > 0, count[c].cast("double") / count[n]).otherwise(F.lit(0.0)) for k, c, n, _, _ in MEASURES}


def error_of(count: dict[str, Column], measure: str) -> Column:
    """Standard error of a measure: a count of events that add ``unit`` each has the variance ``unit * count``."""
    _, c, n, unit, _ = next(m for m in MEASURES if m[0] == measure)
    return F.when(count[n] > 0, F.sqrt(unit * count[c].cast("double")) / count[n]).otherwise(F.lit(0.0))


def beyond(count: dict[str, Column], fence, rules: QualityRules = RULES) -> dict[str, Column]:
    """For each measure, whether it is surely outside the fences that ``fence(measure, side)`` gives."""
    values, out = measures(count), {}
    for k, _, _, _, below in MEASURES:
        room = F.lit(rules.errors) * error_of(count, k)
        out[k] = values[k] - room > fence(k, "high")
        if below:
            out[k] = out[k] | (values[k] + room < fence(k, "low"))
        out[k] = F.coalesce(out[k], F.lit(False))
    return out


def base_failed(count: dict[str, Column], rules: QualityRules = RULES) -> Column:
    return (count["n_words"] < rules.min_words) | (100 * count["n_repeat_words"] > rules.max_repeat_percent * count["n_words"])


def sketch(measured: DataFrame, group: list[Column], values: dict[str, Column], rules: QualityRules = RULES) -> DataFrame:
    """Bucket sketches: rows ``lang, source, measure, bucket, n``. Add ``n`` per key to merge two of them."""
    ln = math.log(rules.gamma)
    pairs = F.array(*[F.struct(F.lit(k).alias("measure"), F.when(v > 0, F.ceil(F.ln(v) / ln)).cast("int").alias("bucket")) for k, v in values.items()])
    return measured.select(group[0].alias("lang"), group[1].alias("source"), F.inline(pairs)).groupBy("lang", "source", "measure", "bucket").agg(F.count("*").alias("n"))


def merge_sketches(*sketches: DataFrame) -> DataFrame:
    whole = sketches[0]
    for s in sketches[1:]:
        whole = whole.unionByName(s)
    return whole.groupBy("lang", "source", "measure", "bucket").agg(F.sum("n").alias("n"))


def quartiles(sketches: DataFrame, rules: QualityRules = RULES) -> DataFrame:
    """Outer deciles, quartiles and median of every sketch and of the sketches merged per language and over all:
    ``level`` 0, 1 and 3.

    A null bucket holds the zeros. The windows see the buckets of one group, a few hundred rows at most.
    """
    levels = sketches.groupingSets([["lang", "source", "measure", "bucket"], ["lang", "measure", "bucket"], ["measure", "bucket"]], "lang", "source", "measure", "bucket").agg(
        (F.grouping("lang") * 2 + F.grouping("source")).cast("int").alias("level"), F.sum("n").alias("n")
    )
    key = ["level", "lang", "source", "measure"]
    g = rules.gamma
    value = F.coalesce(F.lit(2.0) * F.pow(F.lit(g), F.col("bucket")) / (g + 1), F.lit(0.0))
    run = Window.partitionBy(*key).orderBy(F.col("bucket").asc_nulls_first())
    ranked = levels.withColumns({"upto": F.sum("n").over(run), "total": F.sum("n").over(Window.partitionBy(*key)), "value": value})
    # the q-quantile: value of the first bucket whose cumulative count reaches q * total
    at = lambda percent: F.min(F.when(F.col("upto") * 100 >= percent * F.col("total"), F.col("value")))
    return ranked.groupBy(*key).agg(F.max("total").alias("n"), at(10).alias("q10"), at(25).alias("q1"), at(50).alias("q50"), at(75).alias("q3"), at(90).alias("q90"))


def fence_rows(sketches: DataFrame, rules: QualityRules = RULES) -> DataFrame:
    """``lang, source, measure, n, own, low, high``: the fences of every group, and the weight that its own sketch has."""
    q = quartiles(sketches, rules).select("level", "lang", "source", "measure", "n", F.col("q50").alias("mid"), (F.col("q90") - F.col("q50")).alias("up"), (F.col("q50") - F.col("q10")).alias("down"))
    part = lambda level, tag, *keys: q.filter(F.col("level") == level).select(*keys, "measure", *[F.col(c).alias(f"{c}{tag}") for c in ("n", "mid", "up", "down")])
    met = part(0, 0, "lang", "source").join(part(1, 1, "lang"), ["lang", "measure"]).join(part(3, 3), "measure")
    toward = lambda n, own, above: (F.col(n) * own + F.lit(rules.prior) * above) / (F.col(n) + F.lit(rules.prior))
    mid, up, down = (toward("n0", F.col(f"{c}0"), toward("n1", F.col(f"{c}1"), F.col(f"{c}3"))) for c in ("mid", "up", "down"))
    return met.select("lang", "source", "measure", F.col("n0").alias("n"), (F.col("n0") / (F.col("n0") + F.lit(rules.prior))).alias("own"), (mid - F.lit(rules.reach) * down).alias("low"), (mid + F.lit(rules.reach) * up).alias("high"))


def fences(sketches: DataFrame, rules: QualityRules = RULES) -> DataFrame:
    """One row per (lang, source): the fences ``<measure>_low`` and ``<measure>_high`` of every measure."""
    chosen = fence_rows(sketches, rules)
    return chosen.groupBy("lang", "source").agg(*[F.max(F.when(F.col("measure") == k, F.col(c))).alias(f"{k}_{c}") for k, *_ in MEASURES for c in ("low", "high")])


def group_columns() -> list[Column]:
    return [F.coalesce(F.col(c).cast("string"), F.lit("")) for c in ("lang", "source")]


def fences_of(measured: DataFrame, counts: list[str], rules: QualityRules = RULES) -> DataFrame:
    """The fences (written) of measured documents, whose counts have the names ``counts``."""
    count = {k: F.col(f"`{c}`") for k, c in zip(COUNTS, counts, strict=True)}
    return cut(fences(sketch(measured.filter(~base_failed(count, rules)), group_columns(), measures(count), rules), rules), "quality-fences")


def judge(docs: DataFrame, rules: QualityRules = RULES, keep: list[str] | None = None, report: bool = False) -> tuple[DataFrame, list[str], str, str]:
    """Measured documents with their verdicts.

    Returns the columns ``keep`` of ``docs`` (all by default) with the counts, ``base_failed`` and ``kept`` under the
    returned names, which clash with no column of ``docs``; with ``report``, also an array of the measures that are
    beyond a fence, as a last column named after ``kept`` with ``_by``. Narrow rows are measured once and written to the
    shared folder; where ``keep`` has the texts, they are measured a second time rather than written.
    """
    names = fresh(docs, *COUNTS, "failed", "kept", "lang", "source")
    counts, failed, kept, g_lang, g_source = names[: len(COUNTS)], *names[len(COUNTS) :]
    keep = docs.columns if keep is None else keep
    groups = ["lang", "source"]
    measured = measure(docs, counts, keep=list(dict.fromkeys([*keep, *groups])))
    if "text" in keep:
        table = fences_of(measure(docs, counts, keep=groups), counts, rules)
    else:
        measured = cut(measured, "quality-measured")
        table = fences_of(measured, counts, rules)
    count = {k: F.col(f"`{c}`") for k, c in zip(COUNTS, counts, strict=True)}
    table = table.withColumnsRenamed({"lang": g_lang, "source": g_source} | {c: f"__{c}" for c in table.columns if c not in groups})
    by = beyond(count, lambda k, side: F.col(f"__{k}_{side}"), rules)
    inside = F.lit(True)
    for said in by.values():
        inside = inside & ~said
    group = group_columns()
    # one row a group; Spark knows the size of the written table
    joined = measured.join(table, (group[0] == F.col(g_lang)) & (group[1] == F.col(g_source)), "left")
    out = joined.withColumn(failed, base_failed(count, rules)).withColumn(kept, ~F.col(failed) & inside)
    reasons = [F.filter(F.array(*[F.when(said, F.lit(k)) for k, said in by.items()]), lambda x: x.isNotNull()).alias(f"{kept}_by")] if report else []
    return out.select(*[F.col(f"`{c}`") for c in [*keep, *counts, failed, kept]], *reasons), counts, failed, kept


def rejections(docs: DataFrame, rules: QualityRules = RULES) -> DataFrame:
    """``rule, lang, source, documents``: how many documents each rule rejects in each group (several may reject one)."""
    judged, _, failed, kept = judge(docs, rules, ["lang", "source"], report=True)
    rule = F.explode(F.when(F.col(failed), F.array(F.lit("base"))).otherwise(F.col(f"{kept}_by")))
    return judged.select(*[c.alias(n) for c, n in zip(group_columns(), ("lang", "source"), strict=True)], rule.alias("rule")).groupBy("rule", "lang", "source").agg(F.count("*").alias("documents"))


def quality_filter(docs: DataFrame, rules: QualityRules = RULES) -> DataFrame:
    """The rows of ``docs`` that pass the base rules and the adaptive fences, with the columns of ``docs``."""
    judged, _, _, kept = judge(docs, rules)
    return judged.filter(F.col(kept)).select(*[F.col(f"`{c}`") for c in docs.columns])
