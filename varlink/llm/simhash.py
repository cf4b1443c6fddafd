"""Operator 7: SimHash near-duplicates by deletion-variant signatures.

A document's 64-bit fingerprint takes the majority of each bit over the hashes of its word shingles. Two fingerprints
link when at most ``radius`` = 2 bits differ. They are cut into ``radius // 2 + 1`` = 2 segments, so that in one of them
at most one bit differs: every segment is indexed under its variants with one bit wildcarded, equal variants are joined,
and the candidates are verified by their whole distance.

Work goes by distinct fingerprints, so exact copies are one row each, however many there are. A variant that more than
``bucket_limit`` fingerprints share gets no pairs: its members are linked exactly through their one-bit neighbourhoods
(two words differ by at most two bits just when some word is within one bit of both), each neighbourhood as a star, which
takes rows in proportion to the members. Components come from alternating large-star and small-star steps over the
links, with a written table after each.

Edge cases: a text of fewer words than a shingle is one shingle, one without words (also a null one) has fingerprint zero
and is linked like any other; repeated rows get the same answer; documents without ``doc_id`` take part, but never name
a component (one made of such rows only has a null id); an empty table gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, drop_cut, fresh, map_texts

SHINGLE, RADIUS, SEED, BUCKET_LIMIT = 3, 2, 42, 24
FINGERPRINTS_PER_TASK = 100_000
_HALF = 32


def fingerprint(text: str | None, size: int = SHINGLE, seed: int = SEED) -> int:
    """The fingerprint of one text, as an unsigned number."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # of bytes: ASCII only
    if not words:
        return 0
    shingles = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False)) if len(words) >= size else [b" ".join(words)]
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(s, seed) for s in shingles), np.uint64)
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 65_536):  # a bounded table of bits for any length
        part = hashes[at : at + 65_536].astype("<u8").view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(sum(1 << int(i) for i in np.flatnonzero(counts * 2 > len(hashes))))


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def kernel(texts: list) -> list[list]:
    return [[_signed(fingerprint(t)) for t in texts]]


def add_fingerprints(docs: DataFrame, name: str, keep: list[str] | None = None) -> DataFrame:
    """``docs`` with the fingerprint as a signed 64-bit number in column ``name``."""
    return map_texts(docs, "text", [T.StructField(name, T.LongType())], kernel, keep)


# ---------------------------------------------------------------------- links


def segment_variants(prints: DataFrame) -> DataFrame:
    """The index: ``fp, segment, wild, rest`` with one wildcarded bit per row, 64 rows a fingerprint."""
    high, low = F.shiftrightunsigned(F.col("fp"), _HALF), F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF))
    bits = F.sequence(F.lit(0), F.lit(_HALF - 1))

    def wild(segment: int, value):
        return F.transform(bits, lambda i: F.struct(F.lit(segment).cast("tinyint").alias("segment"), i.cast("tinyint").alias("wild"), value.bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("bigint"), i).bitwiseXOR(F.lit(-1).cast("bigint"))).alias("rest")))

    return prints.select("fp", F.inline(F.concat(wild(0, high), wild(1, low))))


def neighbourhoods(prints: DataFrame) -> DataFrame:
    """``fp, word`` for each of the 65 words within one bit of ``fp``."""
    flips = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.col("fp").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), i)))
    return prints.select("fp", F.explode(F.concat(F.array(F.col("fp")), flips)).alias("word"))


def distance(a, b):
    return F.bit_count(a.bitwiseXOR(b))


def find_links(prints: DataFrame, bucket_limit: int = BUCKET_LIMIT, radius: int = RADIUS) -> DataFrame:
    """Links ``a < b`` between the distinct fingerprints ``fp`` of ``prints`` that connect all pairs within ``radius``.

    Every pair in a variant of up to ``bucket_limit`` members is a link of its own; in larger ones the links are the
    stars of the neighbourhoods, which join the same fingerprints.
    """
    if radius != 2:
        raise ValueError("two segments and one wildcard cover a radius of 2")
    key = ["segment", "wild", "rest"]
    # every fingerprint becomes 64 rows, so they are dealt out first, at most so many to a task
    slots = max(int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions")), math.ceil(prints.count() / FINGERPRINTS_PER_TASK))
    prints = prints.repartition(slots, "fp")
    variants = segment_variants(prints)
    # Only variants with company are kept: one sort of numbers, and no group of them is ever gathered.
    sizes = cut(variants.groupBy(*key).agg(F.count("*").alias("n")).filter("n > 1"), "simhash-variants")
    shared = variants.join(sizes, key)
    few = shared.filter(F.col("n") <= bucket_limit).select("fp", *key)
    many = shared.filter(F.col("n") > bucket_limit).select("fp").distinct()
    pairs = few.select(F.col("fp").alias("a"), *key).join(few.select(F.col("fp").alias("b"), *key), key).filter((F.col("a") < F.col("b")) & (distance(F.col("a"), F.col("b")) <= radius)).select("a", "b")
    around = neighbourhoods(many)
    heads = around.groupBy("word").agg(F.min("fp").alias("a"), F.count("*").alias("n")).filter("n > 1")
    stars = around.join(heads, "word").select("a", F.col("fp").alias("b")).filter("a < b")
    return pairs.unionByName(stars).distinct()


def components(links: DataFrame) -> DataFrame:
    """``node, root``: each node of ``links`` (``a, b``) with the smallest node that can be reached from it."""
    now = cut(links, "component-links")
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        # large star: the larger neighbours of a node go to its smallest neighbour
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.filter("b > a").join(least, "a").select(F.col("m").alias("a"), "b").filter("a < b").distinct()
        # small star: the smaller neighbours of a node, and the node, go to its smallest neighbour
        low = large.groupBy("b").agg(F.min("a").alias("m"))
        small = large.join(low, "b").select(F.col("m").alias("a"), F.explode(F.array("a", "b")).alias("b")).filter("a < b").distinct()
        then = cut(small, "component-links")
        changed = then.exceptAll(now).unionByName(now.exceptAll(then)).limit(1).count()
        drop_cut(now)
        now = then
        if not changed:
            break
    return now.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("root"))


def group_near_copies(docs: DataFrame, bucket_limit: int = BUCKET_LIMIT, keep: list[str] | None = None) -> tuple[DataFrame, str, str]:
    """``docs`` (or its columns ``keep``) with fingerprint and component id, under the returned names.

    The narrow rows (``doc_id`` and fingerprint) are written once; texts are read again only when ``keep`` has them, and
    then carry their fingerprint through one join with the table of fingerprints.
    """
    keep = docs.columns if keep is None else keep
    fp, comp = fresh(docs, "fingerprint", "component")
    carry = list(dict.fromkeys([*keep, "doc_id"]))
    printed = cut(add_fingerprints(docs, fp, carry), "simhash-docs")
    prints = cut(printed.groupBy(F.col(fp).alias("fp")).agg(F.min("doc_id").alias("first_doc")), "simhash-prints")
    roots = cut(components(find_links(prints.select("fp"), bucket_limit)), "simhash-roots")
    rooted = prints.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "first_doc")
    names = rooted.groupBy("root").agg(F.min("first_doc").alias(comp))
    (own,) = fresh(docs, "own_fingerprint")
    named = rooted.join(names, "root").select(F.col("fp").alias(own), comp)
    out = printed.join(named, F.col(fp) == F.col(own)).select(*[F.col(f"`{c}`") for c in keep], fp, comp)
    return out, fp, comp


def keep_first(grouped: DataFrame, fp: str, comp: str, columns: list[str]) -> DataFrame:
    """One row of every component of ``grouped``: the one with the smallest ``doc_id``.

    Of rows that repeat this ``doc_id`` one stays. Rows without ``doc_id`` stay only where no row of their component has
    one, and then one of them.
    """
    (twice,) = fresh(grouped, "copies")
    chosen = grouped.filter(F.col("doc_id").eqNullSafe(F.col(comp)))
    single = chosen.filter("doc_id IS NOT NULL")
    repeated = single.groupBy(F.col("doc_id").alias(twice)).agg(F.count("*").alias("n")).filter("n > 1").select(twice)
    alone = single.join(repeated, F.col("doc_id") == F.col(twice), "left_anti")
    again = single.join(repeated, F.col("doc_id") == F.col(twice), "left_semi").dropDuplicates(["doc_id"])
    nameless = chosen.filter("doc_id IS NULL").dropDuplicates([fp])
    return alone.unionByName(again).unionByName(nameless).select(*[F.col(f"`{c}`") for c in columns])


def drop_near_copies(docs: DataFrame, bucket_limit: int = BUCKET_LIMIT) -> DataFrame:
    """One document of every component: the one with the smallest ``doc_id`` (see :func:`keep_first`)."""
    grouped, fp, comp = group_near_copies(docs, bucket_limit)
    return keep_first(grouped, fp, comp, docs.columns)
