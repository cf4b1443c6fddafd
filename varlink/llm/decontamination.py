"""Operator 9: benchmark decontamination with a distributed positional inverted index. DataFrame functions only.

1. Corpus frequencies of the words that the benchmark uses (words are counted as they are written, so no text has to be
   lower-cased; the counts are pre-aggregated).
2. Of each window of an item (``size`` consecutive words; a shorter item is one window) the two rarest words are its
   anchors. A window with a word that the corpus lacks can have no exact match: its anchors are the two rarest of those
   that there are, for proximity only.
3. The postings ``term, document, position`` of the anchors are stored as a table.
4. The list of each window's rarest anchor is read, and the list of the other one is only probed in the documents and near
   the places that the first gives, so frequent words are never multiplied by the windows that have them. Where both are
   as far apart as in the item, the window is a candidate for an exact match.
5. Candidates are compared word by word, which leaves the exact phrase matches.
6. Where both anchors are apart as in the item but for ``SLACK`` words, the window is a proximity match; an item with as
   many of them as ``NEAR_SHARE`` of its anchor pairs is near. Words added, left out or changed inside a passage do
   not hide it there. :func:`proximity_matches` answers for any other pairs of terms from the same postings.

A document is known by its ``doc_id`` and the hash of its text, so repeated ids with other texts do not mix. The tables
that grow with the benchmark are joined without hints: Spark broadcasts them only below its size threshold. A frequent
term's postings are rows keyed by document, never one list, so no task gets all of them.

Edge cases: null texts have no words; items without words or with a null id have no windows; several rows of one item id
count as one item; rows with a null ``doc_id`` are searched too; an empty benchmark leaves all documents clean.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, cut, fresh

SIZE = 10
#: By how many words the anchors of a proximity match may be nearer or further apart, and which share of an item's pairs
#: of anchors must lie so in a document for the item to be near.
SLACK, NEAR_SHARE = 2, 0.5
#: What lies between words, before lower-casing: ASCII other than letters and digits.
_GAP = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def raw_words(text: Column) -> Column:
    """The words as written; null texts have none."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), _GAP), "")


def lower_words(text: Column) -> Column:
    return raw_words(ascii_lower(F.coalesce(text, F.lit(""))))


def count_words(text: Column) -> Column:
    return F.size(raw_words(text)).cast("long")


def text_hash(text: Column) -> Column:
    return F.xxhash64(F.coalesce(text, F.lit("")))


def benchmark_items(benchmark: DataFrame) -> DataFrame:
    """``item, item_id, words``: one row per distinct text of an item."""
    items = benchmark.filter("item_id IS NOT NULL").select("item_id", lower_words(F.col("text")).alias("words")).filter(F.size("words") > 0).distinct()
    return items.select(F.xxhash64("item_id", "words").alias("item"), "item_id", "words")


def corpus_terms(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``raw, term, total``: the written forms of the benchmark's words in the corpus, and the words' frequencies."""
    forms = docs.select(F.explode(raw_words(F.col("text"))).alias("raw")).groupBy("raw").agg(F.count("*").alias("n")).withColumn("term", ascii_lower(F.col("raw")))
    used = items.select(F.explode("words").alias("term")).distinct()
    forms = cut(forms.join(used, "term", "left_semi"), "index-terms")
    return forms.select("raw", "term").join(forms.groupBy("term").agg(F.sum("n").alias("total")), "term")


def plan_windows(items: DataFrame, terms: DataFrame, size: int = SIZE) -> DataFrame:
    """``item, at, length, first, second, whole``: the windows, with the places of their two rarest words.

    ``first`` and ``second`` are places in the item; a window of one word has no second. ``whole`` tells that the corpus has
    all words of the window; windows that lack some and have less than two others are left out.
    """
    length = F.least(F.size("words"), F.lit(size))
    starts = items.withColumn("length", length).select("item", "words", "length", F.explode(F.sequence(F.lit(0), F.size("words") - length)).alias("at"))
    places = starts.select("item", "at", "length", F.posexplode(F.slice("words", F.col("at") + 1, F.col("length"))).alias("i", "term"))
    known = places.join(terms.select("term", "total").distinct(), "term", "left")
    rare = F.collect_list(F.when(F.col("total").isNotNull(), F.struct("total", "term", (F.col("at") + F.col("i")).alias("place"))))
    ranked = known.groupBy("item", "at", "length").agg(F.count("total").alias("present"), F.sort_array(rare).alias("rare"))
    whole = F.col("present") == F.col("length")
    return ranked.filter(whole | (F.col("present") > 1)).select("item", "at", "length", F.col("rare")[0]["place"].alias("first"), F.get(F.col("rare"), F.lit(1))["place"].alias("second"), whole.alias("whole"))


def anchor_pairs(items: DataFrame, windows: DataFrame) -> DataFrame:
    """``item, first, second, lead, other``: the distinct places of anchors, and the words there (``other`` may be null)."""
    words = F.col("words")
    places = windows.select("item", "first", "second").distinct().join(items.select("item", "words"), "item")
    return places.select("item", "first", "second", F.get(words, F.col("first")).alias("lead"), F.when(F.col("second").isNotNull(), F.get(words, F.coalesce("second", F.lit(0)))).alias("other"))


def build_postings(docs: DataFrame, forms: DataFrame) -> DataFrame:
    """``term, doc_id, text_hash, pos`` for every occurrence in ``docs`` of the written ``forms`` (``raw, term``)."""
    placed = docs.select("doc_id", text_hash(F.col("text")).alias("text_hash"), F.posexplode(raw_words(F.col("text"))).alias("pos", "raw"))
    return placed.join(forms, "raw").select("term", "doc_id", "text_hash", "pos")


def meet_anchors(postings: DataFrame, pairs: DataFrame, slack: int = SLACK) -> DataFrame:
    """``doc_id, text_hash, item, first, second, diagonal, off``: where the anchors of a pair meet.

    ``diagonal`` is the position in the document at which the item's first word would lie by the first anchor; ``off`` is by
    how many words the second is displaced, at most ``slack``. Positions are joined by their block of ``block`` words.
    """
    block = 4 * slack + 4
    lead = postings.join(pairs, F.col("term") == F.col("lead")).select("doc_id", "text_hash", "item", "first", "second", "other", (F.col("pos") - F.col("first")).alias("diagonal"))
    alone = lead.filter("other IS NULL").select("doc_id", "text_hash", "item", "first", "second", "diagonal", F.lit(0).alias("off"))
    expected = F.col("diagonal") + F.col("second")
    around = F.array_distinct(F.array(F.floor((expected - slack) / block), F.floor((expected + slack) / block)))
    probes = lead.filter("other IS NOT NULL").withColumns({"expected": expected, "block": F.explode(around)}).withColumnsRenamed({"doc_id": "l_doc", "text_hash": "l_hash"})
    listed = postings.withColumn("p_block", F.floor(F.col("pos") / block))
    same = (F.col("l_hash") == F.col("text_hash")) & F.col("l_doc").eqNullSafe(F.col("doc_id")) & (F.col("other") == F.col("term")) & (F.col("block") == F.col("p_block"))
    met = probes.join(listed, same).withColumn("off", (F.col("pos") - F.col("expected")).cast("int")).filter(F.abs("off") <= slack)
    return alone.unionByName(met.select("doc_id", "text_hash", "item", "first", "second", "diagonal", "off"))


def exact_candidates(met: DataFrame, windows: DataFrame) -> DataFrame:
    """``doc_id, text_hash, item, diagonal, windows``: windows of ``item`` with both anchors in place."""
    of = windows.filter("whole").select(F.col("item").alias("w_item"), F.col("first").alias("w_first"), F.col("second").alias("w_second"), F.struct("at", "length").alias("window"))
    here = (F.col("item") == F.col("w_item")) & (F.col("first") == F.col("w_first")) & F.col("second").eqNullSafe(F.col("w_second"))
    fit = met.filter("off = 0").join(of, here).filter(F.col("diagonal") + F.col("window.at") >= 0)
    return fit.groupBy("doc_id", "text_hash", "item", "diagonal").agg(F.collect_set("window").alias("windows"))


def near_items(met: DataFrame, pairs: DataFrame, items: DataFrame, share: float = NEAR_SHARE) -> DataFrame:
    """``doc_id, text_hash, n_near``: how many items are near in a document."""
    both = pairs.filter("other IS NOT NULL").groupBy(F.col("item").alias("p_item")).agg(F.count("*").alias("pairs"))
    found = met.filter("second IS NOT NULL").groupBy("doc_id", "text_hash", "item").agg(F.countDistinct("first", "second").alias("n"))
    near = found.join(both, F.col("item") == F.col("p_item")).filter(F.col("n") >= F.lit(share) * F.col("pairs")).join(items.select("item", "item_id"), "item")
    return near.groupBy("doc_id", "text_hash").agg(F.countDistinct("item_id").alias("n_near"))


def phrase_matches(docs: DataFrame, items: DataFrame, candidates: DataFrame) -> DataFrame:
    """``doc_id, text_hash, item_id, spans``: exact matches as ``start, length`` in words of the document.

    Only candidate documents are split into words again.
    """
    wanted = candidates.join(items, "item").withColumnsRenamed({"doc_id": "c_doc", "text_hash": "c_hash", "words": "item_words"})
    texts = docs.select("doc_id", text_hash(F.col("text")).alias("text_hash"), "text")
    met = texts.join(wanted, F.col("doc_id").eqNullSafe(F.col("c_doc")) & (F.col("text_hash") == F.col("c_hash")))
    # through a generator, so that the words are made once a row and not again for every window that is compared
    met = met.select("doc_id", "text_hash", "item_id", "item_words", "diagonal", "windows", F.explode(F.array(lower_words(F.col("text")))).alias("words"))
    same = F.filter("windows", lambda w: F.slice("words", F.col("diagonal") + w["at"] + 1, w["length"]) == F.slice("item_words", w["at"] + 1, w["length"]))
    spans = F.transform(same, lambda w: F.struct((F.col("diagonal") + w["at"]).alias("start"), w["length"].alias("length")))
    return met.select("doc_id", "text_hash", "item_id", F.explode(F.array(spans)).alias("spans")).filter(F.size("spans") > 0).distinct()


def find_matches(docs: DataFrame, benchmark: DataFrame, size: int = SIZE) -> tuple[DataFrame, DataFrame]:
    """By the index: the exact phrase matches of the benchmark's windows, and the items that are near."""
    items = cut(benchmark_items(benchmark), "index-items")
    terms = cut(corpus_terms(docs, items), "index-vocabulary")
    windows = cut(plan_windows(items, terms, size), "index-windows")
    pairs = cut(anchor_pairs(items, windows), "index-anchors")
    anchors = pairs.select(F.explode(F.array("lead", "other")).alias("term")).distinct()
    forms = cut(terms.select("raw", "term").join(anchors, "term", "left_semi"), "index-forms")
    postings = cut(build_postings(docs, forms), "index-postings")
    met = cut(meet_anchors(postings, pairs), "index-met")
    candidates = cut(exact_candidates(met, windows), "index-candidates")
    return phrase_matches(docs, items, candidates), near_items(met, pairs, items)


def proximity_matches(postings: DataFrame, pairs: DataFrame, within: int) -> DataFrame:
    """``pair, doc_id, text_hash, left, right``: places where the terms of a pair (``pair, term_a, term_b``) are at most
    ``within`` words apart, in either order.

    The first term's positions go to their block of ``within + 1`` words and its neighbours; there the other term's list
    is probed.
    """
    block = F.floor(F.col("pos") / (within + 1))
    a = postings.join(pairs.withColumnRenamed("term_a", "term"), "term").select("pair", F.col("doc_id").alias("a_doc"), F.col("text_hash").alias("a_hash"), F.col("term_b").alias("a_term"), F.col("pos").alias("left"), F.explode(F.array(block - 1, block, block + 1)).alias("a_block"))
    b = postings.withColumn("block", block)
    same = F.col("a_doc").eqNullSafe(F.col("doc_id")) & (F.col("a_hash") == F.col("text_hash")) & (F.col("a_term") == F.col("term")) & (F.col("a_block") == F.col("block"))
    near = a.join(b, same).filter((F.abs(F.col("left") - F.col("pos")) <= within) & (F.col("left") != F.col("pos")))
    return near.select("pair", "doc_id", "text_hash", "left", F.col("pos").alias("right")).distinct()


def judge_contamination(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, keep: list[str] | None = None, near: str | None = None) -> tuple[DataFrame, list[str]]:
    """``docs`` (or its columns ``keep``) with word count, hit words, item count and item ids under the returned names.

    These come from exact matches. With ``near``, a last column of that name counts the items that are near.
    """
    keep = docs.columns if keep is None else keep
    names = fresh(docs, "n_words", "n_hit", "n_items", "items")
    phrases, close = find_matches(docs.select("doc_id", "text"), benchmark, size)
    found = cut(phrases, "index-matches")
    places = found.select("doc_id", "text_hash", F.explode("spans").alias("s")).select("doc_id", "text_hash", F.explode(F.sequence(F.col("s.start"), F.col("s.start") + F.col("s.length") - 1)).alias("pos")).distinct()
    hits = places.groupBy(F.col("doc_id").alias("h_doc"), F.col("text_hash").alias("h_hash")).agg(F.count("*").alias("hits"))
    items = found.groupBy(F.col("doc_id").alias("i_doc"), F.col("text_hash").alias("i_hash")).agg(F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("items"))
    dirty = hits.join(items, F.col("h_doc").eqNullSafe(F.col("i_doc")) & (F.col("h_hash") == F.col("i_hash"))).select("h_doc", "h_hash", "hits", "items")
    doc, own, n_hit, ids = (f"{n}_" for n in fresh(docs, "doc", "hash", "hits", "ids"))
    dirty = dirty.toDF(doc, own, n_hit, ids)
    left = docs.select(*[F.col(f"`{c}`") for c in keep], F.col("doc_id").alias(f"{doc}l"), text_hash(F.col("text")).alias(f"{own}l"), count_words(F.col("text")).alias(names[0]))
    out = left.join(dirty, F.col(f"{doc}l").eqNullSafe(F.col(doc)) & (F.col(f"{own}l") == F.col(own)), "left")
    more = []
    if near is not None:
        n_doc, n_own, n_near = (f"{n}_" for n in fresh(docs, "near_doc", "near_hash", "near"))
        out = out.join(close.toDF(n_doc, n_own, n_near), F.col(f"{doc}l").eqNullSafe(F.col(n_doc)) & (F.col(f"{own}l") == F.col(n_own)), "left")
        more = [F.coalesce(F.col(n_near), F.lit(0)).cast("long").alias(near)]
    return out.select(*[F.col(f"`{c}`") for c in keep], names[0], F.coalesce(F.col(n_hit), F.lit(0)).cast("long").alias(names[1]), F.coalesce(F.size(F.col(ids)), F.lit(0)).cast("long").alias(names[2]), F.coalesce(F.col(ids), F.array().cast("array<string>")).alias(names[3]), *more), names


def decontaminate(docs: DataFrame, benchmark: DataFrame, size: int = SIZE) -> DataFrame:
    """The rows of ``docs`` in which no window of the benchmark occurs."""
    found = cut(find_matches(docs.select("doc_id", "text"), benchmark, size)[0].select("doc_id", "text_hash").distinct(), "index-dirty")
    doc, own = fresh(docs, "doc", "hash")
    dirty = found.toDF(doc, own)
    return docs.join(dirty, F.col("doc_id").eqNullSafe(F.col(doc)) & (text_hash(F.col("text")) == F.col(own)), "left_anti")
