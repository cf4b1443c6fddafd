"""Near copies by shingle similarity: the pipeline's near-duplicate stage.

Two documents link when the sets of their five-word shingles (ASCII lower case) have a Jaccard similarity of at least
``percent`` = 80. Candidates come from an index of min-wise hashes and are verified on whole sets, so no link is wrong. A
set has ``BANDS`` = 32 keys, each made of the smallest values of ``ROWS`` = 6 hash functions over its shingles; two sets of
similarity s share a key with probability ``1 - (1 - s**6) ** 32``: 0.99994 at 0.8, 0.9999999 at 0.85. Sets that merely have
a passage in common hardly ever share one (0.002 at a similarity of 0.2), so their number does not make pairs.

Work goes by distinct sets, so exact copies are one row each, and no group is expanded into all its pairs: in a key that
more than ``bucket_limit`` sets share, a head (another one in every key) is compared with the others. That is done for the
first bands, then for all among sets that are not yet of one component. Sets of keys that still hold several components,
such as those around one long passage, are searched exactly instead: under any one order of the shingles, two similar sets
share one of the first ``n - ceil(0.8 n) + 1`` of each, and with the shingles in the order of how many of these sets hold
them, a common passage comes last. Shingles that many sets still share there are compared in blocks of bounded size, which
give out only the pairs that their profiles allow. Before whole sets are fetched, candidates are thinned by their profiles: the shingles
of a set counted in 256 classes of the hash. What two profiles differ by is the least that the sets can differ by, so no
similar pair is lost.

The stage also links the fingerprints of operator 7, by its segment variants (:mod:`.simhash`), and its groups are the
components over the links of both kinds: a similarity says nothing of shingles that repeat, nor a majority of bits of few edits.

A row is told by its ``doc_id`` and a hash of its text. Texts are read for the index, again for the sets of the remaining
candidates, and for the output; none of them is shuffled while the lists of rows to fetch or drop can be broadcast.

Sets and shingles are held as 64-bit hashes. Edge cases are those of :mod:`.simhash`: a text of fewer words than a shingle
is one shingle, texts without words are one empty set, and rows without ``doc_id`` never name a component.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import simhash
from .common import byte_slices, cut, drop_cut, fresh
from .simhash import components

SHINGLE, PERCENT, SEED, BUCKET_LIMIT = 5, 80, 42, 4
BANDS, ROWS, FIRST_BANDS = 32, 6, 4
#: Shingles of more sets than this are compared in blocks of about so many sets.
JOINED_SETS, BLOCK_SETS = 32, 512
#: Lists of at most so many rows are broadcast, longer ones joined by a shuffle.
BROADCAST_ROWS = 1_000_000
PROFILE = 256


def shingle_set(text: str | None, size: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """The sorted distinct shingle hashes of one text, as signed 64-bit numbers."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # of bytes: ASCII only
    if not words:
        return np.zeros(0, np.int64)
    shingles = map(b" ".join, zip(*(words[i:] for i in range(size)), strict=False)) if len(words) >= size else [b" ".join(words)]
    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(s, seed) for s in shingles), np.uint64).view(np.int64))


def set_name(hashes: np.ndarray) -> int:
    """A signed 64-bit name of a set; the empty one is zero."""
    return int(np.uint64(xxhash.xxh64_intdigest(hashes.tobytes(), SEED)).astype(np.int64)) if len(hashes) else 0


def profile(hashes: np.ndarray) -> bytes:
    """How many of the hashes fall into each class; counts above 255 stay there, which only brings profiles closer."""
    return np.bincount((hashes & (PROFILE - 1)).astype(np.int64), minlength=PROFILE).clip(max=255).astype(np.uint8).tobytes()


_FACTORS, _TERMS = np.random.default_rng(SEED).integers(0, 1 << 64, (2, BANDS * ROWS), np.uint64, endpoint=False)
_FACTORS |= np.uint64(1)


def band_keys(hashes: np.ndarray) -> list[int]:
    """A key per band: the hash of the band's smallest values. Empty sets have none."""
    if not len(hashes):
        return []
    values, least = hashes.view(np.uint64), np.full(BANDS * ROWS, (1 << 64) - 1, np.uint64)
    for at in range(0, len(values), 2048):  # a bounded table for any length
        np.minimum(least, (values[at : at + 2048, None] * _FACTORS + _TERMS).min(axis=0), out=least)
    raw, width = least.tobytes(), 8 * ROWS
    keys = np.array([xxhash.xxh64_intdigest(raw[k * width : (k + 1) * width], k) for k in range(BANDS)], np.uint64)
    return keys.view(np.int64).tolist()


def _map_sets(docs: DataFrame, fields: list[T.StructField], kinds: list, kernel, keep: list[str]) -> DataFrame:
    """Like ``map_texts``, with list columns."""
    source = docs.select(*[F.col(f"`{c}`") for c in dict.fromkeys([*keep, "text"])])

    def run(batches):
        for batch in batches:
            for part in byte_slices(batch, "text"):
                made = kernel(part.column("text").to_pylist())
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), *(pa.array(v, k) for v, k in zip(made, kinds, strict=True))], names=[*keep, *(f.name for f in fields)])

    return source.mapInArrow(run, T.StructType([source.schema[c] for c in keep] + fields))


def free_shuffles(df: DataFrame) -> None:
    """Let the driver collect its unused plans, whose shuffle files Spark then deletes."""
    df.sparkSession.sparkContext._jvm.java.lang.System.gc()


def checked(rows: DataFrame) -> DataFrame:
    """A written table, marked for broadcast if it is short enough."""
    return F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows


def text_id() -> Column:
    return F.xxhash64("text")


def _named_sets(texts: list) -> list[list]:
    sets = [shingle_set(t) for t in texts]
    return [[set_name(s) for s in sets], sets]


_HASHES = T.StructField("hashes", T.ArrayType(T.LongType()))
_NODE = T.StructField("node", T.LongType())


def index_sets(docs: DataFrame, prints: bool = False) -> DataFrame:
    """``doc_id, tid, node, n, profile, keys``: each document's text id, and its set's name, size, profile and band keys;
    with ``prints`` also the text's fingerprint ``fp``."""

    def kernel(texts: list) -> list[list]:
        sets = [shingle_set(t) for t in texts]
        own = simhash.kernel(texts) if prints else []
        return [[set_name(s) for s in sets], [len(s) for s in sets], [profile(s) for s in sets], [band_keys(s) for s in sets], *own]

    fields = [_NODE, T.StructField("n", T.IntegerType()), T.StructField("profile", T.BinaryType()), T.StructField("keys", T.ArrayType(T.LongType()))]
    kinds = [pa.int64(), pa.int32(), pa.binary(), pa.list_(pa.int64())]
    if prints:
        fields, kinds = [*fields, T.StructField("fp", T.LongType())], [*kinds, pa.int64()]
    rows = docs.select("doc_id", text_id().alias("tid"), "text")
    return _map_sets(rows, fields, kinds, kernel, ["doc_id", "tid"])


def one_row_each(index: DataFrame) -> DataFrame:
    """One row of ``index`` (written, with ``tag``) for each set: the one with the smallest tag."""
    again = index.groupBy("node").agg(F.min("tag").alias("first"), F.count("*").alias("held")).filter("held > 1").select(F.col("node").alias("of"), "first")
    several = checked(cut(again, "similar-several"))
    return index.join(several, F.col("node") == F.col("of"), "left").filter("first IS NULL OR first = tag").drop("of", "first")


def _similar(common, a, b, percent: int):
    return common * (100 + percent) >= (a + b) * percent


def candidates(left: DataFrame, right: DataFrame, percent: int, also: Column | None = None) -> DataFrame:
    """Distinct pairs ``a < b`` of two lots of index rows that share a key, are of different components, and whose sizes
    allow the similarity."""
    also = F.lit(True) if also is None else also
    l, r = left.alias("l"), right.alias("r")
    met = l.join(r, F.col("l.key") == F.col("r.key")).filter(F.col("l.root") != F.col("r.root")).filter(100 * F.least("l.n", "r.n") >= percent * F.greatest("l.n", "r.n")).filter(also)
    return met.select(F.least("l.node", "r.node").alias("a"), F.greatest("l.node", "r.node").alias("b")).distinct()


def rest_candidates(docs: DataFrame, sets: DataFrame, left: DataFrame, percent: int) -> DataFrame:
    """Pairs among the sets of ``left`` (``node, root``) that hold all similar ones of different components."""
    wanted = cut(sets.join(checked(left.select("node")), "node", "left_semi").select("node", F.col("doc_id").alias("own"), F.col("tid").alias("own_tid")), "similar-wanted")
    whole = _map_sets(pick_rows(docs.select("doc_id", "text"), wanted), [_NODE, _HASHES], [pa.int64(), pa.list_(pa.int64())], _named_sets, [])
    whole = cut(whole.dropDuplicates(["node"]), "similar-rest")
    rows = whole.select("node", F.size("hashes").alias("n"), F.explode("hashes").alias("key"))
    placed = rows.join(rows.groupBy("key").agg(F.count("*").alias("held")), "key")
    placed = placed.withColumn("at", F.row_number().over(Window.partitionBy("node").orderBy("held", "key")) - 1)
    kept = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1
    placed = placed.filter((F.col("at") < kept) & (F.col("held") > 1)).join(left, "node").drop("held")
    index = cut(placed.join(placed.groupBy("key").agg(F.count("*").alias("held")), "key"), "similar-rest-index")
    most = F.least("l.at", "r.at") + 1 + F.least(F.col("l.n") - F.col("l.at") - 1, F.col("r.n") - F.col("r.at") - 1)
    few, many = index.filter(F.col("held") <= JOINED_SETS), index.filter(F.col("held") > JOINED_SETS)
    pairs = candidates(few, few, percent, _similar(most, F.col("l.n"), F.col("r.n"), percent))
    if many.isEmpty():
        return pairs
    return pairs.unionByName(block_pairs(many.join(sets.select("node", "profile"), "node"), percent)).distinct()


def block_pairs(index: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Distinct pairs ``a < b`` of rows (``key, held, node, n, root, profile``) that share a key, are of different components
    and have profiles that leave room for the similarity.

    The sets of a key are dealt into blocks, and every two blocks meet in one group of bounded size.
    """
    blocks = F.ceil(F.col("held") / F.lit(BLOCK_SETS)).cast("int")
    own = F.pmod(F.xxhash64("node", "key"), blocks).cast("int")
    dealt = index.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    dealt = dealt.select("key", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "own", "node", "n", "root", "profile")

    def compare(rows: pa.Table) -> pa.Table:
        node, n, root, block, low, high = (rows.column(c).to_numpy() for c in ("node", "n", "root", "own", "low", "high"))
        shape = np.frombuffer(b"".join(rows.column("profile").to_pylist()), np.uint8).reshape(-1, PROFILE).astype(np.int16)
        n, right = n.astype(np.int64), np.flatnonzero(block == high)
        a, b = [], []
        for i in np.flatnonzero(block == low):
            to = right[(node[right] > node[i]) | (low[0] != high[0])]
            to = to[root[to] != root[i]]
            both = n[to] + n[i]
            to = to[(both - np.abs(shape[to] - shape[i]).sum(axis=1, dtype=np.int64)) * (100 + percent) >= 2 * both * percent]
            a.append(np.minimum(node[i], node[to]))
            b.append(np.maximum(node[i], node[to]))
        return pa.table({"a": np.concatenate(a) if a else np.zeros(0, np.int64), "b": np.concatenate(b) if b else np.zeros(0, np.int64)})

    return dealt.groupBy("key", "low", "high").applyInArrow(compare, "a long, b long").distinct()


def alike(pairs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The ``pairs`` whose profiles leave room for the similarity.

    Sets of n and m shingles that differ in d have (n + m - d) / 2 in common; d is at least what the profiles differ by.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            both = [np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, PROFILE).astype(np.int16) for c in ("of_a", "of_b")]
            n = batch.column("n").to_numpy()
            apart = np.abs(both[0] - both[1]).sum(axis=1, dtype=np.int64)
            yield batch.select(["a", "b"]).filter(pa.array((n - apart) * (100 + percent) >= 2 * n * percent))

    side = lambda k: sets.select(F.col("node").alias(k), F.col("n").cast("long").alias(f"n_{k}"), F.col("profile").alias(f"of_{k}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", (F.col("n_a") + F.col("n_b")).alias("n"), "of_a", "of_b")
    return both.mapInArrow(run, "a long, b long")


def verify(docs: DataFrame, sets: DataFrame, pairs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The ``pairs`` of set names whose whole sets are similar; ``sets`` has a row for every name."""
    pairs = cut(alike(pairs, sets, percent), "similar-candidates")
    nodes = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    wanted = cut(sets.join(nodes, "node", "left_semi").select("node", F.col("doc_id").alias("own"), F.col("tid").alias("own_tid")), "similar-wanted")
    found = pick_rows(docs.select("doc_id", "text"), wanted)
    whole = cut(_map_sets(found, [_NODE, _HASHES], [pa.int64(), pa.list_(pa.int64())], _named_sets, []), "similar-sets")
    both = pairs.join(whole.select(F.col("node").alias("a"), F.col("hashes").alias("of_a")), "a").join(whole.select(F.col("node").alias("b"), F.col("hashes").alias("of_b")), "b")
    links = cut(both.filter(_similar(F.size(F.array_intersect("of_a", "of_b")), F.size("of_a"), F.size("of_b"), percent)).select("a", "b").distinct(), "similar-links")
    for t in (pairs, wanted, whole):
        drop_cut(t)
    free_shuffles(docs)
    return links


def pick_rows(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """The rows of ``docs`` that ``wanted`` (written: ``own``, ``own_tid``) names; rows that repeat may come more than once."""
    return docs.join(checked(wanted.select("own", "own_tid")), F.col("doc_id").eqNullSafe(F.col("own")) & (text_id() == F.col("own_tid")), "left_semi")


def with_roots(rows: DataFrame, roots: DataFrame | None) -> DataFrame:
    """``rows`` with the component of each set so far, without the keys that hold one component only."""
    if roots is None:
        return rows.withColumn("root", F.col("node"))
    of = rows.join(checked(roots.withColumnRenamed("node", "of")), F.col("node") == F.col("of"), "left").drop("of").withColumn("root", F.coalesce("root", "node"))
    several = of.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low < high").select("key")
    return cut(of.join(checked(cut(several, "similar-open")), "key", "left_semi"), "similar-rooted")


def find_links(docs: DataFrame, sets: DataFrame, bucket_limit: int = BUCKET_LIMIT, percent: int = PERCENT) -> DataFrame:
    """Links ``a < b`` between the distinct sets (rows of :func:`index_sets`) that connect all similar pairs of the index."""
    rows = sets.select("node", "n", F.posexplode("keys").alias("band", "key"))
    sizes = checked(cut(rows.groupBy("key").agg(F.count("*").alias("held")).filter("held > 1"), "similar-keys"))
    free_shuffles(sets)
    shared = cut(rows.join(sizes, "key"), "similar-index")
    links = roots = None

    def add(pairs: DataFrame) -> None:
        nonlocal links, roots
        found = verify(docs, sets, pairs, percent)
        links = found if links is None else cut(links.unionByName(found), "similar-links")
        roots = cut(components(links), "similar-roots")
        free_shuffles(sets)

    for bands in (FIRST_BANDS, BANDS):
        open_ = with_roots(shared.filter(F.col("band") < bands), roots)
        few, many = open_.filter(F.col("held") <= bucket_limit), open_.filter(F.col("held") > bucket_limit)
        heads = cut(many.groupBy("key").agg(F.min_by(F.struct("node", "n", "root"), F.xxhash64("key", "node")).alias("h")).select("key", "h.*"), "similar-heads")
        add(candidates(few, few, percent).unionByName(candidates(checked(heads), many, percent)).distinct())
    left = cut(with_roots(shared.filter(F.col("held") > bucket_limit), roots).select("node", "root").distinct(), "similar-left")
    if not left.isEmpty():
        add(rest_candidates(docs, sets, left, percent))
    return links


def print_links(index: DataFrame) -> DataFrame:
    """Links ``a < b`` between sets (``node, fp`` of :func:`index_sets`) that connect all whose texts have linked
    fingerprints: a star for each component of fingerprints."""
    told = cut(index.select("node", "fp").distinct(), "similar-prints")
    roots = cut(components(simhash.find_links(told.select("fp").distinct())), "similar-print-roots").withColumnRenamed("node", "of")
    rooted = told.join(checked(roots), F.col("fp") == F.col("of"), "left").select("node", F.coalesce("root", "fp").alias("print"))
    heads = cut(rooted.groupBy("print").agg(F.min("node").alias("a"), F.max("node").alias("z")).filter("a < z").select("print", "a"), "similar-print-heads")
    return rooted.join(checked(heads), "print").filter("a < node").select("a", F.col("node").alias("b")).distinct()


def group_rows(docs: DataFrame, bucket_limit: int = BUCKET_LIMIT, percent: int = PERCENT, prints: bool = False) -> DataFrame:
    """``doc_id, tid, node, root``: a row for each row of ``docs``, with its set and the name of its component."""
    index = cut(index_sets(docs, prints).withColumn("tag", F.monotonically_increasing_id()), "similar-marked")
    links = find_links(docs, one_row_each(index), bucket_limit, percent)
    if prints:
        links = links.unionByName(print_links(index)).distinct()
    roots = cut(components(links), "similar-components").withColumnRenamed("node", "of")
    grouped = cut(index.join(roots, F.col("node") == F.col("of"), "left").select("doc_id", "tid", "node", F.coalesce("root", "node").alias("root")), "similar-rows")
    drop_cut(index)
    free_shuffles(docs)
    return grouped


def group_similar(docs: DataFrame, bucket_limit: int = BUCKET_LIMIT, percent: int = PERCENT) -> tuple[DataFrame, str, str]:
    """``docs`` with set name and component id (the smallest ``doc_id``), under the returned names."""
    name, comp, own, own_tid = fresh(docs, "set", "component", "own", "own_tid")
    grouped = group_rows(docs, bucket_limit, percent)
    least = grouped.groupBy("root").agg(F.min("doc_id").alias(comp))
    named = grouped.select("doc_id", "tid", "node", "root").distinct().join(least, "root").select(F.col("doc_id").alias(own), F.col("tid").alias(own_tid), F.col("node").alias(name), comp)
    return docs.join(named, F.col("doc_id").eqNullSafe(F.col(own)) & (text_id() == F.col(own_tid))).drop(own, own_tid), name, comp


def drop_similar(docs: DataFrame, bucket_limit: int = BUCKET_LIMIT, percent: int = PERCENT, prints: bool = False) -> DataFrame:
    """One row of every component: the one with the smallest ``doc_id``. With ``prints`` fingerprints link as well.

    Of rows that repeat this ``doc_id`` one stays. Rows without ``doc_id`` stay only where no row of their component has
    one, and then one of them.
    """
    own, own_tid = fresh(docs, "own", "own_tid")
    grouped = group_rows(docs, bucket_limit, percent, prints)
    row = F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "tid")
    first = grouped.groupBy("root").agg(F.min(row).alias("kept"), F.count("*").alias("held")).filter("held > 1")
    several = grouped.join(checked(cut(first, "similar-first")), "root").select("doc_id", "tid", (row == F.col("kept")).alias("stays"))
    told = cut(several.groupBy("doc_id", "tid", "stays").agg(F.count("*").alias("n")), "similar-told")
    here = F.col("doc_id").eqNullSafe(F.col(own)) & (text_id() == F.col(own_tid))
    ids = lambda cond: checked(cut(told.filter(cond).select(F.col("doc_id").alias(own), F.col("tid").alias(own_tid)), "similar-ids"))
    out = docs.join(ids("NOT stays OR n > 1"), here, "left_anti")
    if not told.filter("stays AND n > 1").isEmpty():
        again = docs.join(ids("stays AND n > 1"), here).dropDuplicates([own, own_tid]).drop(own, own_tid)
        out = out.unionByName(again)
    return out
