"""Ground truth for evaluation: label rules, roles of tables, pairs and triplets. No scoring operator reads these."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.sampling import priority, priority_bits
from ..functions.text import VAGUE_LABELS, jaro_winkler, plain_label, tokenize_label
from ..functions.vectors import dot, norm
from ..sources.scratch import cut


def drop_vague(truth: DataFrame, stoplist: tuple[str, ...] = VAGUE_LABELS, min_len: int = 3) -> DataFrame:
    """Rows whose ``label`` says something: not in the stoplist, at least ``min_len`` characters."""
    spark = truth.sparkSession
    stop = spark.createDataFrame([(w,) for w in stoplist], "label string")
    return truth.filter(F.char_length("label") >= min_len).join(F.broadcast(stop), F.lower(truth["label"]) == stop["label"], "left_anti")


def label_vectors(labels: DataFrame, vectors: DataFrame, width: int) -> DataFrame:
    """``label, vec``: mean word vector of labels whose words are all known (``vectors``: ``word, vec``)."""
    words = labels.select("label", F.posexplode(tokenize_label(F.col("label"))).alias("i", "word"))
    known = words.join(vectors, "word", "left")
    return known.groupBy("label").agg(F.sum(F.col("vec").isNull().cast("int")).alias("unknown"), F.array(*[F.avg(F.col("vec")[i].cast("double")) for i in range(width)]).alias("vec")).filter("unknown = 0").drop("unknown")


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def label_pairs(truth: DataFrame, vectors: DataFrame | None = None, width: int = 64, cos: float = 0.9, jw: float = 0.95) -> DataFrame:
    """``label_a, label_b, rule``: matching labels, once per pair (a <= b).

    Equal labels always match; two labels of known words by the cosine of their mean vectors; others by Jaro-Winkler.
    Distinct labels are compared, not datasets.
    """
    labels = truth.select(plain_label(F.col("label")).alias("label")).distinct()
    equal = labels.select(F.col("label").alias("label_a"), F.col("label").alias("label_b"), F.lit("equal").alias("rule"))
    side = lambda k: labels.select(F.col("label").alias(f"label_{k}"))
    pairs = side("a").join(side("b"), F.col("label_a") < F.col("label_b"))
    if vectors is not None:
        v = label_vectors(labels, vectors, width)
        vec = lambda k: v.select(F.col("label").alias(f"label_{k}"), F.col("vec").alias(f"v_{k}"))
        pairs = pairs.join(vec("a"), "label_a", "left").join(vec("b"), "label_b", "left").withColumn("cos", F.when(F.col("v_a").isNotNull() & F.col("v_b").isNotNull(), cosine(F.col("v_a"), F.col("v_b"))))
    else:
        pairs = pairs.withColumn("cos", F.lit(None).cast("double"))
    judged = pairs.withColumn("rule", F.when(F.col("cos") > cos, "cosine").when(F.col("cos").isNull() & (jaro_winkler("label_a", "label_b") > jw), "jaro_winkler"))
    return equal.unionByName(judged.filter("rule IS NOT NULL").select("label_a", "label_b", "rule"))


def dataset_matches(truth: DataFrame, labels: DataFrame) -> DataFrame:
    """``dataset_a, dataset_b`` for datasets (a < b) whose labels match."""
    t = truth.select("dataset_id", plain_label(F.col("label")).alias("label"))
    both = labels.select("label_a", "label_b").unionByName(labels.select(F.col("label_b").alias("label_a"), F.col("label_a").alias("label_b"))).distinct()
    a = t.withColumnsRenamed({"dataset_id": "dataset_a", "label": "label_a"})
    b = t.withColumnsRenamed({"dataset_id": "dataset_b", "label": "label_b"})
    return a.join(both, "label_a").join(b, "label_b").filter("dataset_a < dataset_b").select("dataset_a", "dataset_b").distinct()


def assign_roles(tables: DataFrame, heldout_share: float = 0.25, seed: int = 42) -> DataFrame:
    """Whole tables to ``R`` or held-out ``T``: ``table_id, role``."""
    return tables.select("table_id").distinct().withColumn("role", F.when(priority(seed, F.col("table_id")) < heldout_share, "T").otherwise("R"))


def carve_halves(cv: DataFrame, ids: DataFrame, seed: int = 43, key: str = "row_key") -> DataFrame:
    """Half of the rows of the chosen datasets moved to a new dataset of role ``S``: ``role`` and ``source_id`` added."""
    chosen = cv.join(ids.select("dataset_id").distinct().withColumn("carved", F.lit(True)), "dataset_id", "left")
    moved = F.coalesce("carved", F.lit(False)) & (priority(seed, F.col("dataset_id"), F.col(key)) < 0.5)
    return chosen.withColumns({"source_id": F.col("dataset_id"), "role": F.when(moved, "S").otherwise("R")}).withColumn("dataset_id", F.when(F.col("role") == "S", F.concat("dataset_id", F.lit("~S"))).otherwise(F.col("dataset_id"))).drop("carved")


def repository_summary(catalog: DataFrame, matches: DataFrame | None = None) -> DataFrame:
    """``kind, role, tables, datasets, mean_n, sd_n`` and, with ``matches`` (``dataset_a, dataset_b``), how many."""
    out = catalog.groupBy("kind", "role").agg(F.countDistinct("table_id").alias("tables"), F.count("*").alias("datasets"), F.avg("n_values").alias("mean_n"), F.coalesce(F.stddev_samp("n_values"), F.lit(0.0)).alias("sd_n"))
    if matches is None:
        return out
    per = matches.join(catalog.select(F.col("dataset_id").alias("dataset_a"), "kind", "role"), "dataset_a").groupBy("kind", "role").agg(F.count("*").alias("matches"))
    return out.join(per, ["kind", "role"], "left").withColumn("matches", F.coalesce("matches", F.lit(0)))


def cross_table_pairs(pairs: DataFrame, catalog: DataFrame) -> DataFrame:
    """Pairs whose datasets come from different tables."""
    side = lambda k: catalog.select(F.col("dataset_id").alias(f"id_{k}"), F.col("table_id").alias(f"table_{k}"))
    return pairs.join(side("a"), "id_a").join(side("b"), "id_b").filter("table_a <> table_b").drop("table_a", "table_b")


def numbered(df: DataFrame, *order: Column | str) -> DataFrame:
    """``df`` with its place ``i`` (from 1) in the whole ``order`` and the number of rows ``n``.

    Rows are dealt into ranges of the order, written, and counted per range; a row's place is the one in its range plus the
    rows of the ranges before, so no task sorts all. ``order`` must tell all rows apart.
    """
    ranged = cut(df.repartitionByRange(*order).withColumn("range", F.spark_partition_id()), "numbered")
    sizes = ranged.groupBy("range").agg(F.count("*").alias("rows"))
    # one row a range
    before = sizes.withColumns({"before": F.coalesce(F.sum("rows").over(Window.partitionBy(F.lit(1)).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)), "n": F.sum("rows").over(Window.partitionBy(F.lit(1)))})
    inside = ranged.withColumn("i", F.row_number().over(Window.partitionBy("range").orderBy(*order)))
    return inside.join(F.broadcast(before.drop("rows")), "range").withColumn("i", F.col("i") + F.col("before")).drop("range", "before")


def balanced_pairs(truth: DataFrame, per_class: int, seed: int = 3) -> DataFrame:
    """``id_a, id_b, y``: up to ``per_class`` matched and as many unmatched pairs of datasets of different tables.

    ``truth``: ``dataset_id, variable, table_id``. Each dataset meets the next ones of its variable in a seeded order,
    and datasets a seeded number of places further on; no full pairing is made.
    """
    t = truth.select("dataset_id", "variable", "table_id", priority(seed, F.col("dataset_id")).alias("p"))
    own = t.withColumns({"i": F.row_number().over(Window.partitionBy("variable").orderBy("p", "dataset_id")), "n": F.count("*").over(Window.partitionBy("variable"))})
    steps = F.explode(F.sequence(F.lit(1), F.lit(12))).alias("step")
    a = own.select(F.col("dataset_id").alias("id_a"), F.col("table_id").alias("ta"), "variable", "i", "n", steps).filter("step < n").withColumn("i", (F.col("i") + F.col("step") - 1) % F.col("n") + 1)
    b = own.select(F.col("dataset_id").alias("id_b"), F.col("table_id").alias("tb"), "variable", "i")
    matched = a.join(b, ["variable", "i"]).filter("ta <> tb AND id_a < id_b").select("id_a", "id_b").distinct().withColumn("y", F.lit(1))
    every = numbered(t, "p", "dataset_id")
    a = every.select(F.col("dataset_id").alias("id_a"), F.col("table_id").alias("ta"), F.col("variable").alias("va"), "i", "n", steps).withColumn("i", (F.col("i") + F.col("step") * F.lit(7) - 1) % F.col("n") + 1)
    b = every.select(F.col("dataset_id").alias("id_b"), F.col("table_id").alias("tb"), F.col("variable").alias("vb"), "i")
    unmatched = a.join(b, "i").filter("ta <> tb AND va <> vb").select(F.least("id_a", "id_b").alias("id_a"), F.greatest("id_a", "id_b").alias("id_b")).distinct().withColumn("y", F.lit(0))
    pick = lambda df: df.orderBy(priority_bits(seed, F.col("id_a"), F.col("id_b")), "id_a", "id_b").limit(per_class)
    return pick(matched).unionByName(pick(unmatched))


def sample_triplets(truth: DataFrame, matches: DataFrame, seed: int = 9) -> DataFrame:
    """``anchor, positive, negative`` per annotated match: the negative is the dataset a seeded number of places further
    in the catalogue's order that is not annotated as a match of the anchor (unannotated pairs count as unmatched)."""
    both = matches.select(F.col("dataset_a").alias("anchor"), F.col("dataset_b").alias("positive")).unionByName(matches.select(F.col("dataset_b").alias("anchor"), F.col("dataset_a").alias("positive")))
    cat = numbered(truth.select("dataset_id").distinct().withColumn("p", priority_bits(seed, F.col("dataset_id"))), "p", "dataset_id").drop("p")
    tries = F.explode(F.sequence(F.lit(0), F.lit(7))).alias("try")
    drawn = both.join(cat.withColumnRenamed("dataset_id", "anchor"), "anchor").select("anchor", "positive", "i", "n", tries)
    drawn = drawn.withColumn("i", (F.col("i") + priority_bits(seed + 1, F.col("anchor"), F.col("positive"), F.col("try")) % (F.col("n") - 1)) % F.col("n") + 1)
    cands = drawn.join(cat.select(F.col("dataset_id").alias("negative"), "i"), "i")
    free = cands.join(both.withColumnRenamed("positive", "negative"), ["anchor", "negative"], "left_anti").filter("negative <> anchor")
    return free.groupBy("anchor", "positive").agg(F.min(F.struct("try", "negative"))["negative"].alias("negative"))


def assert_no_labels(df: DataFrame) -> DataFrame:
    """Refuses scoring inputs that carry a label or variable."""
    bad = {"label", "variable"} & {c.lower() for c in df.columns}
    if bad:
        raise ValueError(f"labels must not reach a score: {sorted(bad)}")
    return df
