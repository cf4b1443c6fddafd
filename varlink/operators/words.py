"""Word vectors: trained on the repository's text columns, and fields as means of their words' vectors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import words


def fit_word_vectors(texts: DataFrame, width: int = 300, min_rows: int = 5, sample_rows: int = 200_000, seed: int = 42) -> DataFrame:
    """``word, vec`` by skip-gram on the words of string column ``value_str``.

    The fit sees at most ``sample_rows`` rows, chosen by a hash of the text; the model keeps the vocabulary on the driver,
    so its size (words seen in ``min_rows`` of these rows) is bounded by the sample.
    """
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    rows = texts.filter("value_str IS NOT NULL").orderBy(F.xxhash64("value_str")).limit(sample_rows).select(words(F.col("value_str")).alias("w")).filter(F.size("w") > 0)
    model = Word2Vec(vectorSize=width, minCount=min_rows, seed=seed, numPartitions=1, maxIter=1, inputCol="w", outputCol="v").fit(rows)
    return model.getVectors().select("word", vector_to_array("vector").alias("vec"))


def vector_dictionary(vectors: DataFrame, most: int = 500_000) -> dict[str, np.ndarray]:
    """The vectors as a dictionary for the encoder; refused beyond ``most`` words, where :func:`field_word_vectors` joins
    instead."""
    rows = vectors.limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} words: join the vectors instead of broadcasting them")
    return {r["word"]: np.array(r["vec"]) for r in rows}


def field_word_vectors(fields: DataFrame, vectors: DataFrame, width: int, known_only: bool = True) -> DataFrame:
    """``dataset_id, field, vec`` for distinct texts (``dataset_id, value_str``): the mean of the vectors of the known
    words; the zero vector where none is known. A join on the word, for vocabularies of any size.

    ``known_only=False`` divides by all words, so unknown ones count as zero.
    """
    parts = fields.select("dataset_id", F.xxhash64("dataset_id", "value_str").alias("field"), words(F.col("value_str")).alias("w"), F.col("value_str"))
    each = parts.select("dataset_id", "field", F.explode("w").alias("word")).join(vectors, "word")
    n = F.count("*") if known_only else F.max("size")
    each = each.join(parts.select("field", F.size("w").alias("size")).distinct(), "field")
    means = each.groupBy("dataset_id", "field").agg(F.array(*[F.sum(F.col("vec")[i].cast("double")) / n for i in range(width)]).alias("vec"))
    zero = F.array(*[F.lit(0.0)] * width)
    return parts.select("dataset_id", "field").distinct().join(means, ["dataset_id", "field"], "left").withColumn("vec", F.coalesce("vec", zero))
