import pytest
from pyspark.sql import types as T

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])
CLASH = ("n_words", "kept", "fp", "score", "copies", "domain", "item", "spans", "host", "words", "component")

_PROSE = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega"


def messy_rows():
    long_text = "\n".join(f"line number {i} of a very long text with ünïcode {i * 7}" for i in range(6000))
    common = "This very line is shared by many documents."
    rows = [
        (1, None, "en", "s", None),
        (2, "", "en", "s", 0),
        (3, " \t\n\x0b ", None, None, 5),
        (4, long_text, "de", "s", len(long_text)),
        (5, "one two", "en", None, 7),
        (6, "One TWO", "en", "s", 7),
        (7, _PROSE, "en", "s", len(_PROSE)),
        (7, _PROSE, "en", "s", len(_PROSE)),
        (8, _PROSE + " extra", "en", "s", None),
        (None, _PROSE, "en", "s", None),
        (None, "nothing else\n" + common, None, "t", None),
        (9, f"{common}\nÉTÉ à la plage, encore une ligne ici\n{common}", "fr", "t", 10),
        (10, f"  {common.upper()}\t\nsomething", "fr", "t", 10),
        (11, f"{common}\npassword = hunter2hunter2 AKIA{'A' * 16} " + "0123456789abcdef" * 2, "fr", "t", 10),
        (12, "ÀÉ secret:shortvalue; token='x' Passwd: abcdefgh1 api_key=ABCDEFGHIJ\u2003é apikey=1", "fr", "t", 10),
    ]
    return rows


@pytest.fixture(scope="session")
def messy(spark):
    return spark.createDataFrame(messy_rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def clashing(messy):
    from pyspark.sql import functions as F

    return messy.withColumns({c: F.lit(f"own {c}") for c in CLASH if c != "n_chars"})
