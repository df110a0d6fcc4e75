import pytest
from pyspark.sql import types as T

from anchorseek.shipping import ship

DOCS = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()),
    T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()),
    # names that the operators use inside
    *[T.StructField(c, T.IntegerType()) for c in ("_id", "_t", "_n", "_k", "_src", "_key", "_size", "_row", "_mark", "size", "target", "taken", "lang_pred", "findings", "kept", "p_toxic", "_part")],
])


def row(i, text, lang="en", source="a"):
    return (i, text, lang, source, len(text) if text is not None else None, *([7] * 17))


LONG = " ".join(f"word{i % 997}x{i % 31}" for i in range(30_000))
ODD = [
    row(1, "the quick brown fox jumps over the lazy dog again and again until it is tired of jumping"),
    row(2, None), row(3, ""), row(4, " \t\n\x0b "), row(5, LONG),
    row(6, "same text here for two rows of this small table and some more words"), row(6, "same text here for two rows of this small table and some more words"),
    row(7, "null language", None), row(8, "null source", "de", None), row(None, "null id and a few words"),
    row(9, "ÉTÉ été Straße İstanbul K 日本語 テスト über"), row(10, "###$$$ %%% &&& ||| <<>>"), row(11, "one"), row(12, "\x00\x01 odd \x7f bytes \ufffd"),
]


@pytest.fixture(scope="session")
def ready(spark):
    ship(spark)
    return spark


@pytest.fixture(scope="session")
def odd(ready):
    return ready.createDataFrame(ODD, DOCS).cache()


@pytest.fixture(scope="session")
def none(ready):
    return ready.createDataFrame([], DOCS)
