import pytest

#: Texts that upset things: null, empty, blanks, repeats, ties, code points of all widths, one long text.
ODD = [
    (1, None, "en", "src0", 0),
    (2, "", None, None, None),
    (3, " \t\n\x0b\x0c\r ", "en", "src1", 7),
    (4, "One two three\nOne two three\nfour", "en", "src1", 5),
    (4, "One two three\nOne two three\nfour", "en", "src1", 5),
    (5, "one TWO three\none two THREE\nfour", "de", "src2", 5),
    (6, "naïve Ünïcode ñandú é 日本語 😀 x́ ΑΣ <|endoftext|> it's 123", "fr", "src3", 5),
    (None, "lost id", "fr", "src3", 5),
    (None, "lost id", "fr", "src3", 5),
    (7, "word " * 30_000, "en", "src0", 5),
    (8, "a\x00b \x85 　  c", "xx", "", 5),
]


@pytest.fixture(scope="session")
def odd(spark):
    """Rows with the columns of documents and two more whose names clash with outputs."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame(ODD, "doc_id long, text string, lang string, source string, n_chars long")
    return df.withColumn("n_words", F.lit("mine")).withColumn("Kept", F.lit(1)).withColumn("fp", F.lit("x"))


@pytest.fixture(scope="session")
def none(odd):
    return odd.where("false")


@pytest.fixture(scope="session")
def docs(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
