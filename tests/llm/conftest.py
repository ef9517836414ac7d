import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="session")
def docs(spark):
    """Small texts with nulls, blanks, copies, ties, a long text and clashing extra columns."""
    words = [f"w{i % 97}x{i % 13}" for i in range(900)]
    near = words[:]
    near[5] = "changed"
    rows = [
        (0, " ".join(words), "src1", "en"),
        (1, " ".join(near), "src1", "en"),
        (2, None, None, None),
        (3, "", "src0", "fr"),
        (4, " \n\t ", "src0", "fr"),
        (5, "one", "src0", "fr"),
        (6, "one two", "src2", "de"),
        (7, " ".join(words[100:180] + ["tail", "of", "its", "own"]), "src2", None),
        (7, " ".join(words[100:180] + ["tail", "of", "its", "own"]), "src2", None),
        (8, "same same same same same same same same same same same same", "src1", "en"),
        (9, "Résumé naïve ÄÖÜ été 東京 " * 8, "src3", "fr"),
        (None, "a text without an id but with enough words to be a text", "src3", "en"),
        (11, "line a b c\nline a b c\nother line\n\n# $ % & | < > *", "src0", "en"),
    ]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string, lang string")
    return df.withColumn("n_words", F.lit(1)).withColumn("fp", F.lit("x")).withColumn("bucket", F.lit(True)).withColumn("copies", F.lit(9))


@pytest.fixture(scope="session")
def none(docs):
    return docs.limit(0)
