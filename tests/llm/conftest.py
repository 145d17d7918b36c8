import pytest

LONG = " ".join(f"word{i % 700} tail" for i in range(6000))
TEXTS = [
    "The Quick brown fox jumps over the lazy dog and then some more words follow here.",
    "The Quick brown fox jumps over the lazy dog and then some more words follow here.",
    "The  Quick brown fox jumps\tover the lazy dog and then some more words follow here. ",
    None,
    "",
    "   \n\t ",
    "1234 5678 !!! ???",
    LONG,
    LONG + " end",
    "Ünïcödé 你好 🦕 text\nSecond line that is long enough to count\nthird",
    "first\nSecond line that is long enough to count\nother",
    "\n\nsecond LINE that is long enough to count  \nagain",
    "mail a.b@c.example.org or +1 (555) 555-1234 or 10.0.0.1 or 4111 1111 1111 1111 or 300.1.1.1",
]
CLASH = ["rid", "_d", "_t", "row", "size", "kept", "block", "target", "u", "v", "fp", "id", "h", "ids"]


@pytest.fixture(scope="session")
def rows():
    out = [(i, t, ["en", "de", None][i % 3], ["a", "b", None][i % 3]) for i, t in enumerate(TEXTS)]
    out.append((None, "a text without an id and with enough words to be a window", "en", None))
    out.append(out[0])  # a repeated row
    return out


@pytest.fixture(scope="session")
def docs(spark, rows):
    from pyspark.sql import functions as F

    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("n_chars", F.length("text").cast("long"))
    for name in CLASH:
        df = df.withColumn(name, F.lit(7))
    return df


@pytest.fixture(scope="session")
def none(docs):
    return docs.limit(0)
