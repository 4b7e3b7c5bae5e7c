import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, shard string, n_words long, node string"
A = "the quick brown fox jumps over the lazy dog near the quiet river bank while the sun sets slowly behind the old hills and birds sing"
B = "a completely different passage about trains stations tickets and the long way home through the rainy streets of the northern town"


def row(key, text):
    return (key, text, "en", "s", 0 if text is None else len(text), 7, "x", 9, "n")


@pytest.fixture(scope="session")
def edge_rows():
    """Nulls in key and text, empty and blank texts, ties, repeated rows, a long text, columns with clashing names."""
    long_text = "\n".join(f"line {i} of the long text holds word{i * i} and word{i * 7 % 1013} and so on" for i in range(4000))
    return [
        row(1, A), row(2, A), row(3, A + " today"), row(4, B), row(4, B), row(None, B + "\nmore"), row(None, None), row(5, None), row(6, ""), row(7, " \n\t \n"),
        row(8, long_text), row(9, "x"), row(10, "x y z"), row(11, "ÀÉ 日本語 🙂 straße\x0bvertical tab\x0cfeed"), row(12, "spam spam " * 300), row(13, A.upper() + "\n" + B), row(14, "\n".join([A, A, A, B, ""])),
    ]


@pytest.fixture(scope="session")
def edges(spark, edge_rows):
    return spark.createDataFrame(edge_rows, SCHEMA)


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)
