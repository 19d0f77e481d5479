import pytest

from binsketch.session import ship

LINE = "the quick brown fox jumps over the lazy dog and runs far away from the old red barn near the river bank at dawn "
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, ids string, n string, found string, keep string"


@pytest.fixture(scope="session", autouse=True)
def package(spark):
    ship(spark)


def edge_rows():
    """Nulls, empty and very long texts, ties, copies, repeated rows, odd white space, scripts, special strings."""
    words = " ".join(f"w{i % 997}x{i % 31}" for i in range(30_000))
    texts = [None, "", " ", "a", "A  b\n\n c ", LINE * 3, LINE * 3, "intro words here now. " + LINE + "tail", LINE.upper(), "x<|endoftext|>y <s> ▁ \x00", "日本語 ΑΣ ß É é 　x 𝒳 café", "  lead", "trail  ", "one two three", "ONE two three", words, words + " changed end of text", None, "a", "a" * 5000, "ab" * 3000]
    rows = [(i, t, None if i % 5 == 0 else "en", None if i % 7 == 0 else f"s{i % 3}", len(t or ""), "clash", "clash", "clash", "clash") for i, t in enumerate(texts)]
    return rows


@pytest.fixture(scope="session")
def edge(spark):
    return spark.createDataFrame(edge_rows(), SCHEMA).cache()


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)
