import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, text2 string, key string, salt int, n int"


def prose(seed: int, words: int) -> str:
    return " ".join(f"w{(seed * 7919 + i * i * 31 + i * 17) % 5003}" for i in range(words))


@pytest.fixture(scope="session")
def edge_rows():
    """Nulls everywhere, empty and long texts, ties, repeated rows, copies, near copies, shared lines, foreign signs."""
    shared = prose(999, 60)
    base = prose(1, 120)
    near = base.replace("w17 ", "x17 ", 1) + " tail"
    rows = [
        (1, base, "en", "src0", 10, "a", "k", 1, 1), (2, base, "en", "src0", 10, "a", "k", 1, 1), (2, base, "en", "src0", 10, "a", "k", 1, 1),
        (3, near, "en", "src1", 10, None, None, None, None), (4, "", "en", "src1", 0, None, None, None, None), (5, None, None, None, None, None, None, None, None),
        (None, prose(5, 40), "fr", "src2", 3, "b", "k", 2, 2), (None, None, None, None, None, None, None, None, None),
        (6, prose(6, 4000), "de", "src3", 9, "c", "k", 3, 3), (7, shared + "\n" + prose(7, 30), "es", "src4", 9, "c", "k", 3, 3),
        (8, prose(8, 30) + "\n" + shared + "\nend of it", "es", "src5", 9, "c", "k", 3, 3), (9, "   \n\t ", "en", "src0", 5, "c", "k", 3, 3),
        (10, "a b", "en", "src0", 3, "c", "k", 3, 3), (11, "A  b\t", "en", "src0", 3, "c", "k", 3, 3), (12, "éß 漢字 🙂 Σας <|endoftext|>", "en", "src0", 3, "c", "k", 3, 3),
        (13, "12345 ... !!! 678", "en", "src0", 3, "c", "k", 3, 3), (14, prose(8, 31) + "\n" + shared + " \nend", "es", None, 9, "c", "k", 3, 3),
    ]
    return rows


@pytest.fixture(scope="session")
def docs(spark, edge_rows):
    return spark.createDataFrame(edge_rows, SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)
