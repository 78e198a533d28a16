import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, word string, h long, mark int"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and blank texts, repeated rows and ids, a very long text, and columns whose names the operators use themselves."""
    long = " ".join(f"word{k % 977} and{k % 31}" for k in range(20_000))
    same = "The Quick brown fox, JUMPS over the lazy dog near the river bank and sleeps. " * 4
    texts = [(1, same), (2, same), (3, None), (4, ""), (5, "  \n\t "), (6, long), (7, same + "Then it woke up."), (7, same + "Then it woke up."), (None, "Äpfel und Ödland über den Fluß, sagte K."), (8, "one"), (9, "!!! ???"), (10, "Licensed under CC BY 4.0.\nAll rights reserved."), (None, None)]
    return spark.createDataFrame([(i, t, "en" if i and i % 2 else None, None, None, "k", "w", 1, 1) for i, t in texts], SCHEMA).repartition(3)


@pytest.fixture(scope="session")
def nothing(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def bench(spark):
    return spark.createDataFrame([(1, "quick brown fox jumps over the lazy dog near the river bank"), (2, "ÄPFEL und Ödland"), (None, None), (3, ""), (4, "quick brown fox jumps over the lazy dog near the river bank"), (5, "not in any text at all I think")], "item_id long, text string")
