import pytest

#: Null, empty, blank, repeated rows, ties, long and odd texts.
ODD = [
    (1, None),
    (2, ""),
    (3, " \n\t "),
    (4, "The quick brown fox jumps over the lazy dog. " * 8),
    (4, "The quick brown fox jumps over the lazy dog. " * 8),
    (5, "the quick  brown\nfox"),
    (6, "the quick brown fox"),
    (7, "Ωμέγα ΑΣ İstanbul <|endoftext|> it''s 123 é́"),
    (8, "a" * 3000),
    (9, "word " * 4000),
    (10, "x"),
]


@pytest.fixture(scope="session")
def odd(spark):
    """Documents with every odd case and an extra column whose name operators use inside."""
    return spark.createDataFrame([(i, t, f"s{i % 3}" if i % 4 else None, 7) for i, t in ODD], "doc_id long, text string, source string, digest int").repartition(3)


@pytest.fixture(scope="session")
def nothing(odd):
    return odd.limit(0)


@pytest.fixture(scope="session")
def small(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")
