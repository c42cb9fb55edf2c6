import pytest
from pyspark.sql import Row

PROSE = "The river runs past the old mill and under the stone bridge. Children watch boats drift slowly toward the sea. "


@pytest.fixture(scope="session")
def odd(spark):
    """Documents with nulls, empty, very long, tied and repeated texts, and columns of clashing names."""
    long = PROSE * 900
    rows = [
        (1, None, None),
        (2, "", "en"),
        (3, "   \n\t ", "en"),
        (4, PROSE * 3, "en"),
        (5, PROSE * 3, "en"),
        (5, PROSE * 3, "en"),
        (6, long, "en"),
        (7, "x" * 30_000, None),
        (8, "1 2 3 | # $ % ! 中文 ß é \x01\x02 " * 5, "zz"),
        (None, "a row without an id but with words " * 4, None),
        (9, "\n".join(["same line here and there and everywhere in this text"] * 6), "en"),
    ]
    return spark.createDataFrame([Row(doc_id=a, text=b, lang=c, score=1.0, fp=7, tid="t", k1=0, covered=True, quality_score=0.0, words="w") for a, b, c in rows], "doc_id long, text string, lang string, score double, fp int, tid string, k1 int, covered boolean, quality_score double, words string")


@pytest.fixture(scope="session")
def none(odd):
    return odd.where("false")


@pytest.fixture(scope="session")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")
