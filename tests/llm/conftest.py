import pytest

LONG = "lorem ipsum dolor sit amet " * 3000
EDGE = [
    (1, "A shared line of some length\nown 1", "en"),
    (2, "a shared line of some length  \nown 2", "en"),
    (3, "\tA SHARED line of some length\nown 3\n", "en"),
    (4, None, None),
    (5, "", "fr"),
    (6, "Größe ÄÖÜ élan\r\nzwei", "de"),
    (7, "the same text twice, word by word by word", "en"),
    (7, "the same text twice, word by word by word", "en"),
    (8, LONG, None),
    (9, LONG + "x", "en"),
    (10, "   \n\n \t ", "en"),
    (11, "你好 \U0001f600 12345 +49 (30) 1234567 a@b.co 1.2.3.4", "es"),
    (12, "a\x00b ﻿ c", "de"),
    (None, "the same text twice, word by word by word", "en"),
    (None, None, None),
]


@pytest.fixture(scope="session")
def edge(spark):
    """Odd rows with columns whose names operators use inside."""
    rows = [(i, t, lang, "s", 1, "x", 2.0, "k", "p", "q", [1], "r", 1) for i, t, lang in EDGE]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, fp string, size double, shard string, score string, spans string, ids array<int>, _lines string, n_hit int")


@pytest.fixture(scope="session")
def empty(edge):
    return edge.where("doc_id < 0")


def rows_of(df, *cols):
    return sorted((tuple(r) for r in df.select(*cols).collect()), key=repr)
