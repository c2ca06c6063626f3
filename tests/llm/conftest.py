import pytest

EDGE = [
    (0, None), (1, ""), (2, "a"), (3, "   \n\t "), (4, "one two three four"), (4, "one two three four"), (None, "x" * 450), (5, "é" * 300), (6, "aé" * 170 + "\n" + "aé" * 170),
    (7, " ".join(f"w{i}" for i in range(400))), (8, " ".join(f"w{i}" for i in range(400))), (9, " ".join(f"w{i}" for i in range(3, 400))), (10, "ab" * 120_000), (11, "\x00\x01 all rights reserved CC-BY cc/by General  Public\nLicense"),
    (12, "\n".join(["the same line again and again"] * 40)), (13, "x" * 199), (14, "y" + "x" * 200), (15, "x" * 200 + "z"), (17, "hello <|endoftext|> world"), (16, "don't  stop\r\n\r\n  now 中文 123,456"),
]


@pytest.fixture(scope="session")
def edge(spark, tmp_path_factory):
    """A folder with a documents table of odd rows, extra columns with clashing names, in two files."""
    path = str(tmp_path_factory.mktemp("edge"))
    rows = [(d, t, "en", "s", 1, "x", 0.5, "row", 7) for d, t in EDGE]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_words long, labels string, score double, row string, size int").repartition(2).write.parquet(f"{path}/documents.parquet")
    return path


@pytest.fixture(scope="session")
def nothing(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("nothing"))
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([], "page_id long, url string, html string").write.parquet(f"{path}/pages.parquet")
    spark.createDataFrame([], "vec_id long, embedding array<float>, label int").write.parquet(f"{path}/embeddings.parquet")
    return path


def rows_of(spark, sf_dir):
    return [(r[0], r[1]) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()]
