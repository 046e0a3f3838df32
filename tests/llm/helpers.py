"""Small tables with awkward rows."""

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"

EDGE = [
    (0, "one two three\nalpha beta\nalpha beta", "en", "s", 1),
    (1, "one two three\nalpha beta\nalpha beta", "en", "s", 1),
    (1, "one two three\nalpha beta\nalpha beta", "en", "s", 1),
    (2, None, None, None, None),
    (3, "", "en", "t", 0),
    (4, " \n\t ", "de", None, 3),
    (None, "kept text without an id", "fr", "t", 5),
    (5, "word " * 3000, "en", "t", 15000),
    (6, "été ß 漢字 привет <|endoftext|> x", "fr", "u", 9),
]


def edge_docs(spark):
    return spark.createDataFrame(EDGE, SCHEMA).repartition(3)


def docs_of(spark, texts, **more):
    rows = [(i, t, more.get("lang", "en"), f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA).repartition(4)


def empty_docs(spark):
    return spark.createDataFrame([], SCHEMA)
