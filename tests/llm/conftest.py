import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, grp int, bucket int, node int"

#: Rows that every operator must take: nulls, blanks, repeats, equal ids, one long word, clashing column names.
ODD = [
    (900_001, None), (900_002, ""), (900_003, " \n\t "), (900_004, "one"), (900_005, "x" * 5000), (900_006, "a b c d e f g h i j k l m " * 30), (900_006, "a b c d e f g h i j k l m " * 30),
    (900_007, "a b c d e f g h i j k l m n o p " * 10), (None, "no id but some words " * 20), (900_008, "É ß 漢字 \x1c\x85 <|endoftext|> it's don't 12a3 A<|EndOfText|>b Foo,&&& 1$% re,&&& <|endoftext|>,. X&&&y!? " * 9), (900_008, "same id other text " * 30),
]


@pytest.fixture(scope="session")
def docs(spark, sf):
    """The smallest documents table with the odd rows."""
    base = spark.read.parquet(f"{sf}/documents.parquet").selectExpr("doc_id", "text", "lang", "source", "n_chars", "1 AS grp", "2 AS bucket", "3 AS node")
    odd = spark.createDataFrame([(i, t, None, None, None, 1, 2, 3) for i, t in ODD], SCHEMA)
    out = base.unionByName(odd).repartition(5).cache()
    out.count()
    return out


@pytest.fixture(scope="session")
def rows(docs):
    return [(r["doc_id"], r["text"] or "") for r in docs.select("doc_id", "text").collect()]


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)
