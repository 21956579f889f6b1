import duckdb
import pytest


@pytest.fixture(scope="session")
def documents(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and blank texts, ties, repeated rows, a long text without a break, and columns of clashing names."""
    long = " ".join(f"w{i % 97}x{i % 89}" for i in range(3000))
    passage = " ".join(f"p{i}" for i in range(60))
    rows = [
        (1, None, None, None, None, 0),
        (2, "", "en", "a", 0, 1),
        (3, " \t\n ", "en", "a", 3, 2),
        (4, "one two", "en", None, 7, 3),
        (4, "one two", "en", None, 7, 3),
        (5, long, "fr", "b", len(long), 4),
        (6, long + " tail", "fr", "b", len(long) + 5, 5),
        (7, "x" * 5000, "de", "b", 5000, 6),
        (8, f"start here {passage} and on", "de", "c", 1, 7),
        (9, f"other {passage} end", "de", "c", 1, 8),
        (10, "日本語 текст ☃ <|endoftext|> it's 'tis\r\n  x", "de", "é", 1, 9),
        (None, "no id at all", None, "c", 1, 10),
        (11, "1234 !!", "en", "c", 1, 11),
    ]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, k long").selectExpr("*", "k AS n", "k AS bucket", "k AS places", "k AS size", "k AS anchors", "k AS id", "k AS rate")


@pytest.fixture(scope="session")
def empty(odd):
    return odd.where("false")


@pytest.fixture
def sql(sf_dir):
    con = duckdb.connect()
    for t in ("documents", "pages", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return lambda text, cols: sorted(map(str, con.sql(f"SELECT {', '.join(cols)} FROM ({text}) q").fetchall()))


def rows_of(df, cols):
    return sorted(str(tuple(r)) for r in df.select(*cols).collect())
