import pytest

LONG = "lorem ipsum dolor sit amet " * 20_000
CLASHING = ["score", "shard", "size", "slot", "n", "h", "cid", "rid", "hashes", "block", "component", "words", "w", "kept", "edits", "spans", "row", "ids", "law"]


@pytest.fixture(scope="session")
def messy(spark):
    """Nulls, empty, white and very long texts, repeated rows, ties, and extra columns with clashing names."""
    texts = [
        (1, "One two three four five six seven."), (2, "One two three four five six seven."), (2, "One two three four five six seven."), (3, None), (None, "a text without a number"),
        (4, ""), (5, " \n\t "), (6, LONG), (7, "x" * 200_000), (8, "ünïcode — “quotes” ½ 漢字 🙂 <|endoftext|>"), (9, "mail bob.smith@mail.example.com or +1 (555) 555-1234"), (10, "word " * 60), (11, "a\nb\na\n\nb\n"), (None, None),
    ]
    rows = [(i, t, "en", None, None, *["clash"] * len(CLASHING)) for i, t in texts]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in CLASHING)
    return spark.createDataFrame(rows, schema)


@pytest.fixture(scope="session")
def no_documents(messy):
    return messy.limit(0)


@pytest.fixture(scope="session")
def messy_pages(spark):
    rows = [(1, "https://www.Example.COM/en/1?x=1", "<p>a<p>b", "clash"), (2, None, None, "clash"), (3, "no scheme", "", None), (4, "http://a.net/es/" + "y" * 100_000, "<div>" * 3000 + "deep", "clash"), (5, "://", "plain &amp; text", "clash"), (5, "://", "plain &amp; text", "clash"), (None, "ftp://h#f", "<table><tr><td>x</table></p></b>", "clash")]
    return spark.createDataFrame(rows, "page_id long, url string, html string, score string")
