import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def docs(spark):
    """Makes a documents table from texts or (doc_id, text[, lang, source]) rows."""

    def make(rows, extra=False):
        full = []
        for i, r in enumerate(rows):
            r = (i, r) if not isinstance(r, tuple) else r
            r = (*r, *("en", "src0")[len(r) - 2 :]) if len(r) < 4 else r
            full.append((*r, len(r[1] or "")))
        df = spark.createDataFrame(full, SCHEMA)
        if extra:  # columns named like what operators use inside or give back
            for c in ("size", "h", "n_words", "fp", "k", "shard", "taken", "rk", "component_id", "__quality", "__hash", "a b", "row", "key"):
                df = df.selectExpr("*", f"'x' AS `{c}`")
        return df

    return make


#: Null, empty, blanks only, one word, repeated row, ties, odd signs, a very long text.
ODD = [
    (1, None), (2, ""), (3, " \t\n "), (4, "one"), (4, "one"), (None, "no id here at all"), (6, "a b c d e f g h i j"), (7, "a b c d e f g h i j"),
    (8, "naïve — ﬁ 中文\u00a0x \u0301e #$%\n\n|<>\x0bA\x1cb"), (9, "lorem ipsum dolor sit amet " * 4000),
]
