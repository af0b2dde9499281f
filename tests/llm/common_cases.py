"""Awkward rows that every operator on documents must take."""

ROWS = [
    (1, "Released under the MIT License. Some words here, and more words there.", "en", "a", 70),
    (2, None, None, None, None),
    (3, "", "en", "a", 0),
    (4, "   \n\t ", "en", "a", 6),
    (5, "x", None, "b", 1),
    (6, "wort " * 3000 + "ende", "de", "b", 15004),
    (7, "the same text in two rows with a token = \"f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda\" in it", "en", "c", 88),
    (8, "the same text in two rows with a token = \"f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda\" in it", "en", "c", 88),
    (8, "the same text in two rows with a token = \"f3ef4d6b2755a36d7d9c25bd72c4d5f67e061fda\" in it", "en", "c", 88),
    (9, "漢字とかな 🙂 don't stop ñandú Ünïcode", "es", "c", 30),
    (None, "a row without an id but with some words in it", "en", None, 44),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, rows=None, extra=False):
    df = spark.createDataFrame(ROWS if rows is None else rows, SCHEMA)
    if extra:  # names that operators use inside
        for name in ("k", "c", "n", "bucket", "label", "rejected", "html", "fingerprint", "spans"):
            df = df.selectExpr("*", f"'z' AS {name}")
    return df
