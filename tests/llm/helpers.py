"""Small documents with the odd cases that every operator has to take."""

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, id string, t string"
LONG = " ".join(f"word{k % 977} thing{k % 61}" for k in range(20_000))
ODD = [None, "", " ", "\n\n", "!", "a", "Ä", "...", "1 2 3", "line\n\nline\nline", "▁", "x y z", "中文 текст", "tab\tand\x0bvt", "\x00 nul", LONG]


def odd_documents(spark):
    """Nulls in every column, empty and very long texts, repeated rows, and extra columns whose names operators use inside."""
    rows = [(k, t, "en" if k % 2 else None, f"s{k % 3}", len(t or ""), "k", "i", "t") for k, t in enumerate(ODD)]
    rows += [rows[9], rows[9], (None, "no id at all here", "en", None, None, None, None, None), (None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


def documents(spark, texts, first=0):
    return spark.createDataFrame([(k + first, t, "en", "s", len(t or ""), "k", "i", "t") for k, t in enumerate(texts)], SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)
