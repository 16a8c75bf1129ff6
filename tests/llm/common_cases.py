"""Small documents with every odd case, and a wide table whose further columns clash with working names."""

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def prose(seed, n=60):
    import numpy as np

    draw = np.random.default_rng(seed)
    return " ".join(WORDS[i] + str(j) for i, j in zip(draw.integers(0, len(WORDS), n), draw.integers(0, 9, n), strict=True))


DOCUMENTS = [
    (1, prose(1), "en", "a", 1),
    (2, prose(1), "en", "a", 1),
    (3, prose(1) + " \n", "en", "b", 1),
    (4, None, "en", None, 0),
    (5, "", None, "b", 0),
    (6, " \t\n", "en", "b", None),
    (None, prose(2), "en", "c", 1),
    (None, prose(2), "en", "c", 1),
    (8, prose(3, 12_000), "en", "a", 1),
    (9, "one two", "en", "a", 1),
    (9, "one two", "en", "a", 1),
    (10, prose(1).replace("alpha", "alpha", 1) + " tail", "en", "a", 1),
    (11, "grüße aus köln — naïve café ☕ <|endoftext|> done", "de", "d", 1),
]
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def documents(spark, rows=None):
    df = spark.createDataFrame(DOCUMENTS if rows is None else rows, SCHEMA)
    for name in ("_text", "rep", "size", "taken", "row", "component", "n"):
        df = df.selectExpr("*", f"'extra' as {name}")
    return df


def dicts(df):
    return [r.asDict() for r in df.collect()]
