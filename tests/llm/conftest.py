import pytest

LONG = " ".join(f"w{k}" for k in range(30_000))
PASSAGE = " ".join(f"shared{k % 37}x{k}" for k in range(60))

ODD = [
    (1, "", "en", "a"), (2, None, None, None), (3, "one", "en", "a"), (4, "Two words", "fr", "b"), (5, LONG, "en", "a"), (6, LONG + " end", "en", "a"),
    (7, f"before it {PASSAGE} after it", "en", "b"), (8, f"{PASSAGE}\nelse", "en", "a"), (9, "same " * 120, "en", "a"), (10, "same " * 120, "en", "b"), (10, "same " * 120, "en", "b"),
    (11, " \t\n\x0b\x0c\r ", "en", None), (12, "naïve café ÀÉ 漢字 🙂   x́", "fr", "a"), (13, "<turn user> </turn> \\ <|endoftext|> 's", "de", "a"), (None, "no id here at all", "en", "a"), (None, None, "en", "b"),
    (14, "line one that is long enough to count for the rule\n" * 3 + "short", "en", "a"),
] + [(100 + k, f"  Line ONE that is long enough to count for the rule\t\nown {k}\n", "en", "c") for k in range(6)]


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and very long texts, ties, repeated rows, and extra columns whose names clash with the operators' own."""
    clash = "component_id fp size kept sha marks shared starts score predicted n_tokens start target taken copies source_size bucket pattern at part root node first x quality"
    df = spark.createDataFrame([(*r, len(r[1] or "")) for r in ODD], "doc_id long, text string, lang string, source string, n_chars long")
    return df.selectExpr("*", *[f"'extra' as {c}" for c in clash.split()]).repartition(3)


@pytest.fixture(scope="session")
def rows():
    return list(ODD)


@pytest.fixture(scope="session")
def none(odd, spark):
    return spark.createDataFrame([], odd.schema)
