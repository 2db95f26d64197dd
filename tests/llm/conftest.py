import pytest

TEXTS = [
    None, "", " ", "\n\t", "a", "The MIT License. ", "x " * 40_000, "word" * 20_000, "Ünï códe 日本 🎉 <s> </s> <0x41>", "a b c d e f g h", "A  b c\td e f g h",
    "mail a.b@c.com or call +1 (743) 555-3824", "4111 1111 1111 1111 and 10.0.0.1", "  leading and trailing  ", "GNU General Public License, version 3; CC BY-NC 4.0", "a\x00b ▁ c",
]


@pytest.fixture(scope="session")
def odd(spark):
    """Odd texts, each twice (the repeats under the same id and under another), with extra columns of clashing names."""
    rows = [(i, t, "en" if i % 2 else None, "src", i) for i, t in enumerate(TEXTS)]
    rows += [rows[5], (100, TEXTS[5], "fr", None, None), (101, TEXTS[14], None, "src", 3)]
    columns = "doc_id long, text string, lang string, source string, n_chars long"
    df = spark.createDataFrame(rows, columns)
    for name in ("id", "digest", "label", "words", "node", "component", "spans", "hit", "score"):
        df = df.selectExpr("*", f"'clash' AS {name}")
    return df


@pytest.fixture(scope="session")
def none(odd):
    return odd.limit(0)
