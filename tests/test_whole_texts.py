"""Queries on whole texts against brute force: what follows the first characters counts."""

import itertools

import pytest
from pyspark.sql import functions as F

from pairbalance import queries, queries_relational  # noqa: F401  the second adds to the registry
from pairbalance.functions import similarity
from pairbalance.plans import engine

HEAD = "the same sixty characters stand in front of each of the texts: "
TEXTS = [
    HEAD + "a" * 100, HEAD + "a" * 90 + "b" * 10, HEAD + "b" * 100, HEAD + "a" * 400, HEAD + "é" * 100, HEAD + "é" * 100, HEAD + "ü" * 100, None, HEAD, "",
    "other texts, that have another key" * 4, "other texts, that have another key" * 3 + "with another end than the first of",
]


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def brute(rows, test):
    out = {}
    for (i, a, s), (j, b, t) in itertools.combinations(rows, 2):
        if a is not None and b is not None and test(a, b, s, t) and 5 * (d := distance(a, b)) <= max(len(a), len(b)):
            out[i, j] = d
    return out


@pytest.fixture(scope="module")
def table(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("whole"))
    rows = [(i, t, f"src{5 if i % 2 else 15}") for i, t in enumerate(TEXTS) if t is not None]
    spark.createDataFrame(rows, "doc_id long, text string, source string").write.parquet(f"{folder}/documents.parquet")
    titled = [(i, f"http{'s' * (i % 2)}://x/{i}", f"<title>{t}</title>") for i, t, _ in rows]
    spark.createDataFrame(titled, "page_id long, url string, html string").write.parquet(f"{folder}/pages.parquet")
    return folder, [(i, t, "R" if i % 2 else "S") for i, t, _ in rows]


def same_key(a, b, *_):
    return a.strip()[:3].lower() == b.strip()[:3].lower()


@pytest.mark.parametrize("name", ["matches_whole_block", "matches_sub_block", "matches_pair_interval", "matches_documents"])
def test_matches(spark, table, name):
    got = {(r.left_id, r.right_id): r.distance for r in queries.QUERIES[name](spark, table[0]).collect()}
    assert got == brute(table[1], same_key) and (0, 1) in got and (0, 2) not in got and (4, 6) not in got


def test_matches_combined(spark, table):
    got = {(r.left_id, r.right_id) for r in queries.QUERIES["matches_combined"](spark, table[0]).collect()}
    assert got == {k for k, d in brute(table[1], same_key).items() if d == 0} == {(4, 5)}


def test_other_matches(spark, table):
    folder, rows = table
    keyed = lambda a, b: same_key(a, b) or not a[:3].isalpha() or not b[:3].isalpha()
    two = {tuple(sorted((r.left_id, r.right_id))): r.distance for r in queries.QUERIES["two_source_matches"](spark, folder).collect()}
    assert two == brute(rows, lambda a, b, s, t: s != t and same_key(a, b))
    one = {(r.left_id, r.right_id): r.distance for r in queries.QUERIES["missing_keys_one_source"](spark, folder).collect()}
    assert one == brute(rows, lambda a, b, *_: keyed(a, b))
    two = {tuple(sorted((r.left_id, r.right_id))): r.distance for r in queries.QUERIES["missing_keys_two_source"](spark, folder).collect()}
    assert two == brute(rows, lambda a, b, s, t: s != t and keyed(a, b))
    lost = queries.QUERIES["blocking_loss"](spark, folder).first()
    assert tuple(lost) == (n := len(brute(rows, lambda *_: True)), k := len(brute(rows, same_key)), n - k)


def test_bounded_similarity(spark):
    pairs = spark.createDataFrame([*itertools.product(TEXTS[6:], TEXTS[6:]), ("abcdefghij", "abcdefgxyz"), ("abcdefghij", "abcdefvxyz")], "a string, b string")
    a, b = F.col("a"), F.col("b")
    for x, y in pairs.where("a IS NOT NULL AND b IS NOT NULL").select(similarity.edit_similarity(a, b), similarity.edit_similarity_within(7)(a, b)).collect():
        assert y == (x if x >= 0.7 else 0.0)


def test_streamed_matches(spark, table):
    got = {(r.left_id, r.right_id): r.distance for r in engine.match(queries.documents(spark, table[0]), "sub_block", 3, 2, reducer="arrow").collect()}
    assert got == brute(table[1], same_key)


def test_array_functions(spark, tmp_path):
    texts = ["one two  two " + "word " * 60 + "Overlong overlong", "short", "", "é" * 300 + " lengthy " * 40]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in queries.QUERIES["array_functions"](spark, str(tmp_path)).collect()}
    for k, text in enumerate(texts):
        words = text.split(" ")
        assert got[k].n == len(set(text.lower().split(" "))) and got[k].letters == sum(map(len, words))
        assert got[k].long_words == ",".join(sorted({w for w in words if len(w) > 6}))


def test_blocking_loss_has_no_cap(spark, table, monkeypatch):
    """The reference does not come from the capped join of all pairs."""

    def capped(*_, **__):
        raise ValueError("more rows than all pairs take")

    monkeypatch.setattr(queries.whole_block, "all_pairs", capped)
    n, k = len(brute(table[1], lambda *_: True)), len(brute(table[1], same_key))
    assert tuple(queries.QUERIES["blocking_loss"](spark, table[0]).first()) == (n, k, n - k)


def test_uncell_reads_the_sizes_of_blocks(spark, table):
    """The numbers follow the pages: a block of seven titles, one of two and single ones."""
    sizes = {k: len(list(g)) for k, g in itertools.groupby(sorted(t.strip()[:3].lower() for _, t, _ in table[1]))}
    expected = {(n, p, x, y) for n in set(sizes.values()) for p, (x, y) in enumerate(itertools.combinations(range(n), 2))}
    got = [tuple(r) for r in queries.QUERIES["uncell_roundtrip"](spark, table[0]).collect()]
    assert set(got) == expected and len(got) == len(expected) > 20
