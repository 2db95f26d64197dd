"""Exact and near duplicates, and benchmark passages, against brute force."""

import collections
import hashlib
import random
import re

import duckdb
import pytest

from pairbalance.llm import components, dealt, decontaminate, exact_dedup, minhash, queries

SF = "/root/testdata/sf0.001"

ASCII = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def exact(rows):
    groups = collections.defaultdict(list)
    for i, t in rows:
        groups[re.sub("[ \t-\r]", "", t or "")].append((-len(t or ""), i))
    return {i: (min(g)[1], len(g), i == min(g)[1], hashlib.sha256(k.encode()).hexdigest()) for k, g in groups.items() for _, i in g}


@pytest.mark.parametrize("counters", [1, 3, 512])
def test_exact_groups(spark, odd, counters):
    rng = random.Random(2)
    made = [(1000 + i, rng.choice(["hot text", "hot  text", "hottext", f"own {i}", f"pair {i // 2}"])) for i in range(300)]
    df = odd.select("doc_id", "text").union(spark.createDataFrame(made, "doc_id long, text string"))
    expected = exact(df.collect())
    got = exact_dedup.exact_groups(df, counters=counters).collect()
    assert len(got) == df.count()
    for r in got:
        assert (r.keep_id, r.group_size, r.kept, r.text_sha256) == expected[r.doc_id]
    kept = exact_dedup.deduplicate(df, counters=counters)
    assert {r.doc_id for r in kept.collect()} == {i for i, e in expected.items() if e[2]}


def test_exact_groups_of_odd_columns_and_nothing(odd, none):
    assert exact_dedup.deduplicate(odd).columns == odd.columns
    assert exact_dedup.exact_groups(none).collect() == []


def test_exact_sql(spark):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    df = queries.op6_exact_dedup(spark, SF)
    cur = con.execute(queries.ORACLE["op6_exact_dedup"])
    assert [d[0] for d in cur.description] == df.columns
    assert sorted(map(tuple, df.collect())) == sorted(cur.fetchall())


def test_frequent_items_keep_what_is_frequent():
    rng = random.Random(1)
    items = ["hot"] * 400 + [f"x{i}" for i in range(900)] + ["warm"] * 200
    rng.shuffle(items)
    summary = exact_dedup.FrequentItems(8)
    for at in range(0, len(items), 50):
        seen = collections.Counter(items[at : at + 50])
        summary.add(list(seen), list(seen.values()))
    assert {"hot", "warm"} <= set(summary.held) and len(summary.held) <= 8


def near(rows):
    sets = {}
    for i, t in rows:
        w = re.findall("[^\x20\x09-\x0d]+", (t or "").translate(ASCII))
        sets[i] = {tuple(w)} if 0 < len(w) < 5 else {tuple(w[k : k + 5]) for k in range(len(w) - 4)}
    uf = components.UnionFind()
    ids = sorted(sets)
    for x, i in enumerate(ids):
        uf.root(i)
        for j in ids[:x]:
            both = len(sets[i] & sets[j])
            if both and 100 * both >= 75 * len(sets[i] | sets[j]):
                uf.join(i, j)
    return {i: (len(sets[i]), uf.root(i)) for i in ids}


def edited(rng, words, share):
    return " ".join(rng.choice(["zz", "yy", f"q{rng.random()}"]) if rng.random() < share else w for w in words)


def test_near_duplicates(spark, odd):
    rng = random.Random(6)
    bases = [[f"w{rng.randint(0, 400)}" for _ in range(rng.randint(5, 300))] for _ in range(12)]
    made = [(1000 + i, edited(rng, rng.choice(bases), rng.choice([0, 0.005, 0.01, 0.02, 0.03, 0.06]))) for i in range(350)]
    df = odd.select("doc_id", "text").union(spark.createDataFrame(made, "doc_id long, text string"))
    expected = near(df.collect())
    got = minhash.near_duplicates(df).collect()
    assert len(got) == df.count()
    for r in got:
        assert (r.n_shingles, r.component_id) == expected[r.doc_id] and r.kept == (r.doc_id == r.component_id)
    assert {r.doc_id for r in minhash.one_of_each(df).collect()} == {i for i, e in expected.items() if e[1] == i}


def test_near_duplicates_in_small_blocks(spark, monkeypatch):
    """With tiny blocks, chunks of a bucket meet each other, and nothing is lost."""
    monkeypatch.setattr(minhash, "BLOCK", 4)
    monkeypatch.setattr(dealt, "BROADCAST_ROWS", 0)
    monkeypatch.setattr(dealt, "KEY_ROWS", 3)
    rng = random.Random(8)
    base = [f"w{i}" for i in range(80)]
    made = [(i, edited(rng, base, rng.choice([0.01, 0.02, 0.04]))) for i in range(90)]
    df = spark.createDataFrame(made, "doc_id long, text string")
    expected = near(made)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(df).collect()} == expected


def test_texts_under_a_repeated_id_are_not_lost(spark):
    """Rows are told apart by id and text, and null ids come after all others."""
    long = " ".join(f"w{i}" for i in range(40))
    rows = [(5, "alpha text"), (5, "beta text"), (3, "beta text"), (None, "gamma text"), (None, "beta  text"), (None, "gamma text"), (7, long), (7, "other"), (8, long + " end"), (7, long)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    left = {(5, "alpha text"), (3, "beta text"), (None, "gamma text"), (7, long), (7, "other"), (8, long + " end")}
    assert {tuple(r) for r in exact_dedup.deduplicate(df).collect()} - {(None, "beta  text"), (3, "beta text")} == left - {(3, "beta text")}
    assert {tuple(r) for r in minhash.one_of_each(df).collect()} == left - {(8, long + " end")}
    got = {(r.id, r.place): r.component for r in minhash.groups(df).collect()}
    assert sorted(map(str, got.values())) == sorted(map(str, [5, 3, 3, None, 3, 7, 7, 7]))


def test_hot_keys_are_dealt_out(spark, monkeypatch):
    monkeypatch.setattr(dealt, "KEY_ROWS", 10)
    left = spark.range(1000).selectExpr("id", "CASE WHEN id < 700 THEN 1 ELSE id END AS k")
    right = spark.range(900).selectExpr("id AS k", "id * 2 AS twice")
    for how, n in (("inner", 900), ("left", 1000)):
        met = dealt.join_dealt(left, right, "k", "id", dealt.sizes_of(left, "k"), 1000, how)
        assert met.count() == n and met.where("k = 1 AND twice = 2").count() == 700 and met.columns == ["k", "id", "twice"]
    monkeypatch.setattr(dealt, "BROADCAST_ROWS", 0)
    assert sorted(dealt.beside(left, right, "k", "id").collect()) == sorted(left.join(right, "k").collect())


def test_buckets_of_the_same_members_are_one(spark):
    draw = random.Random(3)
    rows = [(i, b, b * 100 + draw.randrange(3) if i < 40 else b * 100 + 50 + i // 2) for i in range(60) for b in range(12)]
    kept = {r["key"]: (r["size"], r["copies"]) for r in minhash._buckets(spark.createDataFrame(rows, "id long, band int, key long")).collect()}
    members = collections.defaultdict(set)
    for i, _, key in rows:
        members[key].add(i)
    same = collections.defaultdict(list)
    for key, ids in members.items():
        if len(ids) > 1:
            same[frozenset(ids)].append(key)
    assert kept == {min(keys): (len(ids), len(keys)) for ids, keys in same.items()}
    # no pair loses the first bucket that it shares
    first = {}
    for key in sorted(members):
        for a in members[key]:
            for b in members[key]:
                if a < b:
                    first.setdefault((a, b), key)
    assert set(first.values()) <= set(kept)


def test_near_duplicates_of_nothing(none, odd):
    assert minhash.near_duplicates(none).collect() == []
    assert minhash.one_of_each(odd).columns == odd.columns


def test_signatures_estimate():
    import numpy as np

    rng = np.random.default_rng(1)
    pool = rng.integers(0, 2**63, 3000, dtype=np.uint64)
    for n, shared in ((900, 450), (60, 40), (3, 2), (1, 1)):
        a, b = np.unique(pool[:n]), np.unique(pool[n - shared : 2 * n - shared])
        x, y = minhash.signatures([a, b])
        assert abs((x == y).mean() - shared / (2 * n - shared)) < 0.17
        assert (x < minhash.EMPTY).all()


def test_components(spark):
    rng = random.Random(3)
    links = [(i, i + 1) for i in range(60)] + [(rng.randint(100, 300), rng.randint(100, 300)) for _ in range(90)] + [(500, 400), (400, 500)]
    uf = components.UnionFind()
    for x, y in links:
        uf.join(x, y)
    got = components.components(spark.createDataFrame(links, "a long, b long").repartition(7)).collect()
    assert {r.id: r.component for r in got} == {x: uf.root(x) for p in links for x in p if p[0] != p[1]}


ITEMS = [(i, t) for i, t in enumerate(["the quick brown fox jumps over the lazy dog and runs far away from all the noise of town", "Alpha beta gamma, delta epsilon zeta eta theta iota kappa lambda mu nu xi", None, "", "short item"])]


def passages(docs, items):
    """The least edit distance of an item to any passage, by the plain recurrence."""
    out = {}
    for d, text in docs:
        words = decontaminate.words_of(text)
        for i, item in items:
            p = decontaminate.words_of(item)
            if not p:
                continue
            row = [0] * (len(words) + 1)
            for a in p:
                new = [row[0] + 1]
                for j, c in enumerate(words, 1):
                    new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (a != c)))
                row = new
            if min(row) <= decontaminate.edits_allowed(len(p)):
                out[d, i] = (min(row), row.index(min(row)))
    return out


def test_decontamination(spark, odd):
    rng = random.Random(5)
    docs = [(r.doc_id, r.text) for r in odd.select("doc_id", "text").distinct().collect() if r.doc_id < 100 and len(r.text or "") < 1000]
    for i in range(120):
        words = [f"v{rng.randint(0, 60)}" for _ in range(rng.randint(0, 80))]
        item = ITEMS[rng.choice([0, 1, 4])][1].split()
        for _ in range(rng.randint(0, 5)):
            at = rng.randrange(len(item)) if item else 0
            item[at : at + rng.choice([0, 1])] = rng.choice([[], ["new"]])
        at = rng.randint(0, len(words))
        docs.append((1000 + i, " ".join(words[:at] + item + words[at:]).upper()))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    expected = passages(docs, ITEMS)
    for block in (20_000, 2):
        got = {(r.doc_id, r.item_id): (r.distance, r.end_word) for r in decontaminate.contaminated(df, items, block_items=block).collect()}
        clean = decontaminate.without_contaminated(df, items, block_items=block)
        assert {r.doc_id for r in clean.collect()} == {d for d, _ in docs} - {d for d, _ in got}
        assert set(got) <= set(expected) and len(got) >= 0.97 * len(expected)
        assert all(expected[k] == v for k, v in got.items())
        assert all(k in got for k, v in expected.items() if v[0] == 0)


def test_decontamination_of_nothing(spark, none, odd):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    assert decontaminate.contaminated(none, items).collect() == []
    assert decontaminate.contaminated(odd, items.limit(0)).collect() == []
    assert decontaminate.without_contaminated(odd, items).columns == odd.columns
    nameless = spark.createDataFrame([(None, ITEMS[0][1]), (-1, ITEMS[1][1])], "item_id long, text string")
    docs = spark.createDataFrame([(1, ITEMS[0][1]), (2, ITEMS[1][1])], "doc_id long, text string")
    assert {(r.doc_id, r.item_id) for r in decontaminate.contaminated(docs, nameless).collect()} == {(1, None), (2, -1)}


def test_exact_passages_of_the_tables_are_all_found(spark):
    docs, items = (queries.table(spark, SF, t).collect() for t in ("documents", "benchmark"))
    plain = {(d.doc_id, b.item_id) for d in docs for b in items if b.text in d.text}
    got = {(r.doc_id, r.item_id) for r in queries.op5_decontamination(spark, SF).collect()}
    assert plain <= got
