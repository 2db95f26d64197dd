"""License scan, URL filter and personal data against brute force."""

import hashlib
import random
import re

import duckdb
import numpy as np
import pytest

from pairbalance.llm import license_scan, pii, queries, url_filter

SF = "/root/testdata/sf0.001"

ASCII = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def license_base(text):
    words = re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", (text or "").translate(ASCII))
    starts, labels = [], set()
    for phrase, label in license_scan.BASE.items():
        parts = phrase.split()
        at = [i for i in range(len(words)) if words[i : i + len(parts)] == parts]
        starts += at
        labels |= {label} if at else set()
    return len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(labels)), words


def license_labels(words):
    """All signatures on all texts, without any prefilter."""
    joined, places = f" {' '.join(words)} ", []
    for priority, (label, _, pattern) in enumerate(license_scan.SIGNATURES):
        for m in re.finditer(f"(?<= )(?:{pattern})(?= )", joined):
            start = joined[: m.start()].count(" ") - 1
            places.append((start, -(m.group().count(" ") + 1), priority, label))
    reach, kept = -1, []
    for start, minus, _, label in sorted(places):
        if start - minus > reach:
            kept.append(label)
        reach = max(reach, start - minus)
    return kept


@pytest.mark.parametrize("source", ["odd", "table", "planted"])
def test_license_scan(spark, odd, source):
    rng = random.Random(4)
    notices = [p.replace("(?: ", " ").replace("?", "") for _, _, p in license_scan.SIGNATURES if not set(p) & set("()[|")]
    planted = [(i, " ".join(rng.sample(["alpha", "Beta.", "gamma,", *rng.sample(notices, 2), "MIT License", "cc-by", "Apache License, Version 2.0"], 6))) for i in range(60)]
    df = {"odd": odd, "table": queries.table(spark, SF, "documents"), "planted": spark.createDataFrame(planted, "doc_id long, text string")}[source]
    texts = df.select("doc_id", "text").collect()
    got = license_scan.scan(df).collect()
    assert len(got) == len(texts)
    found = {r.doc_id: r for r in got}
    for doc_id, text in texts:
        *base, words = license_base(text)
        r = found[doc_id]
        assert [r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels] == base
        kept = license_labels(words)
        assert r.labels == ",".join(sorted({*kept, *filter(None, base[4].split(","))})), text
        assert abs(r.score - len(kept) / (len(kept) + 1)) < 1e-9


def test_every_signature_passes_the_gate(spark):
    """Each text that a signature matches holds its keyword and a piece that the gate looks for."""
    for label, keyword, pattern in license_scan.SIGNATURES:
        assert keyword in pattern or re.search(pattern, keyword), (label, keyword)
        assert any(e in pattern.replace("[sc]", "s").replace("licens", "licen") for e in license_scan.EVIDENCE) or "cc" in pattern, label
    assert len(license_scan.SIGNATURES) > 200


def all_matched(parsed):
    """Every text that a parsed signature matches."""
    out = [""]
    for op, arg in parsed:
        match str(op):
            case "LITERAL":
                parts = [chr(arg)]
            case "IN":
                parts = [chr(c) for _, c in arg]
            case "SUBPATTERN":
                parts = all_matched(arg[-1])
            case "BRANCH":
                parts = [t for b in arg[1] for t in all_matched(b)]
            case "MAX_REPEAT":
                assert arg[:2] == (0, 1)
                parts = ["", *all_matched(arg[2])]
            case _:
                raise ValueError(op)
        out = [a + b for a in out for b in parts]
    return out


def test_every_text_of_a_signature_passes_gate_and_keyword():
    for label, keyword, pattern in license_scan.SIGNATURES:
        for text in all_matched(re._parser.parse(pattern)):
            assert re.fullmatch(pattern, text)
            words = text.split()
            assert set(license_scan.FORMS.get(keyword, (keyword,))) & set(words), (label, text)
            assert any(e in w for w in words for e in license_scan.EVIDENCE) or re.search(license_scan.CC, text), (label, text)


def test_license_scan_of_glued_and_optional_words(spark):
    texts = ["under AGPLv3", "AGPL3 only", "LGPLv2.1 or later", "lgpl2.1", "LGPLv3.0", "GPL3", "GPL2 only and GPLv2", "GPLv1 or later", "Beerware License", "MIT No Attribution", "Public Domain Dedication and License", "AGPL v3 and AGPLv3"]
    found = {r.doc_id: r for r in license_scan.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for k, text in enumerate(texts):
        kept = license_labels(license_base(text)[-1])
        assert kept and found[k].labels == ",".join(sorted(set(kept))), text
        assert abs(found[k].score - len(kept) / (len(kept) + 1)) < 1e-9


def test_license_scan_of_nothing(none):
    assert license_scan.scan(none).collect() == []


URLS = [
    None, "", "no scheme", "http://", "https://A.Example.ORG/es/x?y=/de/", "http://example.org/en/12", "http://notexample.org/en/1", "http://example.org", "http://x.com/fr/a#/de/", "http://x.com/de/",
    "http://x.com?/de/", "a://b://c.com/de/", "https://www.spam-farm.example.net/en/1", "http://buy.example.net/cheap-viagra", "http://x.net/a.exe", "http://x.net/exe", "http://docs.x.net/cheap-pills/", "http://x.net/cgi-bin/s", "http://x.net/über/casino-win.",
]


def test_url_filter(spark):
    rows = [(i, u, "h", "p") for i, u in enumerate(URLS)] + [(4, URLS[4], "h", "p")]
    pages = spark.createDataFrame(rows, "page_id long, url string, host string, path string")
    con = duckdb.connect()
    con.execute("CREATE TABLE pages (page_id BIGINT, url VARCHAR)")
    con.executemany("INSERT INTO pages VALUES (?, ?)", [r[:2] for r in rows])
    got = sorted(map(repr, map(tuple, url_filter.judge(pages).collect())))
    assert got == sorted(map(repr, con.execute(url_filter.oracle_sql()).fetchall()))
    verdicts = {r.page_id: (r.rule, r.verdict) for r in url_filter.judge(pages).collect()}
    assert verdicts[4] == ("example.org/es/", "block") and verdicts[6] == ("org/", "allow") and verdicts[7] == (None, "allow")
    assert verdicts[8] == ("com/fr/", "allow") and verdicts[12] == (None, "block") and verdicts[14] == (None, "block") and verdicts[15] == (None, "allow")
    assert url_filter.judge(pages.limit(0)).collect() == []


def test_rules_are_filed_under_their_rarest_token():
    index = url_filter.rarest_index({"cheap": 9, "pills": 2}, [("block", ("cheap", "pills"), "x")])
    assert list(index) == ["pills"]


def luhn(digits):
    return sum(sum(divmod(int(c) * 2, 10)) if i % 2 else int(c) for i, c in enumerate(digits[::-1])) % 10 == 0


def base_spans(text):
    text, out = text or "", []
    out += [(0, *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)] if "@" in text else []
    out += [(1, *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        digits = re.sub("[^0-9]", "", m.group())
        out += [(2, *m.span())] if 16 <= len(digits) <= 19 and luhn(digits) else []
    out += [(3, *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return sorted(out)


@pytest.mark.parametrize("source", ["odd", "table", "random"])
def test_personal_data(spark, odd, source):
    rng = random.Random(9)
    parts = ["a.b@c.com", "_foo@x.org", "@", ".", "..", "1.2.3.4", "5", "999", "+1 (743) 555-3824", "4111 1111 1111 1111", " ", "-", "+", "(499) 555-6503", "😀", "é", "0", "4111111111111112", "a@b.c..d@e.f", "text "]
    made = [(i, "".join(rng.choice(parts) for _ in range(rng.randint(0, 25)))) for i in range(400)]
    df = {"odd": odd, "table": queries.table(spark, SF, "documents"), "random": spark.createDataFrame(made, "doc_id long, text string")}[source]
    texts = df.select("doc_id", "text").collect()
    got = {r.doc_id: r for r in pii.find(df).collect()}
    for doc_id, text in texts:
        base, r = base_spans(text), got[doc_id]
        lines = [f"{pii.KINDS[k]}:{s}:{e}" for k, s, e in base]
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == i for k, _, _ in base) for i in range(4)], text
        assert r.base_sha256 == hashlib.sha256(",".join(lines).encode()).hexdigest(), text
        assert set(lines) <= set(r.spans.split(",")) or not lines


def test_personal_data_in_long_runs(spark):
    texts = ["a@" + "b.c." * 20_000 + "d", "9" * 60_000, "x" * 100_000 + "@", "+" + "1(" * 20_000, "1 2 3 4 " * 5_000]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in pii.find(df).collect()}
    assert [got[i].n_email for i in range(5)] == [1, 0, 0, 0, 0]
    assert sum(r.n_card + r.n_phone + r.n_ip for r in got.values()) == 0


def test_personal_data_of_nothing(none):
    assert pii.find(none).collect() == []


def test_looser_spans_are_added(spark):
    rows = [(i, f"mail u{i}@host.com or +1 (743) 555-{3000 + i}") for i in range(50)] + [(99, "tel (499) 555-6503 now")]
    got = {r.doc_id: r for r in pii.find(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[99].spans == "phone:4:18" and got[99].n_phone == 0


def test_reliabilities_of_planted_labelers():
    """Votes drawn by labelers of known reliability, against a poor one that is right half of the time."""
    rng = np.random.default_rng(3)
    truth = rng.random(4000) < 0.6
    planted = np.array([[0.95, 0.9], [0.8, 0.85], [0.5, 0.5], [0.9, 0.7]])
    votes = np.stack([np.where(rng.random(4000) < np.where(truth, *p), np.where(truth, 1, -1), np.where(truth, -1, 1)) for p in planted], 1)
    votes[rng.random(votes.shape) < 0.3] = 0
    rows, counts = np.unique(votes, axis=0, return_counts=True)
    right, chance = pii.reliabilities(rows, np.zeros(len(rows), int), counts.astype(float))
    assert np.abs(right - planted).max() < 0.08
    at = {tuple(r): c for r, c in zip(rows, chance, strict=True)}
    judged = np.array([at[tuple(v)] >= 0.5 for v in votes])
    majority = votes.sum(1) > 0
    # the best that can be had, knowing the planted reliabilities
    odds = np.log(0.6 / 0.4) + (votes == 1) @ np.log(planted[:, 0] / (1 - planted[:, 1])) + (votes == -1) @ np.log((1 - planted[:, 0]) / planted[:, 1])
    best = ((odds >= 0) == truth).mean()
    assert (judged == truth).mean() >= best - 0.01 and (judged == truth).mean() > (majority == truth).mean() + 0.02


def test_span_classifier_follows_the_chances():
    names = list(pii.FIELDS)
    rows = np.array([[r, g, c, e, 3, 1] for r in range(3) for g in range(3) for c in range(3) for e in range(2)])
    chance = np.where(rows[:, names.index("context")] == 2, 0.95, 0.05)  # the context alone decides
    weights, bias = pii.span_classifier(rows, chance, np.ones(len(rows)))
    score = bias + sum(np.array(w)[rows[:, f]] for f, w in enumerate(weights))
    assert ((score >= 0) == (chance > 0.5)).all()


def test_votes_overrule_a_pattern(spark):
    """Hits of one loose pattern: those behind words for phones stay, those behind words for things go."""
    rows = [(i, f"phone 212.{300 + i}.1234 now") for i in range(30)] + [(100 + i, f"part 212.{300 + i}.1234 ref") for i in range(30)]
    rows += [(200 + i, f"mail u{i}@host.com or +1 (743) 555-{3000 + i}") for i in range(30)] + [(300, "card 4111111111111112"), (301, 'token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" x'), (302, "token: abcdefghijklmnopqrstuvw")]
    got = {r.doc_id: r for r in pii.find(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[i].spans == "phone:6:18" and got[i].n_phone == 0 for i in range(30))
    assert all(got[100 + i].spans == "" for i in range(30))
    assert all(got[200 + i].n_spans == 2 for i in range(30))
    assert got[300].spans == "" and got[301].spans.startswith("secret:0:") and got[302].spans == ""


def test_personal_data_of_the_tables(spark):
    """What is planted in the documents: base spans of all kinds, and every assigned token."""
    docs = queries.table(spark, SF, "documents")
    got = {r.doc_id: r.spans for r in pii.find(docs).collect()}
    for doc_id, text in docs.select("doc_id", "text").collect():
        tokens = len(re.findall(r'(?i)token = "[0-9a-f]{40}"', text or ""))
        assert got[doc_id].count("secret:") == tokens
        assert bool(got[doc_id]) == bool(tokens or base_spans(text))


def matched(parsed):
    """Texts that a parsed pattern of the URL rules matches: one or two of each repeat."""
    out = [""]
    for op, arg in parsed:
        match str(op):
            case "LITERAL":
                parts = [chr(arg)]
            case "NOT_LITERAL" | "ANY":
                parts = ["x"]
            case "IN":
                if str(arg[0][0]) == "NEGATE":
                    parts = ["/"]
                else:
                    parts = [chr(v) if str(k) == "LITERAL" else chr(v[0]) for k, v in arg]
            case "AT":
                parts = [""]
            case "SUBPATTERN":
                parts = matched(arg[-1])
            case "BRANCH":
                parts = [t for b in arg[1] for t in matched(b)]
            case "MAX_REPEAT":
                once = matched(arg[2])
                parts = (["", *once] if arg[0] == 0 else once)[:3]
            case _:
                raise ValueError(op)
        out = [a + b for a in out for b in parts][:400]
    return out


def test_every_match_of_a_url_rule_holds_its_tokens():
    for _, tokens, pattern in url_filter.PATTERN_RULES:
        plain = pattern.replace("\\z", "$")
        texts = [a + t + b for t in matched(re._parser.parse(plain)) for a in ("", "http://a.b/") for b in ("", "5", "/x", "?q")]
        texts = [t for t in texts if re.search(pattern.replace("\\z", r"\Z"), t)]
        assert texts and all(set(tokens) <= set(re.split("[^a-z0-9]+", t)) for t in texts), pattern


def test_url_rules_at_the_end(spark):
    urls = ["http://a.net/wp-login.php5?x", "http://a.net/wp-login.php?x", "http://a.net/" + "x" * 50_000 + ".exe", "http://a.net/a.exe\n", None]
    rows = [(i, u) for i, u in enumerate(urls)]
    con = duckdb.connect()
    con.execute("CREATE TABLE pages (page_id BIGINT, url VARCHAR)")
    con.executemany("INSERT INTO pages VALUES (?, ?)", rows)
    got = url_filter.judge(spark.createDataFrame(rows, "page_id long, url string")).collect()
    assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, con.execute(url_filter.oracle_sql()).fetchall()))
    assert {r.page_id: r.verdict for r in got} == {0: "allow", 1: "block", 2: "block", 3: "allow", 4: "allow"}
