"""Classifiers by held-out accuracy, tokenizers against their library, and the pipeline stage by stage."""

import hashlib
import zlib

import pytest
import sentencepiece

import corpus_pipeline
from pairbalance.llm import exact_dedup, language, minhash, piece_codec, pieces, quality, queries, token_counts

SF = "/root/testdata/sf0.001"

SF_LARGER = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def library():
    return sentencepiece.SentencePieceProcessor(model_proto=pieces.model_bytes())


def test_encoding_and_counts(spark, odd, library):
    df = odd.select("doc_id", "text").union(queries.table(spark, SF, "documents").selectExpr("doc_id + 1000", "text"))
    texts = dict(df.collect())
    rows = piece_codec.encode_digests(df).collect()
    assert len(rows) == df.count()
    for r in rows:
        ids = library.encode(texts[r.doc_id] or "", add_eos=True)
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(library.decode(ids).encode()).hexdigest()
    for r in token_counts.count_tokens(df).collect():
        n = len(library.encode(texts[r.doc_id] or ""))
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len((texts[r.doc_id] or "").encode()), n, n > 4096)


def test_runs_of_spaces_and_odd_words(library):
    encoder, merger = piece_codec.PrefixEncoder(pieces.model_bytes()), token_counts.RankMerger(pieces.model_bytes())
    texts = [" " * n + x for n in range(40) for x in ("", "a", "\n", "the ", "日")] + ["ab" * 500, "a" * 999, "\n\n\n", "▁▁", " \n \n"]
    for t, n in zip(texts, merger.totals(texts), strict=True):
        ids = library.encode(t)
        assert encoder.encode_text(t) == " ".join(map(str, [*ids, library.eos_id()])) and n == len(ids)
        assert encoder.decode(encoder.encode_text(t)) == library.decode(ids)


def test_whole_ids_and_text_come_back(spark, odd):
    row = piece_codec.encode_documents(odd).where("doc_id = 9").first()
    assert row.decoded == "a b c d e f g h" and row.ids.endswith(" 2")


def test_tokenizers_of_nothing(none):
    assert piece_codec.encode_digests(none).collect() == token_counts.count_tokens(none).collect() == []


def test_language(spark, odd, none):
    df = queries.table(spark, SF_LARGER, "documents")
    rows = language.identify(df).join(df.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r.held_out]
    assert len(rows) == df.count() and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    assert sum(r.lang_pred == r.lang for r in held) >= 0.98 * len(held) and all(0 <= r.score <= 1 for r in rows)
    got = {r.doc_id: r for r in language.identify(odd).collect()}
    assert got[0].lang_pred == got[1].lang_pred == got[3].lang_pred == "und" and got[5].lang_pred != "und"
    assert language.identify(none).collect() == []
    assert {r.lang_pred for r in language.identify(odd.selectExpr("doc_id", "text", "CAST(NULL AS STRING) AS lang")).collect()} == {"und"}


def test_quality(spark, odd, none):
    df, labels = queries.table(spark, SF_LARGER, "documents"), queries.table(spark, SF_LARGER, "labels")
    rows = quality.score_documents(df, labels).join(labels, "doc_id").collect()
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and r.predicted == (r.score >= 0.7) for r in rows)
    assert sum(r.predicted == r.quality for r in held) >= 0.95 * len(held)
    assert quality.score_documents(odd, labels).count() == odd.count() and quality.score_documents(none, labels).collect() == []
    assert {r.score for r in quality.score_documents(odd, labels.limit(0)).collect()} == {0.5}
    assert quality.keep_good(odd, labels).columns == odd.columns


def test_pipeline(spark):
    """Each stage on what the one before kept: decisions take effect, and clean documents stay."""
    assert [len(corpus_pipeline.STAGES), corpus_pipeline.STAGES[-1][1]] == [5, corpus_pipeline.as_pieces]
    docs = queries.table(spark, SF, "documents")
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r.text for r in at.collect()}
        after = {r.doc_id: r.text for r in stage(spark, at, SF).collect()}
        assert after.items() <= before.items()
        if name == "quality classifier":
            scores = quality.score_documents(at, queries.table(spark, SF, "labels"))
            assert set(after) == {r.doc_id for r in scores.collect() if r.predicted}
        if name == "exact dedup":
            assert set(after) == {r.doc_id for r in exact_dedup.exact_groups(at).collect() if r.kept}
        if name == "near-duplicate removal":
            assert set(after) == {r.doc_id for r in minhash.near_duplicates(at).collect() if r.kept}
        if name == "benchmark decontamination":
            items = queries.table(spark, SF, "benchmark").collect()
            assert not any(b.text in t for t in after.values() for b in items)
        at = spark.createDataFrame(stage(spark, at, SF).collect(), docs.schema)
    final = {r.doc_id: r.n_tokens for r in corpus_pipeline.run(spark, SF).collect()}
    assert set(final) == {r.doc_id for r in at.collect()} and all(n > 1 for n in final.values())


@pytest.mark.parametrize("empty", [False, True])
def test_stages_on_odd_tables(spark, odd, none, empty):
    """Nulls, empty and long texts, repeated rows and clashing columns pass through all stages; nothing gives nothing."""
    docs = none if empty else odd
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, SF)
        assert after.columns == docs.columns, name
        rows = after.collect()
        assert {(r.doc_id, r.text) for r in rows} <= {(r.doc_id, r.text) for r in docs.collect()} and not (empty and rows), name
    assert corpus_pipeline.as_pieces(spark, docs, SF).count() == docs.count()
    left = {r.doc_id for r in corpus_pipeline.without_copies(spark, docs, SF).collect()}
    assert empty or {3, 5, 14} <= left and not left & {0, 1, 2, 100, 101}  # of texts without words the longest stays
