"""Null ids, repeated rows, ties, very long texts and clashing column names, for every operator that reads documents."""

import random
import zlib
from collections import Counter

import pytest
from pyspark.sql import functions as F

from slidemedian.llm import bpe_transducer, encoding, exact_dedup, language_id, near_dedup, packing, quality, token_files, toxicity

JSON, RANKS, PIECES = (encoding.public_path(n) for n in ("byte_bpe_50k.json", "byte_bpe_multi_50k.tiktoken", "piece_bpe_32k.model"))
CLASHES = ["score", "held_out", "predicted", "selected", "log_weight", "lang_pred", "start", "shard", "place", "ids", "row", "hash", "entry", "bucket", "cluster", "v", "kept", "component_id", "n_shingles", "draw", "counts", "label", "toxic"]


@pytest.fixture(scope="module")
def odd(spark):
    rng = random.Random(4)
    words = ["river", "stone", "garden", "the", "of", "window", "house"]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    long = text(700_000)  # some 4 MB, more than a slice
    rows = [(i, text(30), "en") for i in range(60)]
    rows += [(None, text(20), "en"), (None, None, None), (3, rows[3][1], "en"), (3, rows[3][1], "en"), (4, "another text of the same id", "en")]
    rows += [(70, long, "en"), (71, "x" * 100_000, "en"), (72, "", "en"), (73, "😀 é \u0000 z", None), (74, "\n\t ", "en"), (75, rows[5][1], "en")]
    table = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    return table.withColumns({c: F.lit("clash") for c in CLASHES}).repartition(3)


@pytest.fixture(scope="module")
def labels(spark):
    rows = [(i, int(i % 7 != 0), int(i % 9 == 0), "x") for i in range(60)] + [(5, 0, 1, "x"), (None, 1, 1, "x"), (72, 1, 0, "x"), (6, None, None, "x"), (999, 1, 1, "x"), (7, 5, 5, "x")]
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int, text string")


def ids(df):
    return Counter(r["doc_id"] for r in df.select("doc_id").collect())


def test_every_row_is_reported_once(spark, odd, labels):
    wanted = ids(odd)
    for report in (
        toxicity.score_documents(odd, labels),
        quality.resample(odd, labels),
        language_id.predict(odd, PIECES),
        exact_dedup.exact_duplicates(odd),
        near_dedup.near_duplicates(odd),
        bpe_transducer.round_trip_digests(odd, RANKS),
        token_files.token_file_report(odd, JSON, added=True),
    ):
        assert ids(report) == wanted
    pieces = packing.pack_documents(odd, JSON, added=True)
    assert set(ids(pieces)) == set(wanted)


def test_rows_that_tie_or_repeat_are_judged_alike(spark, odd, labels):
    scored = toxicity.score_documents(odd, labels).collect()
    assert len({(r["score"], tuple(r["evidence"])) for r in scored if r["doc_id"] == 3}) == 1
    assert len({r["score"] for r in scored if r["doc_id"] in (5, 75)}) == 1  # equal texts, and contradicting labels of one of them
    assert all(not r["held_out"] for r in scored if r["doc_id"] is None)
    drawn = quality.resample(odd, labels).collect()
    assert len({(r["log_weight"], r["gumbel_key"], r["selected"]) for r in drawn if r["doc_id"] == 3}) == 1
    judged = language_id.predict(odd, PIECES).collect()
    assert {r["lang_pred"] for r in judged if r["doc_id"] in (72, 74)} == {"und"} and {r["lang_pred"] for r in judged if r["doc_id"] in (70, 71)} == {"en"}


def test_filters_keep_all_columns(odd, labels):
    for kept in (language_id.keep_known(odd, PIECES), quality.keep_drawn(odd, labels), exact_dedup.drop_exact(odd), near_dedup.keep_one_each(odd)):
        assert kept.columns == odd.columns and {r["score"] for r in kept.collect()} == {"clash"}
    assert ids(exact_dedup.drop_exact(odd))[3] == 1


def test_token_files_start_where_the_last_document_ended(odd):
    rows = sorted(token_files.token_file_report(odd, JSON, added=True).collect(), key=lambda r: r["start"])
    at, last = 0, None
    for r in rows:
        assert r["start"] == at and (last is None or (r["doc_id"] is not None and r["doc_id"] >= last))
        at, last = at + r["n_tokens"], r["doc_id"] if r["doc_id"] is not None else last
    nul = next(r for r in rows if r["doc_id"] == 72)
    assert (nul["n_tokens"], nul["ids_crc32"]) == (1, zlib.crc32(bytes(4)))


def test_empty_tables(spark, odd, labels):
    none, unlabelled = odd.limit(0), labels.limit(0)
    for empty in (
        toxicity.score_documents(none, labels),
        quality.resample(none, labels),
        quality.keep_drawn(none, unlabelled),
        language_id.predict(none, PIECES),
        language_id.keep_known(none, PIECES),
        exact_dedup.drop_exact(none),
        near_dedup.keep_one_each(none),
        bpe_transducer.round_trip_digests(none, RANKS),
        packing.pack_documents(none, JSON),
        token_files.token_file_report(none, JSON),
    ):
        assert empty.count() == 0
