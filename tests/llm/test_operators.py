"""Training-data operators against brute force, libraries and round trips."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from slidemedian.llm import bpe_transducer, embedding_dedup, encoding, exact_dedup, graph, language_id, near_dedup, packing, quality, shared, token_files, toxicity, url_filter

JSON, RANKS, PIECES = (encoding.public_path(n) for n in ("byte_bpe_50k.json", "byte_bpe_multi_50k.tiktoken", "piece_bpe_32k.model"))
ODD = [None, "", " ", "a", "  two  spaces\t and\n\nlines \r\n", "it's we'll 'tis", "naïve façade – Ωmega 数学 😀", "x" * 5000, "<|endoftext|> as text", "\x1c odd\x85space\u00a0here"]


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(1)
    words = ["".join(rng.choice("abcdeéñß") for _ in range(rng.randrange(1, 9))) for _ in range(400)]
    texts = list(ODD)
    for _ in range(60):
        texts.append(" ".join(rng.choice(words) for _ in range(rng.randrange(1, 200))))
    texts += texts[10:20] + [" ".join(rng.choice(words) for _ in range(9000))]
    rows = [(i, t, "en", "s", 0, "clash", True) for i, t in enumerate(texts)]
    rows.append((5, texts[5], "en", "s", 0, "clash", True))  # a repeated row
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_shingles string, kept boolean").repartition(3)


@pytest.fixture(scope="module")
def empty(spark, docs):
    return spark.createDataFrame([], docs.schema)


def texts_of(docs):
    return sorted((r["doc_id"], r["text"] or "") for r in docs.select("doc_id", "text").collect())


def library_ids(text, added=False):
    from tokenizers import Tokenizer

    if not hasattr(library_ids, "t"):
        library_ids.t = Tokenizer.from_file(JSON)
    library_ids.t.encode_special_tokens = not added
    return library_ids.t.encode(text, add_special_tokens=False).ids


def crc(ids):
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_units_of_chunks_have_the_ids_of_whole_texts():
    rng = np.random.default_rng(11)
    letters = [*"abstrevlmdZ", "the", "é", "ß", "Ø", "\u0237", "\u027f", "\u0301", "×", "÷", "ª", "ж", "数", "€", "²", "😀"]
    others = [*"''.,!&$<|>_-0189\n\r\t\x1c\x1f\x00\x7f", "\n\n", "\u0085", "\u00a0", "\u3000", "\u2028"]
    texts = ["".join(rng.choice([*letters, *others, " ", " "], size=rng.integers(1, 30))) for _ in range(4000)]
    texts += [f"go it{a}{b}{c} on it{a}{b}" for a in others for b in others for c in ("s", "Re", "é", "×", "1")]
    words = [w for t in texts for w in t.split(" ")]
    parts, counts = encoding.units(pa.array(words, pa.string()).slice(3))
    at = np.cumsum(counts) - counts
    assert ["".join(parts.slice(low, n).to_pylist()) for low, n in zip(at.tolist(), counts.tolist(), strict=True)] == words[3:]
    assert encoding.units(pa.array(["theandsh&&&", "", "st.\nRéan", "a's", "x\n\nY", "×a", "ß÷"]))[0].to_pylist() == ["theandsh", "&&&", "", "st", ".\n", "Réan", "a", "'s", "x", "\n\nY", "×a", "ß÷"]
    for added in (False, True):
        ids, sizes = zip(*encoding._library(JSON, added).encode_slices(pa.array(texts, pa.string())), strict=True)
        ends = np.cumsum(np.concatenate(sizes))
        for text, found in zip(texts, np.split(np.concatenate(ids), ends[:-1]), strict=True):
            assert found.tolist() == library_ids(text, added), text


def test_units_that_repeat_reach_the_library_once(monkeypatch):
    sent = []
    encoder = encoding._library(JSON, True)
    seen = encoding.joined
    monkeypatch.setattr(encoding, "joined", lambda parts: sent.append(sum(map(len, parts)) // 4) or seen(parts))
    for tail in ("", ",", ".", "!!", ".\nOn"):
        list(encoder.encode_slices(pa.array([" ".join(["x", *(f"{a}{b}zzq{tail}" for a in "abcdefgh" for b in "klmnopqr")])])))
    assert sum(sent) < 1.2 * sent[0] + 100, sent


def test_library_encoder_equals_the_library(docs):
    encoder = encoding.library_encoder(JSON)
    for _, text in texts_of(docs):
        assert encoder.encode(text) == np.array(library_ids(text), dtype="<u4").tobytes()
    # The library at its defaults, in slices, with a memo that overflows all the time.
    rng = random.Random(3)
    spaces = [" ", " ", " ", " ", "\n", "  ", "\t", " \n", "\u00a0", "\u2003 ", "<|endoftext|>", ".", "'s ", "", "\x1c", "\x85 "]
    texts = [t for t in ODD if t is not None] + ["".join(rng.choice("abcé9数") * rng.randrange(1, 5) + rng.choice(spaces) for _ in range(rng.randrange(60))) for _ in range(400)] + [" lead", "trail ", "trail\n", "\nlead", " ", "  "]
    small = encoding._library(JSON, True)
    small.memo.limit = 40
    for _ in range(2):
        found = list(small.encode_slices(pa.array([*texts, None], pa.string())))
        assert np.concatenate([sizes for _, sizes in found]).tolist() == [len(library_ids(t, True)) for t in [*texts, ""]]
        assert np.concatenate([ids for ids, _ in found]).tolist() == [i for t in texts for i in library_ids(t, True)]
        assert len(small.memo.words) <= 40


def test_transducer_equals_tiktoken_and_decodes(spark, docs, empty):
    import public_tokenizers
    import tiktoken

    ranks = bpe_transducer.read_ranks(RANKS)
    reference = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = sorted(map(tuple, bpe_transducer.round_trip_digests(docs, RANKS).collect()))
    expected = []
    for i, text in texts_of(docs):
        ids = reference.encode_ordinary(text)
        expected.append((i, len(ids), hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest(), hashlib.sha256(text.encode()).hexdigest()))
    assert got == sorted(expected)
    encoded = bpe_transducer.encode_documents(docs, RANKS)
    assert sorted((r["doc_id"], r["text"]) for r in bpe_transducer.decode_documents(encoded, RANKS).collect()) == texts_of(docs)
    assert bpe_transducer.round_trip_digests(empty, RANKS).count() == 0


def test_transducer_on_random_bytes():
    machine = bpe_transducer.transducer(RANKS).machine
    rng = random.Random(2)
    for _ in range(300):
        data = bytes(rng.choice(b"abcethins .\xc3\xa9\xff") for _ in range(rng.randrange(25)))
        assert b"".join(machine.tokens[i] for i in machine.encode(data)) == data


def test_utf8_machine_at_any_cut():
    data = "aé数😀\ud7ff".encode() + b"\xff\xe6\x95"
    for cut in range(len(data) + 1):
        machine = bpe_transducer.Utf8Machine()
        text = machine.feed(data[:cut]) + machine.feed(data[cut:]) + machine.close()
        assert text.encode("utf-8", "surrogateescape") == data
    rng = random.Random(4)
    for _ in range(3000):
        data = bytes(rng.choice(b"ab\xc3\xa9\xe0\x80\xa0\xed\x9f\xf0\x90\xf4\x8f\xbf\xff\xc0\xe6\x95\xb0") for _ in range(rng.randrange(9)))
        cuts = sorted(rng.randrange(len(data) + 1) for _ in range(2))
        machine = bpe_transducer.Utf8Machine()
        text = machine.feed(data[: cuts[0]]) + machine.feed(data[cuts[0] : cuts[1]]) + machine.feed(data[cuts[1] :]) + machine.close()
        assert text == data.decode("utf-8", "surrogateescape")


def test_utf8_machine_waits_for_whole_characters():
    machine = bpe_transducer.Utf8Machine()
    assert [machine.feed(bytes([b])) for b in "aé😀".encode()] == ["a", "", "é", "", "", "", "😀"] and machine.close() == ""


def test_token_files(spark, docs, empty):
    got = sorted(token_files.token_file_report(docs, JSON).collect(), key=lambda r: r["start"])
    at, seen = 0, []
    for r, (i, text) in zip(got, texts_of(docs), strict=True):
        ids = [*library_ids(text), 0]
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (i, at, len(ids), crc(ids))
        at += len(ids)
        seen.append(i)
    assert seen == sorted(seen)
    assert token_files.token_file_report(empty, JSON).count() == 0
    path = shared.fresh_path(spark, "test-tokens")
    token_files.write_token_files(docs, path, JSON)
    found = token_files.read_token_files(spark, path, [7, 9]).collect()
    assert sorted(r["doc_id"] for r in found) == [7, 9]


def test_queries_recognise_added_tokens(spark, tmp_path):
    from tokenizers import Tokenizer

    import corpus_pipeline
    from slidemedian.llm import queries

    texts = ["ab <|endoftext|> cd", "<|endoftext|>", "plain words", "x<|endoftext|>\n<|endoftext|> y"]
    table = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    table.write.parquet(f"{tmp_path}/documents.parquet")
    library = Tokenizer.from_file(JSON)
    wanted = {i: [*library.encode(t, add_special_tokens=False).ids, 0] for i, t in enumerate(texts)}
    assert wanted[0] == [397, 220, 50256, 22927, 0]
    assert {r["doc_id"]: (r["n_tokens"], r["ids_crc32"]) for r in queries.op10_token_files(spark, str(tmp_path)).collect()} == {i: (len(w), crc(w)) for i, w in wanted.items()}
    for rows in (queries.op3_lexical_packing(spark, str(tmp_path)), corpus_pipeline.packed_sequences(spark, table, str(tmp_path))):
        for r in rows.collect():
            w = wanted[r["doc_id"]]
            assert (r["doc_tokens"], r["ids_crc32"]) == (len(w), crc(w[r["start"] : r["start"] + r["length"]]))


def check_pieces(docs, rows):
    by_document, by_sequence = {}, {}
    for r in rows:
        by_document.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append(r)
    tokens = padding = 0
    wanted = {}
    for i, text in texts_of(docs):
        wanted.setdefault(i, []).append([*library_ids(text), 0])
    for i, copies in wanted.items():
        ids, pieces = copies[0], sorted(by_document[i], key=lambda r: r["start"])
        assert sum(r["length"] for r in pieces) == len(ids) * len(copies)
        for r in pieces:
            assert r["doc_tokens"] == len(ids) and r["ids_crc32"] == crc(ids[r["start"] : r["start"] + r["length"]])
        if len(copies) == 1:
            at = 0
            for r in pieces:
                assert r["start"] == at
                at += r["length"]
    assert set(by_document) == set(wanted)
    for pieces in by_sequence.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r["offset"]):
            assert r["offset"] == at and r["length"] > 0
            at += r["length"]
        assert at <= 1024
        tokens += at
        padding += 0 if at & (at - 1) == 0 else 1024 - at
    return padding / tokens


def test_packing(docs, empty):
    assert check_pieces(docs, packing.pack_documents(docs, JSON).collect()) == 0
    assert packing.pack_documents(empty, JSON).count() == 0
    with_ids = packing.pack_documents(docs, JSON, with_ids=True).collect()
    assert all(crc(r["ids"]) == r["ids_crc32"] for r in with_ids)


def test_lexical_index_is_bm25():
    rng = np.random.default_rng(1)
    documents = [rng.integers(0, 30, n).astype(np.uint32) for n in (5, 9, 20, 3, 7)]
    index = packing.LexicalIndex(documents)
    mean = np.mean([len(d) for d in documents])

    def weight(t, d):
        tf, df = (d == t).sum(), sum((x == t).any() for x in documents)
        idf = np.log1p((len(documents) - df + 0.5) / (df + 0.5))
        return idf * tf * (packing.K1 + 1) / (tf + packing.K1 * (1 - packing.B + packing.B * len(d) / mean))

    shared_terms = [t for t in np.unique(documents[3]) if sum((d == t).any() for d in documents) > 1]
    expected = [sum(weight(t, d) for t in shared_terms) for d in documents]
    held = index.scores(3)
    for n, e in enumerate(expected):
        assert n == 3 or held[n] == pytest.approx(e, rel=1e-5)


def test_lexical_index_scores_all_shared_terms_by_counts_of_the_table():
    # Ten terms weigh more than those that documents 0 and 1 share.
    documents = [np.array([*range(10), *range(10), 20, 21], dtype=np.uint32), np.array([20, 21], dtype=np.uint32), np.arange(10, dtype=np.uint32)]
    assert packing.LexicalIndex(documents).scores(0)[1] > 0
    df = np.array([*[2] * 20, 900, 900])
    whole = packing.Statistics(1000, 8.0, df)
    wanted = 2 * np.log1p(100.5 / 900.5) * (packing.K1 + 1) / (1 + packing.K1 * (1 - packing.B + packing.B * 2 / 8))
    assert packing.LexicalIndex(documents, whole).scores(0)[1] == pytest.approx(wanted, rel=1e-5)


def test_terms_are_counted_and_projected_for_many_documents_at_once(monkeypatch):
    rng = np.random.default_rng(5)
    documents = [np.minimum(rng.zipf(1.3, size=n) - 1, 50_000).astype("<u2") for n in [*rng.integers(0, 400, size=300), 0, 1, 3000]]
    counts = packing.TermCounts()
    counts.count(np.concatenate(documents[:200]), np.array([len(d) for d in documents[:200]]))
    counts.count(np.zeros(0, dtype="<u2"), np.zeros(2, dtype=np.int64))
    counts.count(np.concatenate(documents[200:]), np.array([len(d) for d in documents[200:]]))
    df = np.bincount(np.concatenate([np.unique(d) for d in documents]))
    assert (counts.documents, counts.length) == (len(documents) + 2, sum(map(len, documents))) and counts.df.tolist() == df.tolist()
    whole = packing.Statistics(len(documents), float(np.mean([len(d) for d in documents])), df)
    monkeypatch.setattr(packing, "COMMON", 30)
    projector = packing.Projector(whole)
    wanted = np.zeros((len(documents), packing.AXES))
    for row, document in zip(wanted, documents, strict=True):
        terms, tf = np.unique(document, return_counts=True)
        weight = packing.bm25(np.sqrt(whole.idf(terms)), tf, len(document), whole.mean)
        if len(terms):
            row += weight @ projector.axes[terms] / np.linalg.norm(weight)
    for docs_each, tokens_each in ((1000, 1_000_000), (7, 500), (1, 1)):
        monkeypatch.setattr(packing, "PROJECTED_DOCS", docs_each)
        monkeypatch.setattr(packing, "PROJECTED_TOKENS", tokens_each)
        assert np.abs(projector.all(documents) - wanted).max() < 1e-5
    assert projector.all([]).shape == (0, packing.AXES)


def test_packing_finds_neighbours_across_the_whole_table(spark, monkeypatch):
    monkeypatch.setattr(packing, "SHARD_DOCS", 40)
    rng = random.Random(2)
    topics = [["".join(rng.choice("abcdefghij") for _ in range(6)) for _ in range(30)] for _ in range(40)]
    rows = [(i, " ".join(rng.choices(topics[i % 40], k=60))) for i in range(400)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    windows = {}
    for r in packing.pack_documents(table, JSON).collect():
        windows.setdefault(r["sequence_id"], []).append(r["doc_id"])
    pairs = [(a, b) for ids in windows.values() for a, b in zip(ids, ids[1:])]
    assert {i for ids in windows.values() for i in ids} == set(range(400))
    assert sum(a % 40 == b % 40 for a, b in pairs) > 0.6 * len(pairs)


def test_exact_dedup(docs, empty):
    groups = {}
    for i, text in texts_of(docs):
        groups.setdefault(text, []).append(i)
    rows = exact_dedup.exact_duplicates(docs).collect()
    assert len(rows) == docs.count()
    of = dict(texts_of(docs))
    for r in rows:
        members = groups[of[r["doc_id"]]]
        assert (r["keep_id"], r["group_size"], r["kept"]) == (max(members), len(members), r["doc_id"] == max(members))
        assert r["text_sha256"] == hashlib.sha256(of[r["doc_id"]].encode()).hexdigest()
    kept = exact_dedup.drop_exact(docs)
    assert kept.columns == docs.columns and sorted(r["doc_id"] for r in kept.collect()) == sorted(map(max, groups.values()))
    assert exact_dedup.exact_duplicates(empty).count() == 0


def test_directory_doubles_until_buckets_fit():
    histogram = {0: 500, 1: 90, 2: 20, 4095: 70}
    bucket = exact_dedup.split_directory(histogram, 100)
    load = {}
    for slot, n in histogram.items():
        load[bucket[slot]] = load.get(bucket[slot], 0) + n
    assert sorted(load.values()) == [70, 110, 500] or all(n <= 100 or n == 500 for n in load.values())
    assert bucket == sorted(bucket) and bucket[0] != bucket[1]
    assert set(exact_dedup.split_directory({}, 10)) == {0}


def test_directory_beyond_twelve_bits(spark):
    docs = spark.range(6000).select(F.col("id").alias("doc_id"), F.concat(F.lit("t"), F.col("id") % 5000).alias("text"))
    index = exact_dedup.build_index(docs, 1)
    assert index.bits > 12 and len(index.directory) == 1 << index.bits
    load = index.chains.groupBy("bucket").count().agg(F.max("count"), F.count("*")).first()
    assert load[0] <= 3 and load[1] > 3000
    found = index.find(docs.withColumn("hash", exact_dedup.text_hash(F.col("text")))).select("doc_id", "entry.*").collect()
    assert len(found) == 6000
    assert all((r["keep_id"], r["group_size"]) == ((r["doc_id"] % 5000 + 5000, 2) if r["doc_id"] % 5000 < 1000 else (r["doc_id"], 1)) for r in found)


def test_chains_compare_bytes_on_collisions(docs, monkeypatch):
    """Four hashes for all texts: the right row must come from each chain by its bytes."""
    plain = {r["doc_id"]: r for r in exact_dedup.exact_duplicates(docs).collect()}
    kept = sorted(map(str, exact_dedup.drop_exact(docs).collect()))
    monkeypatch.setattr(exact_dedup, "text_hash", lambda text: F.xxhash64(exact_dedup.whole(text)).bitwiseAND(F.lit(-4611686018427387904)))
    index = exact_dedup.build_index(docs)
    assert index.members is not None and index.chains.agg(F.max("members")).first()[0] > 5
    rows = exact_dedup.exact_duplicates(docs).collect()
    assert len(rows) == docs.count() and all(plain[r["doc_id"]] == r for r in rows)
    assert sorted(map(str, exact_dedup.drop_exact(docs).collect())) == kept


def test_exact_dedup_of_null_ids_and_clashes(spark):
    rows = [(None, "a", 1, "x"), (None, "a", 2, "y"), (3, None, 3, "z"), (4, "", 4, "z"), (4, "", 4, "z")]
    df = spark.createDataFrame(rows, "doc_id long, text string, hash int, bucket string")
    got = sorted((r["doc_id"] or 0, r["keep_id"] or 0, r["group_size"], r["kept"]) for r in exact_dedup.exact_duplicates(df).collect())
    assert got == [(0, 0, 2, True), (0, 0, 2, True), (3, 4, 3, False), (4, 4, 3, True), (4, 4, 3, True)]
    kept = exact_dedup.drop_exact(df)
    assert kept.columns == df.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 4]


def near_copies(rng, base, share):
    return [w if rng.random() > share else f"w{rng.randrange(10**6)}" for w in base]


@pytest.fixture(scope="module")
def near(spark):
    rng = random.Random(3)
    rows, n = [], 0
    for group in range(12):
        base = [f"v{rng.randrange(300)}" for _ in range(rng.choice([3, 40, 200]))]
        for _ in range(rng.choice([1, 2, 5, 30])):
            rows.append((n, " ".join(near_copies(rng, base, rng.choice([0, 0.01, 0.03, 0.05, 0.08])))))
            n += 1
    rows += [(n, None), (n + 1, ""), (n + 2, " \t"), (n + 3, "One"), (n + 4, "ONE"), (n + 5, rows[3][1])]
    return spark.createDataFrame(rows, "doc_id long, text string")


@pytest.mark.parametrize("words", [2, 5])
@pytest.mark.parametrize("chunk", [1024, 4])
def test_near_dedup_equals_brute_force(near, words, chunk, monkeypatch):
    monkeypatch.setattr(near_dedup, "CHUNK", chunk)
    sets = {}
    for r in near.collect():
        w = [x for x in re.split("[\x20\x09-\x0d]+", (r["text"] or "").translate({c: c + 32 for c in range(65, 91)})) if x]
        sets[r["doc_id"]] = {tuple(w[i : i + words]) for i in range(max(1, len(w) - words + 1))} if w else set()
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in sets:
        for j in sets:
            both = len(sets[i] & sets[j])
            if i < j and both and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    for r in near_dedup.near_duplicates(near, words).collect():
        assert (r["n_shingles"], r["component_id"], r["kept"]) == (len(sets[r["doc_id"]]), find(r["doc_id"]), find(r["doc_id"]) == r["doc_id"]), r


def test_near_dedup_edges(docs, empty):
    rows = near_dedup.near_duplicates(docs).collect()
    assert len(rows) == docs.count()
    kept = near_dedup.keep_one_each(docs)
    assert kept.columns == docs.columns and kept.select("doc_id").distinct().count() == sum(r["kept"] for r in {r["doc_id"]: r for r in rows}.values())
    assert near_dedup.near_duplicates(empty).count() == 0


def test_trees_reach_the_target():
    for n in (10, 10**5, 10**10):
        depth, trees = near_dedup.depth_and_trees(n)
        assert near_dedup.missed(depth, trees, 0.8) <= near_dedup.MISS + near_dedup.missed(depth, 10**6, 0.8) < 2e-4


def test_recall_of_planted_pairs(spark):
    """Pairs at 0.80 to 0.82, among documents that all share a passage."""
    rng, rows = random.Random(6), []
    passage = [f"p{i}" for i in range(12)]
    for i in range(1500):
        words = [f"w{i}x{j}" for j in range(88)]
        rows.append((2 * i, " ".join(passage + words)))
        rows.append((2 * i + 1, " ".join(passage + words[:80] + [f"v{i}x{j}" for j in range(rng.choice([8, 9]))])))
    got = near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 1)
    found = {r["doc_id"]: r["component_id"] for r in got.collect()}
    wanted = {a: a for a in range(0, 3000, 2)}
    for i in range(1500):
        a, b = (set(rows[2 * i + k][1].split()) for k in (0, 1))
        wanted[2 * i + 1] = 2 * i if 100 * len(a & b) >= 80 * len(a | b) else 2 * i + 1
    links = [b for b, a in wanted.items() if a != b]
    assert len(links) > 500 and all(found[i] == wanted[i] for i in set(wanted) - set(links))
    assert np.mean([found[b] == wanted[b] for b in links]) >= 0.999


@pytest.mark.parametrize("limit", [4, 40, 1024])
def test_large_nodes_branch(spark, limit):
    """Nodes far beyond the limit: the paths of links survive, and rounds end."""
    rng = np.random.default_rng(9)
    base = rng.integers(0, 256, (40, 64))
    tails = np.where(rng.random((400, 64)) < 0.15, rng.integers(0, 256, (400, 64)), np.repeat(base, 10, axis=0)).astype(np.uint8)
    trees = 3
    rows = [(i, np.full(trees, 7, dtype=np.int64).tobytes() + tail.tobytes()) for i, tail in enumerate(tails)]
    links = near_dedup.candidate_links(spark.createDataFrame(rows, "doc_id long, trace binary").repartition(1), trees, limit)
    got = {r["v"]: r["component"] for r in graph.components(links).collect()}
    assert [got[i] for i in range(400)] == [i // 10 * 10 for i in range(400)]


def test_rows_that_repeat_an_id_with_other_texts(spark):
    rows = [(1, "a b c d e f g h"), (1, "k l m n o p q r"), (2, "k l m n o p q r"), (3, "a b c d e f g h"), (4, None), (None, "a b c d e f g h")]
    got = near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 1)
    assert sorted((r["doc_id"] or 0, r["component_id"] or 0) for r in got.collect()) == [(0, 0), (1, 1), (1, 1), (2, 1), (3, 1), (4, 4)]


def test_components(spark):
    edges = [(1, 2), (2, 3), (9, 8), (8, 7), (7, 6), (6, 9), (20, 21), (5, 5)] + [(100 + i, 101 + i) for i in range(30)]
    got = {r["v"]: r["component"] for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got[3] == 1 and got[9] == 6 and got[21] == 20 and got[130] == 100 and len(got) == 3 + 4 + 2 + 31


def test_embeddings_equal_brute_force(spark):
    rng = np.random.default_rng(4)
    base = rng.normal(size=(120, 16))
    rows = [base[i % 120] + (0 if i < 150 else rng.normal(size=16) * rng.choice([0.02, 0.15, 0.3])) for i in range(500)]
    data = [(i, [float(np.float32(x)) for x in v]) for i, v in enumerate(rows)]
    bad = [(1000, None), (1001, [0.0] * 16), (1002, [float("nan")] * 16), (1003, [None] + [1.0] * 15), (1004, [1.0]), (1005, []), (1006, [float("inf")] * 16)]
    # Vectors of other lengths are linked among themselves; one of them has its length alone.
    short = [(1100, [1.0, 0.0, 0.1]), (1101, [2.0, 0.0, 0.21]), (1102, [0.0, 1.0, 0.0]), (1103, [1e30, 0.0, 1e29]), (1200, [1.0, 2.0])]
    links = {1100: (2, 1100), 1101: (2, 1100), 1102: (0, 1102), 1103: (2, 1100), 1200: (0, 1200)}
    df = spark.createDataFrame([(*r, "clash", 1) for r in data + bad + short], "vec_id long, embedding array<float>, n_links string, kept int")
    x = np.array([v for _, v in data])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    close = (x @ x.T >= 0.9) & ~np.eye(500, dtype=bool)
    parent = list(range(500))
    for i, j in zip(*np.nonzero(close), strict=True):
        a, b = parent[i], parent[j]
        if a != b:
            parent = [min(a, b) if p in (a, b) else p for p in parent]
    got = {r["vec_id"]: r for r in embedding_dedup.near_duplicate_vectors(df).collect()}
    assert [got[i]["n_links"] for i in range(500)] == close.sum(axis=1).tolist()
    assert [got[i]["component_id"] for i in range(500)] == parent
    assert {i: (got[i]["n_links"], got[i]["component_id"]) for i, _ in short} == links
    for i, _ in bad:
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (0, i, True)
    assert embedding_dedup.near_duplicate_vectors(df.limit(0)).count() == 0


def test_multi_index_visits_the_nearest_cells():
    rng = np.random.default_rng(5)
    sample = rng.normal(size=(300, 8))
    sample /= np.linalg.norm(sample, axis=1, keepdims=True)
    index = embedding_dedup.MultiIndex(sample, 9)
    first, second = index.ranked(sample)
    homes, blocks = index.opened(sample)
    assert homes.tolist() == [row[0] // 9 // embedding_dedup.WIDE for row in index.traverse(sample)]
    for row, f, s, opened in zip(index.traverse(sample), first, second, blocks, strict=True):
        total = (f[:, None] + s[None]).ravel()
        assert total[row].tolist() == np.sort(total)[: len(row)].tolist()
        assert row[0] == total.argmin() and total[row[-1]] <= total.min() + index.gap
        assert len(row) == 81 or np.sort(total)[len(row)] > total.min() + index.gap
        assert np.flatnonzero(opened).tolist() == sorted({c // 9 // embedding_dedup.WIDE for c in row})


@pytest.mark.parametrize("chunk", [7, 8192])
def test_blocks_in_chunks_count_links_once(spark, monkeypatch, chunk):
    """A dense group over many cells, copies, and ids that repeat."""
    monkeypatch.setattr(embedding_dedup, "CHUNK", chunk)
    monkeypatch.setattr(embedding_dedup, "CELL", 4)
    rng = np.random.default_rng(12)
    x = np.concatenate([rng.normal(size=8) + rng.normal(size=(150, 8)) * 0.3, rng.normal(size=(100, 8))])
    x = np.concatenate([x, x[:40], x[:5]])
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(3, x[3].tolist()), (None, x[0].tolist())]
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    close = unit @ unit.T >= 0.9
    got = embedding_dedup.near_duplicate_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert len(got) == len(rows) and sum(r["vec_id"] is None for r in got) == 1
    once = {r["vec_id"]: r["n_links"] for r in got}
    near_three = np.flatnonzero(close[3])
    wanted = close.sum(axis=1) - 1 + np.isin(np.arange(len(x)), near_three)  # vec 3 comes twice
    assert [once[i] for i in range(len(x))] == wanted.tolist()


def test_language_id(spark, docs, empty):
    rng = random.Random(6)
    words = {"en": ["the", "house", "with", "nothing", "river"], "de": ["der", "schön", "nicht", "straße", "über"], "es": ["el", "año", "corazón", "nunca", "río"]}
    rows = [(i, " ".join(rng.choice(words[lang]) for _ in range(12)), lang) for i in range(150) for lang in (rng.choice(list(words)),)]
    rows += [(900, None, "en"), (901, "123 !!", "de"), (902, "", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r["doc_id"]: r for r in language_id.predict(df, PIECES).collect()}
    assert all(got[i]["lang_pred"] == lang for i, _, lang in rows[:-3])
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0 for i in (900, 901, 902))
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i in got)
    assert language_id.keep_known(df, PIECES).count() == 150
    assert language_id.predict(empty, PIECES).count() == 0


def test_forward_pass_sums_all_segmentations():
    pieces = ["a", "b", "ab", "ba", "aba"]
    segmenter = language_id.Segmenter(pieces)
    chance = np.array([[0.3], [0.2], [0.15], [0.25], [0.1], [0.0]])

    def total(word):
        return 1.0 if not word else sum(chance[i, 0] * total(word[len(p) :]) for i, p in enumerate(pieces) if word.startswith(p))

    for word in ("abab", "baba", "aaaa", "abaab"):
        codes, width = language_id._codes([word]), len(word)
        lattice = segmenter.lattice(codes)
        assert segmenter.prefixes(chance, lattice, width)[0, width, 0] == pytest.approx(total(word))
        assert segmenter.suffixes(chance, lattice, width)[0, 0, 0] == pytest.approx(total(word))
        assert segmenter.log_mass(chance, codes)[0, 0] == pytest.approx(np.log(total(word)))
    # Pieces across every border of a run, against exact arithmetic.
    from fractions import Fraction

    word, exact = "".join(random.Random(1).choice("ab") for _ in range(200)), [Fraction(1)]
    for end in range(1, len(word) + 1):
        exact.append(sum(Fraction(float(chance[i, 0])) * exact[end - len(p)] for i, p in enumerate(pieces) if word[:end].endswith(p)))
    wanted = math.log(exact[-1].numerator) - math.log(exact[-1].denominator)
    assert segmenter.log_mass(chance, language_id._codes([word]))[0, 0] == pytest.approx(wanted, rel=1e-9)


def test_language_needs_a_familiar_text(spark):
    rng = random.Random(8)
    words = {"en": ["the", "house", "with", "nothing", "river", "stone"], "de": ["der", "schön", "nicht", "straße", "über", "stein"]}
    text = lambda own, n: " ".join(rng.choice(own) for _ in range(n))
    rows = [(i, text(words[lang], 120), lang) for i in range(200) for lang in (rng.choice(list(words)),)]
    strangers = [(900, text(["привет", "дома", "ничего", "река"], 200), "en"), (901, text(["qzxkv", "wvvqj", "zzkqx"], 200), "de"), (902, "数学" * 300, "en")]
    plain = [(903, "the", "en"), (904, text(words["de"], 3000), "de"), (905, "THE HOUSE. " * 50, "en"), (906, "Donaudampfschiffahrt" * 400, "de")]
    df = spark.createDataFrame(rows + plain, "doc_id long, text string, lang string")
    assert language_id.keep_known(df.unionByName(spark.createDataFrame([(i, t, None) for i, t, _ in strangers], df.schema)), PIECES).where("doc_id < 906").count() == 203


def test_language_scorer_forgets_and_repeats(spark):
    model = language_id.estimate([("der schöne stein", "de"), ("the house of stone", "en")], language_id.public_pieces(PIECES))
    texts = pa.array([f"haus{i} stone der house x " * 3 for i in "abcdefghij"], pa.string())
    small, large = (language_id.WordScorer(model, limit) for limit in (6, 1000))
    for part in (texts, texts.slice(3), texts):
        one, other = (language_id.judge(s, part) for s in (small, large))
        assert one[0] == other[0] and np.allclose(one[1], other[1])


def test_block_max_search_is_exact():
    rng = np.random.default_rng(7)
    vectors = []
    for _ in range(300):
        terms = rng.choice(12, rng.integers(1, 4), replace=False)
        w = rng.random(len(terms)) + 0.1
        vectors.append((np.sort(terms), w / np.linalg.norm(w)))
    vectors += vectors[:20] + [(np.zeros(0, dtype=np.int64), np.zeros(0))]  # ties, and an example without terms
    index = toxicity.BlockMaxIndex(vectors, 12, block=16)
    table = np.zeros((len(vectors), 12))
    for row, (terms, w) in zip(table, vectors, strict=True):
        row[terms] = w
    for i, query in enumerate(vectors[:60]):
        scores = table @ table[i]
        for skip in (-1, i):
            wanted = sorted((-round(x, 12), j) for j, x in enumerate(scores) if x > 1e-9 and j != skip)[:10]
            assert [j for j, _ in index.search(query, 10, skip)] == [j for _, j in wanted]
            assert [x for _, x in index.search(query, 10, skip)] == pytest.approx([-x for x, _ in wanted])
    assert toxicity.BlockMaxIndex([], 3).search((np.array([1]), np.array([1.0])), 5) == []


def held_some(texts):
    return [i for i in sorted(texts) if i < 9000 and zlib.crc32(str(i).encode()) % 3 == 1][:60]


def test_toxicity(spark, docs, empty):
    rng = random.Random(8)
    plain, foul = [f"w{i}" + "x" * (i % 4) for i in range(80)], ["idiot", "scum", "moron"]
    rows = []
    for i in range(600):
        words = [rng.choice(plain) for _ in range(30)] + ([rng.choice(foul) for _ in range(2)] if i % 5 == 0 else [])
        rows.append((i, " ".join(rng.sample(words, len(words)))))
    rows += [(9000, None), (9001, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1, int(i % 5 == 0)) for i in range(600)] + [(7777, 1, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")
    letters = df.withColumn("text", F.translate("text", "0123456789", "abcdefghij"))
    got = {r["doc_id"]: r for r in toxicity.score_documents(letters, labels).collect()}
    held = [i for i in range(600) if zlib.crc32(str(i).encode()) % 3 == 1]
    assert all(got[i]["held_out"] for i in held)
    assert sum(got[i]["predicted"] == int(i % 5 == 0) for i in held) >= 0.97 * len(held)
    assert all(0 <= r["score"] <= 1 for r in got.values()) and got[9000]["predicted"] == 0
    # Brute force: dense cosines over all words of all examples, and the same vote and curve.
    texts = {r["doc_id"]: r["text"] or "" for r in letters.collect()}
    train = [i for i in range(600) if zlib.crc32(str(i).encode()) % 3 != 1]
    count = lambda t: Counter(re.findall(r"[^\W\d_]+", t.lower()))
    held, toxic = Counter(), Counter()
    for i in train:
        held.update(count(texts[i]).keys())
        toxic.update(count(texts[i]).keys() if i % 5 == 0 else ())
    names = sorted(t for t in held if held[t] > 1)
    weights = toxicity.term_weights(np.array([held[t] for t in names], float), np.array([toxic[t] for t in names], float), len(train), sum(i % 5 == 0 for i in train))

    def dense(text):
        own = count(text)
        v = np.array([(1 + math.log(own[t])) * w if own[t] else 0.0 for t, w in zip(names, weights, strict=True)])
        return v / np.linalg.norm(v) if v.any() else v

    examples, base = np.stack([dense(texts[i]) for i in train]), sum(i % 5 == 0 for i in train) / len(train)

    def vote(text, skip=-1):
        cosines = examples @ dense(text)
        best = sorted((j for j in range(len(train)) if cosines[j] > 1e-9 and j != skip), key=lambda j: (-round(cosines[j], 12), j))[: toxicity.NEAREST]
        w = cosines[best] ** 2
        return (sum(x * (train[j] % 5 == 0) for x, j in zip(w, best, strict=True)) + toxicity.PRIOR_VOTES * base) / (w.sum() + toxicity.PRIOR_VOTES), [train[j] for j in best]

    curve = toxicity.monotone_fit(np.array([vote(texts[i], n)[0] for n, i in enumerate(train)]), np.array([float(i % 5 == 0) for i in train]))
    for i in [*held_some(texts), 3, 5]:
        value, evidence = vote(texts[i])
        assert got[i]["evidence"] == evidence
        assert got[i]["score"] == pytest.approx(float(np.interp(value, *curve)))
    assert {train.index(e) >= 0 and e % 5 == 0 for r in got.values() for e in r["evidence"]} == {True, False}
    assert got[9000]["score"] == got[9001]["score"] == pytest.approx(base)
    none = toxicity.score_documents(docs, labels.limit(0)).collect()
    assert len(none) == docs.count() and all(r["predicted"] == 0 for r in none)
    assert toxicity.score_documents(empty, labels).count() == 0


def test_quality(spark, docs, empty):
    rng = random.Random(9)
    good, junk = [f"w{i}" for i in range(200)], [f"j{i}!!" for i in range(50)]
    rows = [(i, " ".join(rng.choice(junk if i % 6 == 0 else good) for _ in range(40))) for i in range(500)] + [(9000, None), (9001, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("selected", F.lit("clash"))
    labels = spark.createDataFrame([(i, int(i % 6 != 0), 0) for i in range(0, 500, 2)] + [(i, int(i % 6 != 0), 0) for i in range(3, 500, 8)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality.resample(df, labels).collect()}
    assert not any(got[i]["selected"] for i in range(0, 500, 6))
    # The cut-off is a quantile of unseen good documents and the draw is random at the border.
    assert sum(got[i]["selected"] for i in range(500)) >= 0.97 * sum(i % 6 != 0 for i in range(500))
    # Brute force: both models gram by gram.
    def grams(text):
        tokens = [xxhash.xxh64_intdigest(t) for w in (text or "").lower().split() for t in re.findall(r"[^\W_]+|(?:[^\w\s]|_)+", w)]
        pairs = [((a * 0x9E3779B97F4A7C15 + b) * 0xC2B2AE3D27D4EB4F) % 2**64 for a, b in zip(tokens, tokens[1:])]
        return [(g >> 48) % quality.BUCKETS for g in tokens + pairs]

    labelled = {r["doc_id"]: r["quality"] for r in labels.collect()}
    raw, target = Counter(), Counter()
    for i, text in rows:
        raw.update(grams(text))
        if labelled.get(i) and zlib.crc32(str(i).encode()) % 3 != 1:
            target.update(grams(text))
    all_raw, all_target = sum(raw.values()), sum(target.values())
    ratio = {g: (target[g] + quality.STRENGTH) / (n / all_raw * all_target + quality.STRENGTH) for g, n in raw.items()}
    total = sum(raw[g] / all_raw * r for g, r in ratio.items())
    for i, text in rows:
        assert got[i]["log_weight"] == pytest.approx(sum(math.log(ratio[g] / total) for g in grams(text)), abs=1e-9)
    least = min(r["gumbel_key"] for r in got.values() if r["selected"])
    assert all(r["selected"] == (r["gumbel_key"] >= least) for r in got.values())
    kept = quality.keep_drawn(df, labels)
    assert kept.columns == df.columns and kept.where("doc_id >= 9000").count() == 2
    assert quality.keep_drawn(docs, labels.limit(0)).count() == docs.count()
    assert quality.resample(empty, labels).count() == 0


def test_kth_largest(spark):
    rng = random.Random(10)
    values = [rng.gauss(0, 1) for _ in range(500)] + [0.25] * 20 + [1e9]
    df = spark.createDataFrame([(v,) for v in values], "x double")
    for k in (1, 2, 100, 300, 521):
        assert quality.kth_largest(df, "x", k) == sorted(values)[-k]
    assert quality.kth_largest(df, "x", 0) is None


def test_urls(spark):
    urls = {
        "https://WWW.Example.ORG/es/1?q=a#b": ("www.example.org", "/es/1", "example.org/es/", "block"),
        "http://x.org/en": ("x.org", "/en", "org/", "allow"),
        "http://example.org/en/12": ("example.org", "/en/12", "example.org/en/1", "block"),
        "http://notexample.org/es/1": ("notexample.org", "/es/1", "org/", "allow"),
        "http://org": ("org", "", None, "allow"),
        "http://a.com/fr/": ("a.com", "/fr/", "com/fr/", "allow"),
        "x://y.com/de/?x://z": ("y.com", "/de/", "com/de/", "block"),
        "no scheme/here": ("", "", None, "allow"),
        None: ("", "", None, "allow"),
        "http://h?x": ("h", "", None, "allow"),
    }
    rows = [(i, u, None) for i, u in enumerate(urls)]
    got = {r["page_id"]: r for r in url_filter.judge_urls(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i, (host, path, rule, verdict) in enumerate(urls.values()):
        assert (got[i]["host"], got[i]["path"], got[i]["rule"], got[i]["verdict"]) == (host, path, rule, verdict)
    assert url_filter.judge_urls(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_propagation_equals_power_iteration(spark):
    edges = [("a", "b", 2.0), ("b", "c", 1.0), ("c", "a", 1.0), ("b", "d", 3.0), ("e", "c", 1.0)]
    seeds = [("a", 3, 0), ("e", 1, 0), ("d", 0, 5)]
    got = {r["host"]: (r["trust"], r["distrust"]) for r in url_filter.propagate(spark.createDataFrame(edges, "source string, target string, weight double"), spark.createDataFrame(seeds, "host string, trust long, distrust long"), steps=6).collect()}
    hosts = "abcde"
    for flow, at in ((0, 1), (1, 2)):
        step = np.zeros((5, 5))
        for s, t, w in edges:
            i, j = (hosts.index(s), hosts.index(t)) if flow == 0 else (hosts.index(t), hosts.index(s))
            step[i, j] += w
        out = step.sum(axis=1, keepdims=True)
        step = np.divide(step, out, out=np.zeros_like(step), where=out > 0)
        seed = np.array([dict((s[0], s[at]) for s in seeds).get(h, 0) for h in hosts], dtype=float)
        seed /= seed.sum()
        mass = seed
        for _ in range(6):
            moved = 0.85 * mass @ step
            mass = moved + seed * (1 - moved.sum())
        for i, h in enumerate(hosts):
            assert got.get(h, (0, 0))[flow] == pytest.approx(mass[i], abs=1e-12)


@pytest.mark.parametrize("ways", [0, 10**6])
def test_propagation_converges_along_a_chain(spark, monkeypatch, ways):
    monkeypatch.setattr(url_filter, "DRIVER_WAYS", ways)
    monkeypatch.setattr(url_filter, "TOLERANCE", 1e-12 if ways else 1e-2)
    # Distrust comes back along the chain from its end, 20 links away; trust from its start.
    n = 21
    edges = [(f"h{i:02}", f"h{i + 1:02}", 1.0) for i in range(n - 1)]
    seeds = [("h20", 0, 1), ("h00", 1, 0)]
    got = {r["host"]: (r["trust"], r["distrust"]) for r in url_filter.propagate(spark.createDataFrame(edges, "source string, target string, weight double"), spark.createDataFrame(seeds, "host string, trust long, distrust long")).collect()}
    step = np.eye(n, k=1)
    step[-1, 0] = 0
    # Solved: mass = 0.85 mass step + seed (1 - what moved).
    seed = np.zeros(n)
    seed[0] = 1
    flow = np.linalg.solve(np.eye(n) - 0.85 * step.T, seed)
    flow /= flow.sum()
    for i in range(n):
        wanted = flow[i], flow[n - 1 - i]
        assert got[f"h{i:02}"] == pytest.approx(wanted, abs=1e-10 if ways else 2e-2)
        assert ways == 0 or (got[f"h{i:02}"][1] > got[f"h{i:02}"][0]) == (wanted[1] > wanted[0])
        assert min(got[f"h{i:02}"]) > 0


def test_links_become_edges(spark):
    html = '<a href="http://B.com/x">b</a> <a href=//c.org>c</a> <a href="/own">o</a> <img src=\'https://b.com/i.png\'>'
    pages = spark.createDataFrame([("a.net", html), ("a.net", None)], "host string, html string")
    edges = {(r["source"], r["target"]): r["weight"] for r in url_filter.host_edges(pages, pages.select("host").distinct()).collect()}
    assert edges == {("a.net", "b.com"): 2.0, ("a.net", "c.org"): 1.0}


def test_lookup_under_skew(spark, monkeypatch):
    rows = spark.range(3000).select(F.when(F.col("id") < 2000, 7).when(F.col("id") < 2010, None).otherwise(F.col("id")).alias("k"), "id")
    entries = rows.where("k IS NOT NULL").groupBy("k").agg(F.count("*").alias("n"))
    got = shared.look_up(rows, entries, ["k"], "n", "found")
    assert got.count() == 3000 and got.where("found.n = 2000").count() == 2000 and got.where("found IS NULL").count() == 10
    # Rows that the broadcast serves, and rows without a key, spread over the partitions of the join.
    monkeypatch.setattr(shared, "FREQUENT", 10)
    options = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.shuffle.partitions": "16"}
    held = {key: spark.conf.get(key) for key in options}
    for key, value in options.items():
        spark.conf.set(key, value)
    try:
        for skewed in (rows, rows.withColumn("k", F.when(F.col("id") < 2000, None).otherwise(F.col("k")))):
            known = skewed.where("k IS NOT NULL").groupBy("k").agg(F.count("*").alias("n"))
            found = shared.look_up(skewed, known, ["k"], "n", "found").select(F.spark_partition_id().alias("p"), "k", "found")
            assert found.groupBy("p").agg(F.count("*").alias("n"), F.count("found").alias("m")).agg(F.max("n"), F.sum("m")).first()[0] < 400
            assert found.where("k IS NOT NULL AND found IS NULL").count() == 0
    finally:
        for key, value in held.items():
            spark.conf.set(key, value)
