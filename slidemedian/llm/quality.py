"""Quality by importance resampling.

Tokens (runs of letters and digits, and runs of other characters) and pairs of
neighbouring tokens are hashed into buckets. Two generative models give each
bucket a probability: the raw model by its share in all documents, the target
model by its counts in documents that labels call good. The target model has
the raw one as its prior: a bucket that should have come up ``E`` times in the
target text, and came up ``c`` times, is ``(c + s) / (E + s)`` times as likely
as in raw text, so buckets that the target text is too small to show are judged
neither way. A document's log-weight is the sum of log-ratios of the two models
over its n-grams, and documents are drawn without replacement in proportion to
their weights: the k largest of log-weight plus Gumbel noise stay.

k is the number of documents whose log-weight reaches a cut-off, the
``SPARED`` quantile of labelled good documents that the model has not seen, but
never more than 0: text without evidence against it is not rejected.

Defined cases: a text that is null or has no token has log-weight 0; rows that
tie at the k-th key all stay; labels that are null or of no document are not
used; without labels all weights are 0 and everything stays; repeated rows are
drawn alike; an empty table gives no rows; other columns are untouched.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .encoding import gathered, slices
from .shared import bucket_of, settle, stateless_worker

#: Hash buckets; bound of the labelled sample; strength ``s`` of the prior, in expected counts.
BUCKETS, SAMPLE_TEXTS, STRENGTH = 1 << 16, 30_000, 50.0
#: Share of good documents that the cut-off may cost.
SPARED = 0.001
#: Bins of each pass of the search for the k-th key; passes.
BINS, PASSES = 4096, 4

_TOKENS = re.compile(r"[^\W_]+|(?:[^\w\s]|_)+").findall


def gram_buckets(texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For parts of ``texts``: the buckets of all tokens and all pairs of neighbours, and the place of each one's text in the part."""
    for part in slices(texts):
        lists = pc.utf8_split_whitespace(pc.utf8_lower(pc.fill_null(part, "")))
        words = lists.flatten().dictionary_encode()
        tokens = [_TOKENS(w) for w in words.dictionary.to_pylist()]
        sizes = np.fromiter(map(len, tokens), dtype=np.int64, count=len(tokens))
        pool = np.fromiter((xxhash.xxh64_intdigest(t.encode("utf-8", "surrogatepass")) for own in tokens for t in own), dtype=np.uint64, count=int(sizes.sum()))
        single, length = gathered(pool, sizes, np.asarray(words.indices))
        owner = np.repeat(np.repeat(np.arange(len(part)), pc.list_value_length(lists).to_numpy(zero_copy_only=False)), length)
        together = owner[1:] == owner[:-1]
        with np.errstate(over="ignore"):
            double = ((single[:-1] * np.uint64(0x9E3779B97F4A7C15) + single[1:]) * np.uint64(0xC2B2AE3D27D4EB4F))[together]
        yield (np.concatenate([single, double]) >> np.uint64(48)).astype(np.int64) % BUCKETS, np.concatenate([owner, owner[1:][together]])


def target_ratios(raw: np.ndarray, target: np.ndarray, strength: float = STRENGTH) -> np.ndarray:
    """Log-ratio of the target and the raw model for each bucket, from counts."""
    if not target.sum():
        return np.zeros(len(raw))
    share = raw / raw.sum()
    likelier = (target + strength) / (share * target.sum() + strength)
    # The target model's probabilities add up to 1.
    return np.log(likelier) - np.log((share * likelier).sum())


def labelled_ids(labels: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Sorted ids and their quality, at most about ``SAMPLE_TEXTS``, drawn by a hash of the id."""
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where(F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1))
    share = min(1.0, SAMPLE_TEXTS / max(1, usable.count()))
    draw = F.pmod(F.xxhash64(F.lit("quality sample"), "doc_id"), F.lit(1_000_000))
    drawn = usable.where(draw < int(share * 1_000_000)).distinct().orderBy(draw, "doc_id", "quality").limit(2 * SAMPLE_TEXTS)
    rows = sorted({(r["doc_id"], r["quality"]) for r in drawn.collect()})
    return np.array([r[0] for r in rows], dtype=np.int64), np.array([r[1] for r in rows], dtype=np.int64)


def _is_good(ids: np.ndarray, doc_ids: pa.Array) -> np.ndarray:
    """Which documents are among ``ids``, sorted."""
    if not len(ids):
        return np.zeros(len(doc_ids), dtype=bool)
    wanted = pc.fill_null(doc_ids, 0).to_numpy()
    place = np.minimum(np.searchsorted(ids, wanted), len(ids) - 1)
    return (ids[place] == wanted) & np.asarray(pc.is_valid(doc_ids))


def log_ratios(docs: DataFrame, good: np.ndarray, folds: int, held_out: int) -> np.ndarray:
    """Log-ratio of target and raw model for each bucket; raw counts cover all documents, target counts those of ``good`` outside the held-out fold."""
    shared = docs.sparkSession.sparkContext.broadcast(good)

    def count(batches):
        stateless_worker("quality")
        raw, target = (np.zeros(BUCKETS, dtype=np.int64) for _ in range(2))
        for batch in batches:
            learn, low = _is_good(shared.value, batch.column(0)) & batch.column(1).to_numpy(zero_copy_only=False), 0
            for part, (grams, owner) in zip(slices(batch.column(2)), gram_buckets(batch.column(2)), strict=True):
                raw += np.bincount(grams, minlength=BUCKETS)
                target += np.bincount(grams[learn[low + owner]], minlength=BUCKETS)
                low += len(part)
        used = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (used, raw[used], target[used])], names=["bucket", "raw", "target"])

    fold = F.coalesce(bucket_of("doc_id", folds) != held_out, F.lit(False))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), fold.alias("learn"), "text").mapInArrow(count, "bucket long, raw long, target long")
    raw, target = (np.zeros(BUCKETS) for _ in range(2))
    for r in rows.groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect():
        raw[r["bucket"]], target[r["bucket"]] = r["raw"], r["target"]
    return target_ratios(raw, target)


def with_log_weight(docs: DataFrame, ratios: np.ndarray, name: str) -> DataFrame:
    """``docs`` and each row's log-weight in column ``name``; the other columns pass through."""
    shared, at = docs.sparkSession.sparkContext.broadcast(ratios), docs.columns.index("text")

    def weigh(batches):
        stateless_worker("quality")
        for batch in batches:
            weights, low = np.zeros(batch.num_rows), 0
            for part, (grams, owner) in zip(slices(batch.column(at)), gram_buckets(batch.column(at)), strict=True):
                weights[low : low + len(part)] = np.bincount(owner, shared.value[grams], len(part))
                low += len(part)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(weights, pa.float64())], names=[*batch.schema.names, name])

    return docs.mapInArrow(weigh, docs.select("*", F.lit(0.0).alias(name)).schema)


def gumbel(seed: int = 7):
    """Gumbel noise that is a function of the document's id."""
    uniform = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("doc_id").cast("long")), 12) + F.lit(0.5)) / F.lit(float(1 << 52))
    return -F.log(-F.log(uniform))


def kth_largest(rows: DataFrame, key: str, k: int) -> float | None:
    """The k-th largest value, by passes of histograms of bounded size."""
    if k <= 0:
        return None
    low, high = rows.agg(F.min(key), F.max(key)).first()
    if low is None:
        return None
    above = 0
    for _ in range(PASSES):
        width = (high - low) / BINS
        if width <= 0 or low + width <= low:
            break
        inside = rows.where((F.col(key) >= low) & (F.col(key) <= high))
        bins = {r["bin"]: r for r in inside.groupBy(F.least(F.floor((F.col(key) - low) / width), F.lit(BINS - 1)).alias("bin")).agg(F.count("*").alias("n"), F.min(key).alias("low"), F.max(key).alias("high")).collect()}
        for b in sorted(bins, reverse=True):
            if above + bins[b]["n"] >= k:
                low, high = bins[b]["low"], bins[b]["high"]
                break
            above += bins[b]["n"]
        if low == high:
            break
    return low


def drawn(docs: DataFrame, labels: DataFrame, columns: list[str], folds: int = 3, held_out: int = 1) -> DataFrame:
    """``columns`` of ``docs`` with __log_weight, __key and __selected.

    The scored rows are written once: the search for the k-th key reads only
    their two numbers.
    """
    ids, quality = labelled_ids(labels)
    ratios = log_ratios(docs, ids[quality == 1], folds, held_out)
    scored = settle(with_log_weight(docs, ratios, "__log_weight").select(*[F.col(f"`{c}`") for c in columns], "__log_weight"), "quality")
    keyed = scored.withColumn("__key", F.col("__log_weight") + gumbel())
    fold = bucket_of("doc_id", folds) == held_out
    good = docs.sparkSession.createDataFrame([(int(i),) for i, q in zip(ids, quality, strict=True) if q] or [(-1,)], "doc_id long")
    unseen = keyed.where(fold).select(F.col("doc_id").cast("long").alias("doc_id"), "__log_weight").join(F.broadcast(good), "doc_id")
    cut = unseen.agg(F.percentile_approx("__log_weight", SPARED, 10_000)).first()[0]
    k = keyed.where(F.col("__log_weight") >= min(cut, 0.0)).count() if cut is not None else keyed.count()
    threshold = kth_largest(keyed, "__key", k)
    return keyed.withColumn("__selected", F.lit(False) if threshold is None else F.col("__key") >= threshold)


def resample(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, log_weight, gumbel_key, selected) of every row."""
    rows = drawn(docs.select("doc_id", "text"), labels, ["doc_id"])
    return rows.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("__log_weight").alias("log_weight"), F.col("__key").alias("gumbel_key"), F.col("__selected").alias("selected"))


def keep_drawn(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are drawn, all columns as they are."""
    return drawn(docs, labels, docs.columns).where("__selected").select(*[F.col(f"`{c}`") for c in docs.columns])
