"""Toxicity by the nearest labelled examples.

Labelled texts are TF-IDF vectors over the words of all of them; words that
tell the labels apart, in either direction, keep their full weight, and all
others a share of it, so that a long harmless text does not drown what matters.
All examples, toxic or not, lie in blocks of an inverted index. Each block
knows the largest weight of each term, so a search scores the most promising
blocks first and stops when no other block can hold a nearer example. The
cosine is exact. The nearest examples vote, weighted by closeness; a monotone
curve, fitted on the examples themselves with each left out of its own search,
turns votes into calibrated scores. The examples found are the evidence.

Terms are maximal runs of letters, lower-cased, that at least ``LEAST_TEXTS``
examples hold. A term's weight grows with its association with the label
(log-likelihood ratio), up to what the best of as many unrelated terms would
reach by chance.

Defined cases: a text that is null, empty or without any term gets the share of
toxic texts among the examples; labels that are null or belong to no document
are not used, contradicting labels both count; examples at the same distance
go by the order of their ids; without labelled texts every score is 0; repeated
rows are scored alike; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import re
import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .encoding import gathered, slices
from .shared import bucket_of, worker_state

#: Bound of the labelled sample in texts, and the longest text that is drawn, in characters.
SAMPLE_TEXTS, SAMPLE_CHARS = 2_400, 200_000
#: Examples that must hold a term; examples that vote; examples in a block; blocks scored before the first look at the bounds.
LEAST_TEXTS, NEAREST, BLOCK, FIRST_BLOCKS = 2, 15, 64, 4
#: Share of the weight that a term keeps which does not tell the labels apart; vote of the base rate, so that few or far examples say little.
NEUTRAL, PRIOR_VOTES = 0.1, 0.5
#: Score from which a text counts as toxic.
THRESHOLD = 0.7

_WORDS = re.compile(r"[^\W\d_]+").findall

#: Term numbers in ascending order, and a number for each.
Vector = tuple[np.ndarray, np.ndarray]


def term_counts(texts: pa.Array, among: dict[str, int]) -> Iterator[Vector]:
    """The terms of each text and how often it holds them."""
    for part in slices(texts):
        lists = pc.utf8_split_whitespace(pc.utf8_lower(pc.fill_null(part, "")))
        words = lists.flatten().dictionary_encode()
        terms = [[among[t] for t in _WORDS(w) if t in among] for w in words.dictionary.to_pylist()]
        sizes = np.fromiter(map(len, terms), dtype=np.int64, count=len(terms))
        pool = np.fromiter((t for own in terms for t in own), dtype=np.int64, count=int(sizes.sum()))
        found, length = gathered(pool, sizes, np.asarray(words.indices))
        owner = np.repeat(np.arange(len(part)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))
        ends = np.cumsum(np.bincount(owner, length, len(part)).astype(np.int64))
        for low, high in zip(np.append(0, ends[:-1]).tolist(), ends.tolist(), strict=True):
            yield np.unique(found[low:high], return_counts=True)


def association(toxic_with: np.ndarray, other_with: np.ndarray, toxic: int, other: int) -> np.ndarray:
    """Log-likelihood ratio of a 2 x 2 table for each term."""
    total = toxic + other
    table = np.stack([toxic_with, other_with, toxic - toxic_with, other - other_with]).astype(float)
    held, label = toxic_with + other_with, np.array([toxic, other, toxic, other])[:, None]
    expected = label * np.stack([held, held, total - held, total - held]) / total
    return 2 * np.where(table > 0, table * np.log(np.maximum(table, 1) / np.maximum(expected, 1e-12)), 0).sum(axis=0)


class BlockMaxIndex:
    """Exact top-k by cosine over unit vectors."""

    def __init__(self, vectors: list[Vector], terms: int, block: int = BLOCK):
        # Like examples next to each other make blocks with low maxima: by the commonest term, then by the heaviest.
        held = np.bincount(np.concatenate([np.zeros(0, dtype=np.int64), *[t for t, _ in vectors]]), minlength=terms)
        key = lambda i: (int(vectors[i][0][held[vectors[i][0]].argmax()]), int(vectors[i][0][vectors[i][1].argmax()]), i) if len(vectors[i][0]) else (-1, -1, i)
        self.order = np.array(sorted(range(len(vectors)), key=key), dtype=np.int64)
        self.size, self.block, self.blocks = len(vectors), block, -(-len(vectors) // block)
        sizes = np.array([len(vectors[i][0]) for i in self.order], dtype=np.int64)
        flat, weights = (np.concatenate([np.zeros(0), *[vectors[i][k] for i in self.order]]) for k in (0, 1))
        place = np.repeat(np.arange(self.size), sizes)
        # Postings by block and term; where each term's begin in each block; and the largest weight there.
        cell = place // block * terms + flat.astype(np.int64)
        by_cell = np.argsort(cell, kind="stable")
        self.place, self.weights = place[by_cell].astype(np.int32), weights[by_cell]
        held = np.bincount(cell, minlength=self.blocks * terms)
        self.begins = np.concatenate([[0], np.cumsum(held)]).astype(np.int32)
        cells = np.flatnonzero(held)
        largest = np.maximum.reduceat(self.weights, self.begins[cells]) if len(cells) else np.zeros(0)
        by_term = np.argsort(cells % max(1, terms), kind="stable")
        self.largest, self.at_block = largest[by_term], cells[by_term] // max(1, terms)
        self.spread = np.bincount(cells % max(1, terms), minlength=terms)
        self.first = np.cumsum(self.spread) - self.spread
        self.terms = terms

    def _score(self, blocks: np.ndarray, query: Vector, scores: np.ndarray) -> None:
        cells = (blocks[:, None] * self.terms + query[0]).ravel()
        begins = self.begins[cells].astype(np.int64)
        count = self.begins[cells + 1] - begins
        held = np.flatnonzero(count)
        begins, count = begins[held], count[held]
        at = np.repeat(begins - (np.cumsum(count) - count), count)
        at += np.arange(len(at))
        weight = np.repeat(query[1][held % len(query[0])], count) * self.weights[at]
        low = (blocks * self.block)[:, None] + np.arange(self.block)
        scores[low[low < self.size]] = 0
        scores += np.bincount(self.place[at], weight, self.size)

    def search(self, query: Vector, k: int, skip: int = -1) -> list[tuple[int, float]]:
        """(example, cosine) of the k nearest with a positive cosine; ties go to the lower example."""
        terms, weights = query
        if not len(terms) or not self.size:
            return []
        count = self.spread[terms]
        at = np.repeat(self.first[terms] - (np.cumsum(count) - count), count) + np.arange(count.sum())
        bound = np.bincount(self.at_block[at], self.largest[at] * np.repeat(weights, count), self.blocks)
        order = np.argsort(-bound, kind="stable")
        scores = np.full(self.size, -1.0)
        done, more = 0, FIRST_BLOCKS
        while done < self.blocks:
            self._score(order[done : done + more], query, scores)
            done, more = done + more, 2 * more
            seen = scores[self.order != skip] if skip >= 0 else scores
            least = np.partition(seen, -k)[-k] if len(seen) > k else -1.0
            # Rounding must not cost an example that ties.
            if done >= self.blocks or bound[order[done]] < max(least, 1e-12) - 1e-9:
                break
        near = np.flatnonzero((scores >= max(least, 1e-12)) & (self.order != skip))
        best = near[np.lexsort((self.order[near], -np.round(scores[near], 12)))][:k]
        return [(int(self.order[i]), float(scores[i])) for i in best]


def monotone_fit(votes: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Least-squares non-decreasing curve through (vote, label), as knots."""
    pools: list[list[float]] = []  # vote sum, label sum, count
    for vote, label in sorted(zip(votes.tolist(), labels.tolist(), strict=True)):
        pools.append([vote, label, 1])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            last = pools.pop()
            pools[-1] = [a + b for a, b in zip(pools[-1], last, strict=True)]
    return np.array([p[0] / p[2] for p in pools]), np.array([(p[1] + 0.02) / (p[2] + 0.04) if p[1] in (0, p[2]) else p[1] / p[2] for p in pools])


@dataclass
class ToxicityModel:
    terms: dict[str, int]
    weights: np.ndarray
    index: BlockMaxIndex
    labels: np.ndarray
    ids: list[int]
    base: float
    knots: tuple[np.ndarray, np.ndarray] | None = None
    name: str = field(default_factory=lambda: uuid.uuid4().hex)

    def vector(self, counts: Vector) -> Vector:
        terms, held = counts
        raw = (1 + np.log(held)) * self.weights[terms]
        length = np.sqrt((raw * raw).sum())
        return (terms, raw / length) if length else (terms[:0], raw[:0])

    def vote(self, nearest: list[tuple[int, float]]) -> float:
        weights = np.array([s for _, s in nearest]) ** 2
        return float((weights @ self.labels[[i for i, _ in nearest]] + PRIOR_VOTES * self.base) / (weights.sum() + PRIOR_VOTES)) if nearest else self.base

    def score(self, counts: Vector) -> tuple[float, list[int]]:
        """Score of a text and the doc_ids of the examples behind it."""
        nearest = self.index.search(self.vector(counts), NEAREST)
        if not nearest or self.knots is None:
            return self.base, []
        return float(np.interp(self.vote(nearest), *self.knots)), [self.ids[i] for i, _ in nearest]


def term_weights(held: np.ndarray, held_toxic: np.ndarray, examples: int, toxic: int) -> np.ndarray:
    """IDF of each term, times what its association with the label leaves of it."""
    idf = np.log((1 + examples) / (1 + held))
    if not toxic or toxic == examples:
        return idf
    strength = association(held_toxic, held - held_toxic, toxic, examples - toxic)
    chance = 2 * np.log(max(2, len(held)))
    return idf * np.clip(strength / (2 * chance), NEUTRAL, 1.0)


def fit(examples: list[tuple[int, str | None, int]]) -> ToxicityModel:
    """Learn from (doc_id, text, label)."""
    labels = np.array([label for _, _, label in examples], dtype=float)
    held, toxic = Counter(), Counter()
    for _, text, label in examples:
        own = set(_WORDS(text.lower())) if text else set()
        held.update(own)
        if label:
            toxic.update(own)
    names = sorted(t for t, n in held.items() if n >= LEAST_TEXTS)
    terms = {t: i for i, t in enumerate(names)}
    weights = term_weights(np.array([held[t] for t in names], dtype=float), np.array([toxic[t] for t in names], dtype=float), len(examples), int(labels.sum()))
    base = float(labels.mean()) if len(labels) else 0.0
    model = ToxicityModel(terms, weights, BlockMaxIndex([], len(terms)), labels, [i for i, _, _ in examples], base)
    vectors = [model.vector(c) for c in term_counts(pa.array([t for _, t, _ in examples], pa.string()), terms)]
    model.index = BlockMaxIndex(vectors, len(terms))
    if examples:
        votes = np.array([model.vote(model.index.search(v, NEAREST, skip=i)) for i, v in enumerate(vectors)])
        model.knots = monotone_fit(votes, labels)
    return model


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, folds: int, held_out: int, bound: int) -> DataFrame:
    """(doc_id, text, label) of at most ``bound`` labelled texts outside fold ``held_out``: those with the least hash."""
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label"))
    usable = usable.where(F.col("doc_id").isNotNull() & F.col("label").isin(0, 1) & (bucket_of("doc_id", folds) != held_out))
    draw = F.pmod(F.xxhash64(F.lit("labelled sample"), "doc_id"), F.lit(1 << 40))
    # Twice as many, since some have no text or a very long one.
    few = usable.where(draw <= int(min(1.0, 2.5 * bound / max(1, usable.count())) * (1 << 40)))
    drawn = few.distinct().orderBy(draw, "doc_id", "label").limit(2 * bound)
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.length("text") <= SAMPLE_CHARS).join(F.broadcast(drawn), "doc_id")
    return found.orderBy(draw, "doc_id", "label", "text").limit(bound)


def score_documents(docs: DataFrame, labels: DataFrame, folds: int = 3, held_out: int = 1) -> DataFrame:
    """(doc_id, held_out, score, predicted, evidence) of every whole text."""
    spark = docs.sparkSession
    sample = labelled_sample(docs, labels, "toxic", folds, held_out, SAMPLE_TEXTS)
    shared = spark.sparkContext.broadcast(fit(sorted((r["doc_id"], r["text"], r["label"]) for r in sample.collect())))

    def mark(batches):
        known = worker_state("toxicity", shared.value.name, lambda: shared.value)
        for batch in batches:
            found = [known.score(counts) for counts in term_counts(batch.column(2), known.terms)]
            scores = [s for s, _ in found]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(scores, pa.float64()), pa.array([int(s >= THRESHOLD) for s in scores], pa.int32()), pa.array([e for _, e in found], pa.list_(pa.int64()))],
                names=["doc_id", "held_out", "score", "predicted", "evidence"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(bucket_of("doc_id", folds) == held_out, F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(mark, "doc_id long, held_out boolean, score double, predicted int, evidence array<long>")
