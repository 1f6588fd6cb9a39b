"""Lexical retrieval packing.

Documents are dealt into shards by lexical content; each shard holds a BM25
inverted index over the token ids of its documents, weighted by the counts of
the whole table. A seed document opens a window; the index returns the unused
neighbours of the seed, best first, and they fill the rest of the window. A
neighbour that does not fit is cut; what is left of it seeds the next window.
So every window but a shard's last is full, and the last is cut into pieces
whose lengths are powers of two, which need no padding.

Dealing: weighted terms of a document are projected to ``AXES`` numbers; a tree
of splits, grown on a sample, gives its leaf; shards are ranges of leaves in
tree order, and a leaf with more documents than a shard spreads over several.
A seed asks its own shard only, so neighbours across a border are missed.

A task packs what it has buffered at the end of a shard, and whenever that
reaches ``SHARD_TOKENS``, so its memory is bounded.

Defined cases: a null text counts as empty and has the end id alone; repeated
rows are separate documents; an empty table gives no pieces; a document that
has no lexical neighbour is followed by the next unused one of its shard.
"""

from __future__ import annotations

import uuid
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .encoding import binary_array, id_type, library_encoder, with_end
from .shared import settle, worker_state

#: Window in tokens; documents that a shard aims at; buffered tokens at which a task packs.
WINDOW, SHARD_DOCS, SHARD_TOKENS = 1024, 2000, 4_000_000
#: BM25 saturation and length normalisation.
K1, B = 1.2, 0.75
#: Terms of at least one in so many documents have dense rows in an index.
DENSE = 4
#: Numbers that a document is projected to; documents on which the tree is grown; leaves for each shard; sampled documents that a split needs.
AXES, TREE_SAMPLE, LEAVES_EACH, LEAST_SPLIT = 96, 20_000, 4, 8
#: Most frequent terms that are projected by one product for many documents; documents and tokens that are projected at once.
COMMON, PROJECTED_DOCS, PROJECTED_TOKENS = 1024, 1000, 1_000_000

PIECES = T.StructType(
    [
        T.StructField("doc_id", T.LongType()),
        T.StructField("start", T.LongType()),
        T.StructField("length", T.LongType()),
        T.StructField("ids_crc32", T.LongType()),
        T.StructField("doc_tokens", T.LongType()),
        T.StructField("sequence_id", T.LongType()),
        T.StructField("offset", T.LongType()),
    ]
)


@dataclass(frozen=True)
class Statistics:
    """Of the whole table: documents, mean length, and documents of each term id."""

    documents: int
    mean: float
    df: np.ndarray

    def idf(self, terms: np.ndarray) -> np.ndarray:
        df = self.df[terms]
        return np.log1p((self.documents - df + 0.5) / (df + 0.5))


def statistics_of(documents: list[np.ndarray]) -> Statistics:
    flat = np.concatenate([np.unique(d) for d in documents]).astype(np.int64)
    return Statistics(len(documents), float(np.mean([len(d) for d in documents])), np.bincount(flat))


def bm25(idf: np.ndarray, tf: np.ndarray, length, mean: float) -> np.ndarray:
    return idf * tf * (K1 + 1) / (tf + K1 * (1 - B + B * length / max(mean, 1e-9)))


def term_table(ids: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(term, document, how often) by document and term, from one sort of the ids of documents of these sizes."""
    bits = 8 * ids.itemsize if ids.itemsize <= 4 else 32
    kind = np.uint32 if bits == 16 and len(sizes) <= 1 << 16 else np.uint64
    keys = np.sort((np.repeat(np.arange(len(sizes), dtype=kind), sizes) << kind(bits)) | ids.astype(kind))
    first = np.flatnonzero(np.concatenate([np.ones(min(1, len(keys)), dtype=bool), keys[1:] != keys[:-1]]))
    keys, tf = keys[first], np.diff(first, append=len(keys)).astype(np.float64)
    return (keys & kind((1 << bits) - 1)).astype(np.uint16 if bits == 16 else np.uint32), (keys >> kind(bits)).astype(np.int64), tf


class LexicalIndex:
    """BM25 postings of one shard; terms are token ids. ``whole`` counts the table, else the shard does."""

    def __init__(self, documents: list[np.ndarray], whole: Statistics | None = None):
        whole = whole or statistics_of(documents)
        lengths = np.array([len(d) for d in documents])
        flat, owner, tf = term_table(np.concatenate(documents), lengths)
        sizes = np.bincount(owner, minlength=len(documents))
        counted = np.bincount(flat)
        vocabulary = np.flatnonzero(counted)
        held, place = counted[vocabulary], (np.cumsum(counted > 0) - 1)[flat]
        weight = bm25(whole.idf(vocabulary)[place], tf, lengths[owner], whole.mean)
        order = np.argsort(flat, kind="stable")  # by counting, where ids have 16 bits
        ends = np.cumsum(held)[:-1]
        self.owners, self.weights = np.split(owner[order].astype(np.intp), ends), np.split(weight[order], ends)
        self.first = np.concatenate([[0], np.cumsum(sizes)])
        self.place, self.held, self.size = place, held, len(documents)
        often = (held * DENSE >= self.size) & (held > 1)
        self.row = np.where(often, np.cumsum(often) - 1, -1)
        self.dense = np.zeros((int(often.sum()), self.size), dtype=np.float32)
        chosen = self.row[place]
        self.dense[chosen[chosen >= 0], owner[chosen >= 0]] = weight[chosen >= 0]

    def scores(self, seed: int) -> np.ndarray:
        """BM25 of every document for all terms of the seed that another document of the shard has too."""
        place = self.place[self.first[seed] : self.first[seed + 1]]
        row = self.row[place]
        asked = np.zeros(len(self.dense), dtype=np.float32)
        asked[row[row >= 0]] = 1
        out = asked @ self.dense
        rare = place[(row < 0) & (self.held[place] > 1)].tolist()
        if rare:
            out = out + np.bincount(np.concatenate([self.owners[p] for p in rare]), np.concatenate([self.weights[p] for p in rare]), self.size)
        return out


class Projector:
    """The weighted terms of documents, scaled to length 1, on ``AXES`` random axes."""

    def __init__(self, whole: Statistics):
        self.whole, self.axes = whole, np.random.default_rng(1).standard_normal((len(whole.df), AXES), dtype=np.float32)
        # The root of the idf on both sides makes inner products weigh a shared term once by it.
        self.idf = np.sqrt(whole.idf(np.arange(len(whole.df))))

        common = np.argsort(-whole.df, kind="stable")[:COMMON]
        self.column = np.full(len(whole.df), -1)
        self.column[common] = np.arange(len(common))
        self.common = self.axes[common]

    def some(self, documents: list[np.ndarray]) -> np.ndarray:
        lengths = np.array([len(d) for d in documents])
        terms, owner, tf = term_table(np.concatenate(documents), lengths)
        weight = bm25(self.idf[terms], tf, lengths[owner], self.whole.mean)
        norm = np.sqrt(np.bincount(owner, weight * weight, len(documents)))
        weight = (weight / np.where(norm > 0, norm, 1.0)[owner]).astype(np.float32)
        column = self.column[terms]
        often = column >= 0
        dense = np.zeros((len(documents), len(self.common)), dtype=np.float32)
        dense[owner[often], column[often]] = weight[often]
        out = dense @ self.common
        terms, weight, ends = terms[~often], weight[~often], np.cumsum(np.bincount(owner[~often], minlength=len(documents)))
        low = 0
        for row, high in zip(out, ends.tolist(), strict=True):
            if high > low:
                row += weight[low:high] @ self.axes[terms[low:high]]
            low = high
        return out

    def all(self, documents: list[np.ndarray]) -> np.ndarray:
        out, part, tokens = [np.zeros((0, AXES), dtype=np.float32)], [], 0
        for document in documents:
            part.append(document)
            tokens += len(document)
            if tokens >= PROJECTED_TOKENS or len(part) == PROJECTED_DOCS:
                out.append(self.some(part))
                part, tokens = [], 0
        return np.concatenate([*out, self.some(part)] if part else out)


class SplitTree:
    """Splits at the widest gap near the median along the main axis of each node's sample; leaves are numbered in tree order.

    A node without a split passes its documents on to the lower side. Only
    nodes that split are held, so the size of the tree is bounded by the sample.
    """

    def __init__(self, sample: np.ndarray, leaves: int):
        self.depth = max(0, int(np.ceil(np.log2(leaves))))
        axes, cuts = {}, {}
        nodes = {1: sample}
        for _ in range(self.depth):
            grown = {}
            for node, rows in nodes.items():
                if len(rows) < LEAST_SPLIT:
                    continue
                centred = rows - rows.mean(axis=0)
                axis = np.linalg.eigh(centred.T @ centred)[1][:, -1].astype(np.float32)
                along = rows @ axis
                middle = np.sort(along)[int(0.3 * len(rows)) : int(0.7 * len(rows)) + 1]
                at = int(np.diff(middle).argmax())
                cut = (middle[at] + middle[at + 1]) / 2
                axes[node], cuts[node] = axis, cut
                grown[2 * node], grown[2 * node + 1] = rows[along <= cut], rows[along > cut]
            nodes = grown
        self.nodes = np.array(sorted(axes), dtype=np.int64)
        self.axes = np.array([axes[n] for n in self.nodes.tolist()], dtype=np.float32).reshape(-1, sample.shape[1])
        self.cuts = np.array([cuts[n] for n in self.nodes.tolist()], dtype=np.float32)

    def leaves(self, rows: np.ndarray) -> np.ndarray:
        node = np.ones(len(rows), dtype=np.int64)
        for _ in range(self.depth if len(self.nodes) else 0):
            at = np.minimum(np.searchsorted(self.nodes, node), len(self.nodes) - 1)
            upper = (np.einsum("ij,ij->i", rows, self.axes[at]) > self.cuts[at]) & (self.nodes[at] == node)
            node = 2 * node + upper
        return node - (1 << self.depth) if len(self.nodes) else node - 1


def pack_shard(documents: list[np.ndarray], window: int = WINDOW, whole: Statistics | None = None):
    """Yield (document, start, length, sequence, offset); sequences count from 0. The end id is no term."""
    if not documents:
        return
    index = LexicalIndex([d[:-1] for d in documents], whole)
    unused = np.ones(len(documents), dtype=bool)
    following, sequence, offset = 0, 0, 0
    opening: list[tuple[int, int, int]] = []  # pieces of the window that is being filled
    seed, start = 0, 0
    scores = None
    while True:
        unused[seed] = False
        left = len(documents[seed]) - start
        take = min(left, window - offset)
        opening.append((seed, start, take))
        offset += take
        if offset == window:
            at = 0
            for piece in opening:
                yield (*piece, sequence, at)
                at += piece[2]
            sequence, offset, opening, scores = sequence + 1, 0, [], None
        if take < left:
            start += take
            continue
        if scores is None:
            scores = index.scores(seed)
        candidates = np.where(unused, scores, -1.0)
        best = int(candidates.argmax())
        if candidates[best] <= 0:
            while following < len(documents) and not unused[following]:
                following += 1
            if following == len(documents):
                break
            best = following
        seed, start = best, 0
    # What is left is shorter than a window: cut at powers of two, largest first.
    begun = 0
    while begun < offset:
        length = 1 << ((offset - begun).bit_length() - 1)
        end, at = begun + length, 0
        while opening and at < length:
            document, start, count = opening[0]
            take = min(count, length - at)
            yield document, start, take, sequence, at
            at += take
            opening[0] = (document, start + take, count - take)
            if count == take:
                opening.pop(0)
        begun, sequence = end, sequence + 1


def documents_of(column: pa.Array, kind: str) -> list[np.ndarray]:
    """The ids of each row of packed ids, the end id included."""
    return [np.frombuffer(ids, dtype=kind) for ids in column.to_pylist()]


class TermCounts:
    """Documents, length and documents of each term id, as a task meets them; packed as one row."""

    def __init__(self):
        self.documents, self.length, self.df = 0, 0, np.zeros(0, dtype=np.int64)

    def _widen(self, size: int) -> None:
        if size > len(self.df):
            self.df = np.concatenate([self.df, np.zeros(size - len(self.df), dtype=np.int64)])

    def count(self, ids: np.ndarray, sizes: np.ndarray) -> None:
        """Documents one after the other, without their end ids."""
        df = np.bincount(term_table(ids, sizes)[0])
        self._widen(len(df))
        self.df[: len(df)] += df
        self.documents, self.length = self.documents + len(sizes), self.length + len(ids)

    def packed(self) -> bytes:
        return np.array([self.documents, self.length, *self.df], dtype="<i8").tobytes()

    def add(self, packed: bytes) -> None:
        counts = np.frombuffer(packed, dtype="<i8")
        self._widen(len(counts) - 2)
        self.df[: len(counts) - 2] += counts[2:]
        self.documents, self.length = self.documents + int(counts[0]), self.length + int(counts[1])


def table_statistics(encoded: DataFrame) -> Statistics:
    """The sum of all tasks' counts; each partition sends at most one row for each term id."""

    def add_up(batches):
        own = TermCounts()
        for batch in batches:
            for packed in batch.column(0).to_pylist():
                own.add(packed)
        held = np.flatnonzero(own.df)
        yield pa.RecordBatch.from_arrays([pa.array([-2, -1, *held.tolist()], pa.int64()), pa.array([own.documents, own.length, *own.df[held].tolist()], pa.int64())], names=["term", "n"])

    counts = encoded.select("counts").where("counts IS NOT NULL").mapInArrow(add_up, "term long, n long").groupBy("term").agg(F.sum("n").alias("n"))
    found = {r["term"]: r["n"] for r in counts.collect()}
    documents, length = found.pop(-2, 0), found.pop(-1, 0)
    df = np.zeros(max(found, default=-1) + 1, dtype=np.int64)
    df[list(found)] = list(found.values())
    return Statistics(documents, length / max(documents, 1), df)


class Dealer:
    """The shard of each document: leaves in tree order share the shards out by their shares of the sample.

    A leaf that is larger than a shard spreads over several by the hash of
    ``doc_id``, so no shard is much larger than another, whatever recurs.
    """

    def __init__(self, sample: np.ndarray, shards: int):
        self.tree, self.shards = SplitTree(sample, LEAVES_EACH * shards), shards
        self.leaves, counts = np.unique(self.tree.leaves(sample), return_counts=True)
        self.ends = np.concatenate([[0], np.cumsum(counts)]) * (shards / max(1, len(sample)))

    def __call__(self, doc_ids: np.ndarray, projected: np.ndarray) -> np.ndarray:
        leaf = self.tree.leaves(projected)
        place = np.searchsorted(self.leaves, leaf)
        seen = np.minimum(place, len(self.leaves) - 1)
        width = np.where(self.leaves[seen] == leaf, self.ends[seen + 1] - self.ends[seen], 0.0)
        with np.errstate(over="ignore"):
            mixed = (doc_ids.astype(np.uint64) ^ np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xBF58476D1CE4E5B9)
            mixed = (mixed ^ (mixed >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
        inside = (mixed >> np.uint64(11)).astype(np.float64) / (1 << 53)
        return np.minimum((self.ends[place] + width * inside).astype(np.int64), self.shards - 1)


def sampled_rows(encoded: DataFrame, whole: Statistics, kind: str, name: str) -> np.ndarray:
    """Projections of a sample of bounded size."""
    shared = encoded.sparkSession.sparkContext.broadcast(whole)

    def project(batches):
        own = worker_state("projector", name, lambda: Projector(shared.value))
        for batch in batches:
            rows = own.all([d[:-1] for d in documents_of(batch.column(0), kind)])
            yield pa.RecordBatch.from_arrays([pa.array([row.tobytes() for row in rows], pa.binary())], names=["row"])

    chosen = encoded.select("ids").sample(min(1.0, TREE_SAMPLE / whole.documents), seed=1)
    rows = [bytes(r["row"]) for r in chosen.mapInArrow(project, "row binary").collect()]
    return np.frombuffer(b"".join(rows), dtype=np.float32).reshape(-1, AXES)


def deal(encoded: DataFrame, whole: Statistics, kind: str) -> DataFrame:
    """(shard, doc_id, ids); the rows of a shard lie next to each other in one partition."""
    shards = max(1, -(-whole.documents // SHARD_DOCS))
    if shards == 1:
        return encoded.select(F.lit(0).cast("long").alias("shard"), "doc_id", "ids").repartition(1).sortWithinPartitions("doc_id", "ids")
    name = uuid.uuid4().hex
    shared = encoded.sparkSession.sparkContext.broadcast((whole, Dealer(sampled_rows(encoded, whole, kind, name), shards)))

    def place(batches):
        whole, dealer = shared.value
        projector = worker_state("projector", name, lambda: Projector(whole))
        for batch in batches:
            found = dealer(pc.fill_null(batch.column(0), 0).to_numpy(), projector.all([d[:-1] for d in documents_of(batch.column(1), kind)]))
            yield pa.RecordBatch.from_arrays([pa.array(found), batch.column(0), batch.column(1)], names=["shard", "doc_id", "ids"])

    return encoded.mapInArrow(place, "shard long, doc_id long, ids binary").repartition(shards, "shard").sortWithinPartitions("shard", "doc_id", "ids")


def pack_documents(docs: DataFrame, vocabulary: str, window: int = WINDOW, end_id: int = 0, with_ids: bool = False, added: bool = False) -> DataFrame:
    """One row for each piece; ``with_ids`` adds the piece's ids as an array; ``added`` as in ``library_encoder``."""
    kind = id_type(vocabulary)
    names = [f.name for f in PIECES] + ["ids"] * with_ids

    def packed(ids: list[int], texts: list[np.ndarray], first: int):
        rows: list[list] = [[] for _ in names]
        last = -1
        for document, start, length, sequence, offset in pack_shard(texts, window, whole):
            piece = texts[document][start : start + length].astype("<u4")
            last = max(last, sequence)
            for column, value in zip(rows, (ids[document], start, length, zlib.crc32(piece), len(texts[document]), first + sequence, offset), strict=False):
                column.append(value)
            if with_ids:
                rows[-1].append(piece.astype(np.int32))
        arrays = [pa.array(column, pa.int64()) for column in rows[:7]] + ([pa.array(rows[7], pa.list_(pa.int32()))] if with_ids else [])
        return pa.RecordBatch.from_arrays(arrays, names=names), first + last + 1

    def encode(batches):
        """Rows of ids, and in the end a row of the task's counts, whose ids are null."""
        encoder, counts = library_encoder(vocabulary, added), TermCounts()
        for batch in batches:
            low = 0
            for ids, sizes in encoder.encode_slices(batch.column(1)):
                counts.count(ids := ids.astype(kind), sizes)
                ids, sizes = with_end(ids, sizes, end_id)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, len(sizes)), binary_array(ids, sizes), pa.nulls(len(sizes), pa.binary())], names=["doc_id", "ids", "counts"])
                low += len(sizes)
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.array([counts.packed()], pa.binary())], names=["doc_id", "ids", "counts"])

    def pack(batches):
        following = TaskContext.get().partitionId() << 36
        ids, texts, tokens, at = [], [], 0, None
        for batch in batches:
            for shard, doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), documents_of(batch.column(2), kind), strict=True):
                if texts and (shard != at or tokens >= SHARD_TOKENS):
                    rows, following = packed(ids, texts, following)
                    yield rows
                    ids, texts, tokens = [], [], 0
                at = shard
                ids.append(doc_id)
                texts.append(text)
                tokens += len(text)
        if ids:
            yield packed(ids, texts, following)[0]

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text")
    written = settle(rows.mapInArrow(encode, "doc_id long, ids binary, counts binary"), "packing-ids")
    whole, encoded = table_statistics(written), written.where("ids IS NOT NULL").select("doc_id", "ids")
    schema = T.StructType([*PIECES.fields, *([T.StructField("ids", T.ArrayType(T.IntegerType(), False))] if with_ids else [])])
    return deal(encoded, whole, kind).mapInArrow(pack, schema)
