"""Near-duplicate embeddings through an inverted multi-index.

The two halves of the vectors have codebooks of their own; their product is a
grid of cells. A vector lies in the cell of its nearest codewords. A
multi-sequence traversal visits cells in the order of the sum of the two
distances: codewords of both halves are sorted by distance, and each one of the
first half is opened with ever more of the second. It goes on until the sum
exceeds that of the vector's own cell by more than a gap, which is calibrated
before: on a sample, a partner at exactly the least similarity must lie in a
visited cell with the target recall, one way or the other. The vectors of the
visited cells are compared by exact cosine in double precision.

Cells are stored in blocks that share a few neighbouring first codewords; a
block with very many vectors is cut in chunks of bounded size. A vector goes to
each block once, whatever the number of cells it visits there, and the task
finds them again.

Equal vectors are one class with a count before anything else. Links are
counted, and components found, without a list of pairs: a block adds up the
copies linked with each vector, and hands on a spanning forest of its links.

Vectors of different lengths are never linked; each length has an index of its
own, from its share of the sample.

Defined cases: vectors that are null, empty, zero, hold a null or a component
that is not finite are linked with nothing; a null ``vec_id`` is linked with
nothing and has no component; rows that repeat a ``vec_id`` are reported as
often; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import components
from .shared import look_up, settle, worker_state

#: Least cosine of a link; recall that the visits are calibrated to.
COSINE, RECALL = 0.9, 0.999
#: Bound of the training sample, and of its growth with the codewords; rounds of codebook training; queries and partners of the calibration.
SAMPLE, SAMPLE_EACH, ROUNDS, PROBES = 8_000, 8, 8, 600
#: Vectors that a cell aims at; most codewords of a half (reached at about a thousand million vectors); first codewords of a block; vectors of a chunk.
CELL, MOST_CODES, WIDE, CHUNK = 64, 4096, 4, 8_192


def codebook(points: np.ndarray, size: int, seed: int) -> np.ndarray:
    """Centres by Lloyd's rounds from a random start."""
    rng = np.random.default_rng(seed)
    centres = points[rng.choice(len(points), size, replace=False)].copy()
    for _ in range(ROUNDS):
        nearest = distances(points, centres).argmin(axis=1)
        counts = np.bincount(nearest, minlength=size)
        sums = np.stack([np.bincount(nearest, points[:, d], size) for d in range(points.shape[1])], axis=1)
        centres = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], centres)
    return centres


def neighbourly(centres: np.ndarray) -> np.ndarray:
    """An order of the centres in which neighbours are close: halves along the main axis, again and again."""
    if len(centres) <= 2:
        return np.arange(len(centres))
    centred = centres - centres.mean(axis=0)
    along = centred @ np.linalg.eigh(centred.T @ centred)[1][:, -1]
    order = np.argsort(along, kind="stable")
    low, high = order[: len(order) // 2], order[len(order) // 2 :]
    return np.concatenate([low[neighbourly(centres[low])], high[neighbourly(centres[high])]])


def distances(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """Squared distances, points by centres; each is the same whatever other points come along."""
    return (points**2).sum(axis=1)[:, None] - 2 * np.einsum("nd,cd->nc", points, centres) + (centres**2).sum(axis=1)[None]


class MultiIndex:
    """Two codebooks, and how far beyond its own cell a vector's visits go."""

    def __init__(self, sample: np.ndarray, codes: int, seed: int = 5):
        self.half = sample.shape[1] // 2
        self.codes = max(1, min(codes, len(sample))) if self.half else 1
        halves = sample[:, : self.half], sample[:, self.half :]
        self.books = [codebook(half, self.codes, seed + i) if self.codes > 1 else half[:1] for i, half in enumerate(halves)]
        if self.codes > 1:
            self.books[0] = self.books[0][neighbourly(self.books[0])]
        self.gap = self._calibrate(sample, np.random.default_rng(seed + 2)) if self.codes > 1 else 0.0

    def ranked(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return tuple(distances(part, book) for part, book in zip((unit[:, : self.half], unit[:, self.half :]), self.books, strict=True))

    def _calibrate(self, sample: np.ndarray, rng: np.random.Generator) -> float:
        query = sample[rng.choice(len(sample), min(PROBES, len(sample)), replace=False)]
        query = np.repeat(query, -(-PROBES * 4 // len(query)), axis=0)
        aside = rng.normal(size=query.shape)
        aside -= (aside * query).sum(axis=1, keepdims=True) * query
        aside /= np.maximum(np.linalg.norm(aside, axis=1, keepdims=True), 1e-12)
        partner = COSINE * query + np.sqrt(1 - COSINE**2) * aside

        def beyond(a: np.ndarray, b: np.ndarray) -> np.ndarray:
            """How far beyond a's own cell the cell of b is, from a."""
            (first, second), (i, j) = self.ranked(a), [d.argmin(axis=1) for d in self.ranked(b)]
            there = np.take_along_axis(first, i[:, None], 1) + np.take_along_axis(second, j[:, None], 1)
            return there[:, 0] - first.min(axis=1) - second.min(axis=1)

        return float(np.quantile(np.minimum(beyond(query, partner), beyond(partner, query)), RECALL, method="higher"))

    def reach(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        """The distance up to which each vector visits cells."""
        return first.min(axis=1) + second.min(axis=1) + self.gap

    def opened(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The block of each vector, and (vectors, blocks): those in which it visits at least one cell."""
        first, second = self.ranked(unit)
        nearest = np.minimum.reduceat(first, np.arange(0, self.codes, WIDE), axis=1)
        return first.argmin(axis=1) // WIDE, nearest + second.min(axis=1, keepdims=True) <= self.reach(first, second)[:, None]

    def traverse(self, unit: np.ndarray) -> list[list[int]]:
        """The cells that each vector visits, nearest first: codewords of the first half are opened in order, each with a prefix of the second's."""
        first, second = self.ranked(unit)
        by_first, by_second = first.argsort(axis=1, kind="stable"), second.argsort(axis=1, kind="stable")
        out = []
        for a, b, i, j, limit in zip(first, second, by_first, by_second, self.reach(first, second), strict=True):
            total = a[i][:, None] + b[j][None]
            rows, columns = np.nonzero(total <= limit)
            nearest = np.argsort(total[rows, columns], kind="stable")
            out.append((i[rows[nearest]] * self.codes + j[columns[nearest]]).tolist())
        return out


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, size, vector, d1, d2): vectors that can be linked, as bytes of doubles or, where the table holds those, floats, and a digest of their values."""
    value, kind = F.col("embedding"), vectors.schema["embedding"].dataType.elementType.simpleString()
    narrow = "float" if kind in ("float", "tinyint", "smallint") else "double"
    finite = F.forall(value, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.transform("embedding", lambda x: x.cast(narrow)).alias("embedding"))
    rows = rows.where(F.col("vec_id").isNotNull() & value.isNotNull() & (F.size(value) > 0) & finite & F.exists(value, lambda x: x != 0))

    def digest(batches):
        for batch in batches:
            lists = batch.column(1)
            sizes = np.diff(np.asarray(lists.offsets))
            values = np.asarray(lists.flatten()) + 0.0  # no negative zero
            ends = np.cumsum(sizes)
            raw = [values[e - s : e].tobytes() for e, s in zip(ends.tolist(), sizes.tolist(), strict=True)]
            names = np.frombuffer(b"".join(xxhash.xxh3_128_digest(r) for r in raw), dtype=np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes.astype(np.int32)), pa.array(raw, pa.binary()), pa.array(names[:, 0]), pa.array(names[:, 1])], names=["vec_id", "size", "vector", "d1", "d2"])

    return rows.mapInArrow(digest, "vec_id long, size int, vector binary, d1 long, d2 long")


def units(raw: list[bytes], size: int) -> np.ndarray:
    """Unit vectors in double precision."""
    table = np.frombuffer(b"".join(raw), dtype=np.float32 if raw and len(raw[0]) == 4 * size else np.float64).reshape(len(raw), -1).astype(np.float64)
    # Scaled first, so that no square leaves the range of doubles.
    table = table / np.abs(table).max(axis=1, keepdims=True)
    return table / np.linalg.norm(table, axis=1, keepdims=True)


class HeldBlock:
    """The vectors of one chunk of a block, by cell, and what links them with vectors that visit."""

    def __init__(self, index: MultiIndex, ids: np.ndarray, unit: np.ndarray, copies: np.ndarray):
        first, second = index.ranked(unit)
        cell = first.argmin(axis=1) * index.codes + second.argmin(axis=1)
        order = np.argsort(cell, kind="stable")
        self.index, self.ids, self.unit, self.copies = index, ids[order], unit[order], copies[order]
        self.first, self.second, self.reach = first[order], second[order], index.reach(first, second)[order]
        self.cells, starts = np.unique(cell[order], return_index=True)
        self.bounds = [*starts.tolist(), len(ids)]
        self.label, self.counted = np.arange(len(ids)), np.zeros(len(ids), dtype=np.int64)

    def visit(self, ids: np.ndarray, unit: np.ndarray, copies: np.ndarray) -> tuple[list, list]:
        """Links counted for the visitors, and a forest of links."""
        first, second = self.index.ranked(unit)
        limit = self.index.reach(first, second)
        home_first, home_second = first.argmin(axis=1), second.argmin(axis=1)
        links, forest = np.zeros(len(ids), dtype=np.int64), []
        for at, cell in enumerate(self.cells.tolist()):
            low, high = self.bounds[at], self.bounds[at + 1]
            visitors = np.flatnonzero(first[:, cell // self.index.codes] + second[:, cell % self.index.codes] <= limit)
            if not len(visitors):
                continue
            close = unit[visitors] @ self.unit[low:high].T >= COSINE
            close &= ids[visitors][:, None] != self.ids[low:high]
            if not close.any():
                continue
            links[visitors] += close @ self.copies[low:high]
            # A pair that each finds from its side is counted there; else the visitor counts for both.
            back = self.first[low:high, home_first[visitors]] + self.second[low:high, home_second[visitors]] <= self.reach[low:high, None]
            self.counted[low:high] += (copies[visitors][:, None] * (close & ~back.T)).sum(axis=0)
            for row in np.flatnonzero(close.any(axis=1)).tolist():
                found = low + np.flatnonzero(close[row])
                names, one = np.unique(self.label[found], return_index=True)
                forest += [(int(ids[visitors[row]]), int(self.ids[found[i]])) for i in one]
                for name in names[1:]:
                    self.label[self.label == name] = names[0]
        return np.stack([ids[links > 0], links[links > 0]], axis=1).tolist(), forest

    def counts(self) -> list:
        return [[int(i), int(n)] for i, n in zip(self.ids, self.counted, strict=True) if n]


def compare_blocks(classes: DataFrame, indexes: dict[int, MultiIndex]) -> DataFrame:
    """(id, links, a, b): links counted for ``id`` by one block, or a link of its spanning forest."""
    spark = classes.sparkSession
    shared = spark.sparkContext.broadcast((indexes, uuid.uuid4().hex))

    def own_indexes() -> dict[int, MultiIndex]:
        return worker_state("multi-index", shared.value[1], lambda: dict(shared.value[0]))

    def index_of(size: int) -> MultiIndex:
        """A length that the sample lacks is rare; its vectors share one cell."""
        held = own_indexes()
        if size not in held:
            held[size] = MultiIndex(np.zeros((1, size)), 1)
        return held[size]

    def place(batches):
        for batch in batches:
            sizes, raw = np.asarray(batch.column(1)), batch.column(2).to_pylist()
            home, opened = np.zeros(len(raw), dtype=np.int32), [None] * len(raw)
            for size in np.unique(sizes).tolist():
                index = index_of(size)
                for at in np.array_split(np.flatnonzero(sizes == size), -(-int((sizes == size).sum()) // 1000)):
                    unit = units([raw[i] for i in at], size)
                    home[at], blocks = index.opened(unit)
                    for i, row in zip(at.tolist(), blocks, strict=True):
                        opened[i] = np.flatnonzero(row).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(home), pa.array(opened, pa.list_(pa.int32()))], names=["id", "size", "vector", "copies", "home", "opened"])

    placed = settle(classes.mapInArrow(place, "id long, size int, vector binary, copies long, home int, opened array<int>"), "cells")
    # One row for each block.
    chunks = placed.groupBy("size", F.col("home").alias("block")).agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("chunks"))
    payload = ["id", "vector", "copies"]
    stored = placed.withColumn("block", F.col("home")).join(chunks, ["size", "block"]).select("size", "block", F.pmod(F.xxhash64("id"), F.col("chunks")).cast("int").alias("chunk"), F.lit(0).alias("asks"), *payload)
    asking = placed.select("size", F.explode("opened").alias("block"), *payload).join(chunks, ["size", "block"])
    asking = asking.select("size", "block", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(1).alias("asks"), *payload)

    def compare(batches):
        key, held, waiting = None, None, []
        for batch in batches:
            keys = np.stack([np.asarray(batch.column(k)) for k in range(4)], axis=1)
            cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), len(keys)]
            for low, high in zip(cuts, cuts[1:], strict=False):
                if low == high:
                    continue
                size = int(keys[low][0])
                if tuple(keys[low][:3]) != key:
                    yield from _counts(held.counts() if held else [], [])
                    key, held, waiting = tuple(keys[low][:3]), None, []
                part = batch.slice(low, high - low)
                rows = (np.asarray(part.column(4)), units(part.column(5).to_pylist(), size), np.asarray(part.column(6)))
                if keys[low][3] == 0:
                    waiting.append(rows)
                    continue
                if held is None and waiting:
                    held, waiting = HeldBlock(index_of(size), *(np.concatenate(x) for x in zip(*waiting, strict=True))), []
                for at in range(0, part.num_rows if held else 0, 1024):
                    yield from _counts(*held.visit(*(x[at : at + 1024] for x in rows)))
        yield from _counts(held.counts() if held else [], [])

    rows = stored.unionByName(asking).repartition("size", "block", "chunk").sortWithinPartitions("size", "block", "chunk", "asks", "id")
    return rows.mapInArrow(compare, "id long, links long, a long, b long")


def _counts(counts: list, forest: list):
    if counts or forest:
        blank_c, blank_f = [None] * len(counts), [None] * len(forest)
        columns = ([c[0] for c in counts] + blank_f, [c[1] for c in counts] + blank_f, blank_c + [f[0] for f in forest], blank_c + [f[1] for f in forest])
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["id", "links", "a", "b"])


def train(classes: DataFrame) -> dict[int, MultiIndex]:
    """An index for each length of vectors in a sample of bounded size."""
    total = classes.count()
    codes = int(np.clip(round((total / CELL) ** 0.5), 2, MOST_CODES))
    bound = max(SAMPLE, SAMPLE_EACH * codes)
    draw = F.pmod(F.xxhash64(F.lit("codebook"), "id"), F.lit(1 << 40))
    drawn = classes.where(draw <= int(min(1.0, 2 * bound / max(1, total)) * (1 << 40))).orderBy(draw, "id").limit(bound).select("size", "vector").collect()
    by_size: dict[int, list[bytes]] = {}
    for row in drawn:
        by_size.setdefault(row["size"], []).append(bytes(row["vector"]))
    # Codewords by the share of a length; ids that repeat with other vectors need no care here.
    return {size: MultiIndex(units(raw, size), max(1, round(codes * (len(raw) / len(drawn)) ** 0.5))) for size, raw in by_size.items()}


def near_duplicate_vectors(vectors: DataFrame) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row."""
    good = usable(vectors)
    classes = settle(good.groupBy("d1", "d2").agg(F.min("vec_id").alias("id"), F.count("*").alias("copies"), F.first("size").alias("size"), F.first("vector").alias("vector")), "vector-classes")
    found = settle(compare_blocks(classes.select("id", "size", "vector", "copies"), train(classes)), "vector-links")
    counted = found.where("id IS NOT NULL").groupBy("id").agg(F.sum("links").alias("links"))
    joined = components(found.where("a IS NOT NULL").select("a", "b"))
    named = classes.drop("vector", "size").join(counted, "id", "left").join(joined.withColumnRenamed("v", "id"), "id", "left")
    entries = settle(named.select("d1", "d2", "copies", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).cast("long").alias("links"), F.coalesce("component", "id").alias("component")), "vector-names")
    named_rows = look_up(good.select("vec_id", "d1", "d2"), entries, ["d1", "d2"], "copies", "class")
    linked = named_rows.select("vec_id", F.col("class.links").alias("n_links"), F.col("class.component").alias("component_id"))
    ids = vectors.select(F.col("vec_id").cast("long").alias("vec_id"))
    once = linked.groupBy("vec_id").agg(F.max("n_links").alias("n_links"), F.min("component_id").alias("component_id"))
    whole = ids.join(once, "vec_id", "left")
    return whole.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


SQL = """
WITH RECURSIVE good AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b ON a.vec_id <> b.vec_id AND len(a.v) = len(b.v) WHERE list_cosine_similarity(a.v, b.v) >= 0.9),
reach AS (SELECT vec_id AS a, vec_id AS b FROM embeddings UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
least_reached AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a),
counted AS (SELECT a, count(*) AS n FROM links GROUP BY a)
SELECT e.vec_id, CAST(coalesce(c.n, 0) AS BIGINT) AS n_links, r.component_id, e.vec_id = r.component_id AS kept
FROM embeddings e JOIN least_reached r ON e.vec_id = r.a LEFT JOIN counted c ON e.vec_id = c.a
"""
