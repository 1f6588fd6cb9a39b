"""Near-duplicate documents by a chosen-path set similarity join.

A document is its set of word shingles. Its trace holds minwise tokens of the
set: one for each of ``COORDINATES`` hash functions. A tree branches all
documents by a token, each branch by a token that the path so far selects, and
so on; documents that take the same path meet in a node. The first levels, at
which nodes are still large, are passed in one step. A node with at most
``NODE`` documents is compared exhaustively, by traces. A larger one is
compared with ``NODE`` of its documents, and those that are like none of them
branch again, each by ``BRANCHES`` tokens that the node selects, in another
round; rounds end when no node has documents left. Independent trees repeat
this; their number follows from the depth, the finite trace and the target
recall.

That yields coarse clusters, and every cluster is then resolved exactly on the
full sets, by an inverted index of its shingles. Sets that are known to be
connected are not compared again. No list of pairs is ever made.

Hot groups: documents with equal sets are combined into one before anything
else; tasks replace very similar documents of one path by one of them before
the shuffle. A cluster larger than ``CHUNK`` is cut in chunks. All chunks are
compared with the first; that splits the cluster into components, and then
only chunks of different components are compared, so that a cluster of near
copies costs as many rows as it has documents. Each task is bounded.

Defined cases: words are runs without ASCII white space, A-Z lower-cased; a
text with fewer words than a shingle has one shingle, all its words; a null
text, or one without words, has the empty set and is linked with nothing; a
row with a null ``doc_id`` is linked with nothing; rows that repeat a
``doc_id`` are reported as often, each by its own text; an empty table gives
no rows; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .encoding import slices
from .graph import components
from .shared import look_up, settle, stateless_worker

#: Defaults where no contract says otherwise: words of a shingle, similarity as a fraction.
SHINGLE_WORDS, SIMILARITY = 5, (80, 100)
#: Hash functions; chance that a pair at the similarity is missed by all trees.
COORDINATES, MISS = 64, 1e-4
#: Documents that meet by chance shrink by about this factor a level; documents of a node from which the first step goes a level deeper.
BRANCHING, ENOUGH = 60, 128
#: Estimated similarity from which a pair is looked at exactly; from which a task lets one document stand for another; from which a node does.
LOOK, ABSORB, FOLLOW = 0.58, 0.93, 0.85
#: Documents of a node that are compared exhaustively; tokens by which each of the others branches.
NODE, BRANCHES = 1024, 4
#: Documents, and shingles, of a chunk.
CHUNK, CHUNK_SHINGLES = 1024, 2_000_000

_MIX = np.uint64(0x9E3779B97F4A7C15)


def shingle_sets(texts: pa.Array, words_each: int) -> Iterator[np.ndarray]:
    """Sorted 64-bit hashes of the distinct shingles of each text."""
    for part in slices(texts):
        lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(part, "")))
        found = lists.flatten()
        full = np.asarray(pc.greater(pc.binary_length(found), 0))
        owner = np.repeat(np.arange(len(part)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))[full]
        numbered = found.filter(pa.array(full)).dictionary_encode()
        named = np.fromiter((xxhash.xxh64_intdigest(w) for w in numbered.dictionary.cast(pa.binary()).to_pylist()), dtype=np.uint64, count=len(numbered.dictionary))
        hashes = named[np.asarray(numbered.indices)] if len(named) else named
        ends = np.cumsum(np.bincount(owner, minlength=len(part)))
        width = max(1, min(words_each, len(hashes)))
        rolled = _rolled(hashes, width)
        for low, high in zip(np.append(0, ends[:-1]).tolist(), ends.tolist(), strict=True):
            if high - low >= width == words_each:
                yield np.unique(rolled[low : high - width + 1])
            else:
                yield _rolled(hashes[low:high], high - low) if high > low else hashes[:0]


def _rolled(hashes: np.ndarray, width: int) -> np.ndarray:
    """One number for every ``width`` neighbours."""
    with np.errstate(over="ignore"):
        out = np.full(max(0, len(hashes) - width + 1), width, dtype=np.uint64)
        for i in range(width):
            out = (out ^ hashes[i : len(hashes) - width + 1 + i]) * _MIX
            out ^= out >> np.uint64(31)
    return out


def _odd(seed: int, count: int) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(f"{seed}/{i}") | 1 for i in range(count)], dtype=np.uint64)


_FACTORS, _OFFSETS = _odd(1, COORDINATES), _odd(2, COORDINATES)


def minwise(shingles: np.ndarray) -> np.ndarray:
    """One token for each hash function."""
    least = np.full(COORDINATES, np.iinfo(np.uint64).max)
    with np.errstate(over="ignore"):
        for low in range(0, len(shingles), 1024):
            part = shingles[low : low + 1024, None] * _FACTORS + _OFFSETS
            np.minimum(least, part.min(axis=0), out=least)
    return least


def missed(depth: int, trees: int, similarity: float) -> float:
    """Chance that a pair is seen by no tree: the mean over how many of the tokens, which all trees share, agree."""
    agree = np.arange(COORDINATES + 1)
    logs = np.array([math.lgamma(COORDINATES + 1) - math.lgamma(a + 1) - math.lgamma(COORDINATES - a + 1) for a in agree])
    chance = np.exp(logs + agree * math.log(similarity) + (COORDINATES - agree) * math.log1p(-similarity)) if similarity < 1 else (agree == COORDINATES).astype(float)
    seen = agreement_of(agree / COORDINATES) >= LOOK
    return float((chance * np.where(seen, (1 - (agree / COORDINATES) ** depth) ** trees, 1.0)).sum())


def depth_and_trees(documents: int, similarity: tuple[int, int] = SIMILARITY, miss: float = MISS) -> tuple[int, int]:
    """Levels of the first step, and trees. What ``LOOK`` alone misses no number of trees finds."""
    depth, part = max(1, math.ceil(math.log(max(2, documents) / ENOUGH) / math.log(BRANCHING))), similarity[0] / similarity[1]
    target = miss + missed(depth, 1 << 20, part)
    trees = 1
    while missed(depth, trees, part) > target:
        trees += 1
    return depth, trees


def paths(tokens: np.ndarray, depth: int, trees: int) -> np.ndarray:
    """The node, as a 64-bit number, that a trace reaches in each tree."""
    with np.errstate(over="ignore"):
        node = (np.arange(1, trees + 1, dtype=np.uint64)) * _MIX
        for _ in range(depth):
            node ^= node >> np.uint64(29)
            node *= np.uint64(0xBF58476D1CE4E5B9)
            chosen = (node >> np.uint64(40)) % np.uint64(COORDINATES)
            node = (node ^ tokens[chosen] ^ (chosen << np.uint64(50))) * _MIX
    return node


def traces(docs: DataFrame, words_each: int, depth: int, trees: int) -> DataFrame:
    """(doc_id, n_shingles, d1, d2, trace): set size, 128-bit digest, and nodes followed by one byte of each token."""

    def trace(batches):
        stateless_worker("near_dedup")
        for batch in batches:
            sizes, first, second, out = [], [], [], []
            for shingles in shingle_sets(batch.column(1), words_each):
                digest = xxhash.xxh3_128_digest(shingles.tobytes())
                sizes.append(len(shingles))
                first.append(int.from_bytes(digest[:8], "little", signed=True))
                second.append(int.from_bytes(digest[8:], "little", signed=True))
                if len(shingles):
                    tokens = minwise(shingles)
                    out.append(paths(tokens, depth, trees).tobytes() + (tokens >> np.uint64(20)).astype(np.uint8).tobytes())
                else:
                    out.append(None)
            arrays = [batch.column(0), pa.array(sizes, pa.int64()), pa.array(first, pa.int64()), pa.array(second, pa.int64()), pa.array(out, pa.binary())]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "n_shingles", "d1", "d2", "trace"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(trace, "doc_id long, n_shingles long, d1 long, d2 long, trace binary")


def agreement_of(hits):
    """Estimated similarity from a share of equal bytes, free of chance hits."""
    return (hits - 1 / 256) / (1 - 1 / 256)


def agreement(one: np.ndarray, many: np.ndarray) -> np.ndarray:
    """Estimated similarity of one trace and many."""
    return agreement_of((many == one).mean(axis=1))


def exhaustive_links(ids: np.ndarray, tails: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the pairs of a node that look similar."""
    group, links = np.arange(len(ids)), []
    for i in range(len(ids) - 1):
        near = i + 1 + np.flatnonzero(agreement(tails[i], tails[i + 1 :]) >= LOOK)
        for j in near[group[near] != group[i]]:
            if group[j] != group[i]:
                links.append((int(ids[i]), int(ids[j])))
                group[group == group[j]] = group[i]
    return links


class Node:
    """The documents of one node, as they arrive; gives links and what branches on.

    Up to ``limit`` documents are held and compared with all others. Once there
    are more, a document that one held is very like stands aside for it, and
    documents beyond the limit that are like none of those held go on.
    """

    def __init__(self, number: int, limit: int = NODE):
        self.number, self.limit = number, limit
        self.ids, self.tails, self.group = np.zeros(0, dtype=np.int64), np.zeros((0, COORDINATES), dtype=np.uint8), np.zeros(0, dtype=np.int64)
        self.large = False
        self.links: list[tuple[int, int]] = []

    def _joined(self, i: int, near: np.ndarray) -> None:
        """Link document ``i`` of those held with the groups of ``near``; a forest of the links is kept."""
        for j in near[self.group[near] != self.group[i]]:
            if self.group[j] != self.group[i]:
                self.links.append((int(self.ids[i]), int(self.ids[j])))
                self.group[self.group == self.group[j]] = self.group[i]

    def _hold(self, one: int, tail: np.ndarray, like: np.ndarray) -> None:
        self.ids, self.tails, self.group = np.append(self.ids, one), np.concatenate([self.tails, tail[None]]), np.append(self.group, one)
        self._joined(len(self.ids) - 1, np.flatnonzero(like >= LOOK))

    def _thin(self) -> None:
        """Documents that an earlier one stands for leave; their links stay."""
        stays = np.ones(len(self.ids), dtype=bool)
        for i in range(len(self.ids)):
            if stays[i]:
                later = i + 1 + np.flatnonzero(agreement(self.tails[i], self.tails[i + 1 :]) >= FOLLOW)
                stays[later] = False
        self.ids, self.tails, self.group = self.ids[stays], self.tails[stays], self.group[stays]

    def add(self, ids: np.ndarray, tails: np.ndarray) -> np.ndarray:
        """Take documents in; gives the places of those that branch on."""
        onward = []
        for place, (one, tail) in enumerate(zip(ids, tails, strict=True)):
            like = agreement(tail, self.tails)
            if self.large and len(like) and like.max() >= FOLLOW:
                self.links.append((int(one), int(self.ids[like.argmax()])))
                self._meet(int(one), np.flatnonzero(like >= LOOK))
                continue
            if len(self.ids) >= self.limit and not self.large:
                self.large = True
                self._thin()
                like = agreement(tail, self.tails)
            if len(self.ids) < self.limit:
                self._hold(int(one), tail, like)
                continue
            near = np.flatnonzero(like >= LOOK)
            if len(near):
                self.links.append((int(one), int(self.ids[near[0]])))
                self._meet(int(one), near)
            onward.append(place)
        return np.array(onward, dtype=np.int64)

    def _meet(self, one: int, near: np.ndarray) -> None:
        """Groups that a passing document is like are one."""
        first = near[0]
        for j in near[self.group[near] != self.group[first]]:
            if self.group[j] != self.group[first]:
                self.links.append((one, int(self.ids[j])))
                self.group[self.group == self.group[j]] = self.group[first]

    def children(self, tails: np.ndarray) -> np.ndarray:
        """(documents, BRANCHES): the nodes to which documents branch, by tokens that this node selects."""
        with np.errstate(over="ignore"):
            seed = np.array([self.number], dtype=np.int64).view(np.uint64) * _MIX
            chosen = np.random.default_rng(int(seed[0])).choice(COORDINATES, BRANCHES, replace=False).astype(np.uint64)
            named = (seed ^ (chosen[None] << np.uint64(8)) ^ tails[:, chosen.astype(np.int64)].astype(np.uint64)) * np.uint64(0xBF58476D1CE4E5B9)
            return ((named ^ (named >> np.uint64(31))) * _MIX).view(np.int64)


def candidate_links(sets: DataFrame, trees: int, limit: int = NODE) -> DataFrame:
    """(a, b): links of documents that meet in a node and look similar; ``sets`` has doc_id and trace."""

    def spread(batches):
        """Rows (node, doc_id, tail), and links for documents that another one stands for."""
        for batch in batches:
            ids = np.array(batch.column(0).to_pylist(), dtype=np.int64)
            if not len(ids):
                continue
            whole = np.frombuffer(b"".join(batch.column(1).to_pylist()), dtype=np.uint8).reshape(len(ids), -1)
            nodes = np.ascontiguousarray(whole[:, : 8 * trees]).view(np.int64)
            tails = whole[:, 8 * trees :]
            for tree in range(trees):
                order = np.argsort(nodes[:, tree], kind="stable")
                sorted_nodes = nodes[order, tree]
                starts = np.flatnonzero(np.concatenate([[True], sorted_nodes[1:] != sorted_nodes[:-1]]))
                keep = np.ones(len(ids), dtype=bool)
                linked: list[tuple[int, int]] = []
                sizes = np.diff(np.append(starts, len(ids)))
                for start, size in zip(starts[sizes > 3], sizes[sizes > 3], strict=True):
                    members = order[start : start + size]
                    members = np.roll(members, -(tree * size // trees))  # another one stands in each tree
                    waiting = np.ones(size, dtype=bool)
                    for i in range(size):
                        if waiting[i]:
                            like = (agreement(tails[members[i]], tails[members]) >= ABSORB) & waiting
                            like[i] = False
                            linked += [(int(ids[members[j]]), int(ids[members[i]])) for j in np.flatnonzero(like)]
                            keep[members[like]] = False
                            waiting[like] = False
                kept = np.flatnonzero(keep)
                values = [pa.array(nodes[kept, tree]), pa.array(ids[kept]), pa.array([t.tobytes() for t in tails[kept]], pa.binary()), pa.nulls(len(kept), pa.int64())]
                yield pa.RecordBatch.from_arrays(values, names=["node", "a", "tail", "b"])
                if linked:
                    pairs = np.array(linked)
                    # Their node is a name of their own, so they spread evenly.
                    values = [pa.array(pairs[:, 0]), pa.array(pairs[:, 0]), pa.nulls(len(pairs), pa.binary()), pa.array(pairs[:, 1])]
                    yield pa.RecordBatch.from_arrays(values, names=["node", "a", "tail", "b"])

    def compare(batches):
        """Links, and rows of the next round, which have no ``b``."""
        node = None
        for batch in batches:
            passed = pc.is_null(batch.column(2))
            if pc.any(passed).as_py():
                known = batch.filter(passed)
                yield _round_rows(known.column(1), known.column(3), None, None)
                batch = batch.filter(pc.invert(passed))
            if not batch.num_rows:
                continue
            numbers, ids = (np.asarray(batch.column(k)) for k in (0, 1))
            tails = np.frombuffer(b"".join(batch.column(2).to_pylist()), dtype=np.uint8).reshape(len(ids), -1)
            cuts = [0, *(np.flatnonzero(numbers[1:] != numbers[:-1]) + 1).tolist(), len(ids)]
            links: list[tuple[int, int]] = []
            for low, high in zip(cuts, cuts[1:], strict=False):
                if node is None or node.number != numbers[low]:
                    if high < len(ids) and high - low <= limit:
                        # Nothing of this node came before, and nothing follows.
                        links += exhaustive_links(ids[low:high], tails[low:high])
                        continue
                    links += node.links if node else []
                    node = Node(int(numbers[low]), limit)
                onward = node.add(ids[low:high], tails[low:high]) + low
                if len(onward):
                    children = node.children(tails[onward])
                    again = np.repeat(onward, BRANCHES)
                    yield _round_rows(pa.array(ids[again]), pa.nulls(len(again), pa.int64()), pa.array(children.ravel()), pa.array([tails[i].tobytes() for i in again], pa.binary()))
            links += node.links
            node.links = []
            if links:
                flat = np.array(links, dtype=np.int64)
                yield _round_rows(pa.array(flat[:, 0]), pa.array(flat[:, 1]), None, None)

    rows, found = sets.select("doc_id", "trace").mapInArrow(spread, "node long, a long, tail binary, b long"), []
    while True:
        dealt = rows.repartition("node").sortWithinPartitions("node", "a")
        done = settle(dealt.mapInArrow(compare, "a long, b long, node long, tail binary"), "node-links")
        found.append(done.where("b IS NOT NULL").select("a", "b"))
        onward = done.where("b IS NULL").select("node", "a", "tail", "b")
        if onward.isEmpty():
            return reduce(DataFrame.unionByName, found)
        rows = onward


def _round_rows(a: pa.Array, b: pa.Array, node: pa.Array | None, tail: pa.Array | None) -> pa.RecordBatch:
    blank = [pa.nulls(len(a), kind) if own is None else own for own, kind in ((node, pa.int64()), (tail, pa.binary()))]
    return pa.RecordBatch.from_arrays([a, b, *blank], names=["a", "b", "node", "tail"])


def _pairs(links: list[tuple[int, int]]) -> pa.RecordBatch:
    flat = np.array(links, dtype=np.int64)
    return pa.RecordBatch.from_arrays([pa.array(flat[:, 0]), pa.array(flat[:, 1])], names=["a", "b"])


class ClusterResolver:
    """Exact links, up to connectivity, among the sets of one cluster.

    Each set in turn is compared with those after it that are not in its
    component yet: postings of its shingles give all intersection sizes at
    once. Where everything is linked, the first set settles the cluster.
    """

    def __init__(self, sets: list[np.ndarray], similarity: tuple[int, int] = SIMILARITY, known: list[int | None] | None = None):
        self.part, self.whole = similarity
        self.sizes = np.array([len(s) for s in sets])
        self.ends = np.concatenate([[0], np.cumsum(self.sizes)])
        _, self.shingle, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        order = np.argsort(self.shingle, kind="stable")
        self.owner = np.repeat(np.arange(len(sets)), self.sizes)[order]
        self.bounds = np.concatenate([[0], np.cumsum(counts)])
        self.group = np.arange(len(sets))
        first: dict[int, int] = {}
        for i, name in enumerate(known or ()):
            if name is not None:
                self.group[i] = first.setdefault(name, i)

    def overlaps(self, one: int) -> np.ndarray:
        """Intersection sizes of one set and all."""
        own = self.shingle[self.ends[one] : self.ends[one + 1]]
        starts, counts = self.bounds[own], self.bounds[own + 1] - self.bounds[own]
        shared = counts > 1
        starts, counts = starts[shared], counts[shared]
        place = np.repeat(starts - np.concatenate([[0], np.cumsum(counts)[:-1]]), counts) + np.arange(counts.sum())
        return np.bincount(self.owner[place], minlength=len(self.sizes))

    def resolve(self) -> np.ndarray:
        """Component number of each set."""
        for i in range(len(self.sizes)):
            if not (self.group[i + 1 :] != self.group[i]).any():
                continue
            overlap = self.overlaps(i)
            linked = self.whole * overlap >= self.part * (self.sizes[i] + self.sizes - overlap)
            linked[: i + 1] = False
            for j in np.flatnonzero(linked & (self.group != self.group[i])):
                if self.group[j] != self.group[i]:
                    self.group[self.group == self.group[j]] = self.group[i]
        return self.group


def _in_chunks(members: DataFrame) -> DataFrame:
    """Add ``chunk`` and ``chunks``, of bounded size, to the parts of clusters (cluster, part, v, n_shingles)."""
    parts = F.greatest(F.ceil(F.count("*") / CHUNK), F.ceil(F.sum("n_shingles") / CHUNK_SHINGLES)).cast("int")
    sizes = members.groupBy("cluster", "part").agg(parts.alias("chunks"))
    placed = members.join(sizes, ["cluster", "part"])
    return placed.withColumn("chunk", F.pmod(F.xxhash64("v"), F.col("chunks")).cast("int"))


def resolve_units(docs: DataFrame, units: DataFrame, words_each: int, similarity: tuple[int, int]) -> DataFrame:
    """(a, b): exact links up to connectivity among the documents of each unit (cluster, i, j, v, part).

    Documents of one ``part`` that is not null are known to be connected.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("v"), "text")
    # Shuffled at every size: how many documents are in clusters has no bound.
    rows = texts.join(units.hint("shuffle_hash"), "v").select("cluster", "i", "j", "v", "part", "text")

    def resolve(batches):
        stateless_worker("near_dedup")
        unit, ids, known, sets, links = None, [], [], [], []

        def finish():
            if len(ids) < 2:
                return []
            group = ClusterResolver(sets, similarity, known).resolve()
            return [(ids[g], ids[i]) for i, g in enumerate(group.tolist()) if ids[g] != ids[i]]

        for batch in batches:
            heads = zip(*(batch.column(k).to_pylist() for k in range(5)), strict=True)
            for (*key, v, part), shingles in zip(heads, shingle_sets(batch.column(5), words_each), strict=True):
                if key != unit:
                    links += finish()
                    unit, ids, known, sets = key, [], [], []
                if not len(shingles) or (ids and ids[-1] == v and np.array_equal(sets[-1], shingles)):
                    continue
                ids.append(v)
                known.append(part)
                sets.append(shingles)
            if links:
                yield _pairs(links)
                links = []
        links += finish()
        if links:
            yield _pairs(links)

    return rows.repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j", "v").mapInArrow(resolve, "a long, b long")


def resolve_clusters(docs: DataFrame, clusters: DataFrame, words_each: int, similarity: tuple[int, int]) -> DataFrame:
    """(v, component): exact components, from clusters (v, cluster, n_shingles) of documents.

    First every chunk of a cluster meets the first chunk. In a cluster of
    several chunks, the components found so far are parts; the largest part is
    compared with the others, and the others with each other, but no part with
    itself.
    """
    whole = _in_chunks(clusters.withColumn("part", F.lit(0).cast("long")))
    rivals = F.when(F.col("chunk") == 0, F.sequence(F.lit(0), F.col("chunks") - 1)).otherwise(F.array("chunk"))
    first = whole.select("cluster", F.lit(0).alias("i"), F.explode(rivals).alias("j"), "v", F.lit(None).cast("long").alias("part"))
    links = settle(resolve_units(docs, first, words_each, similarity), "cluster-links")
    large = settle(whole.where("chunks > 1").select("cluster", "v", "n_shingles"), "large-clusters")
    if large.isEmpty():
        return components(links)
    found = components(links)
    named = large.join(found, "v", "left").select("cluster", "v", "n_shingles", F.coalesce("component", "v").alias("part"))
    parts = named.groupBy("cluster", "part").agg(F.count("*").alias("n"))
    largest = parts.groupBy("cluster").agg(F.max(F.struct("n", "part")).alias("top"), F.count("*").alias("parts")).where("parts > 1")
    split = named.join(largest.select("cluster", F.col("top.part").alias("main")), "cluster").withColumn("known", F.col("part"))
    others = _in_chunks(split.where("part != main").withColumn("part", F.lit(0).cast("long")))
    mains = _in_chunks(split.where("part = main").withColumn("part", F.lit(1).cast("long")))
    # Chunks of the others come first, in both sides of a unit; chunks of the main part meet only those.
    counts = others.select("cluster", F.col("chunks").alias("others")).distinct()
    lower = others.withColumn("own", F.sequence(F.lit(0), F.col("chunks") - 1))
    pairs = F.transform("own", lambda o: F.struct(F.least(o, F.col("chunk")).alias("i"), F.greatest(o, F.col("chunk")).alias("j")))
    among = lower.select("cluster", F.explode(pairs).alias("u"), "v", "known")
    sides = mains.select("cluster", F.col("chunk").alias("main_chunk"), "v", "known").join(counts, "cluster")
    of_main = sides.select("cluster", F.explode(F.transform(F.sequence(F.lit(0), F.col("others") - 1), lambda o: F.struct(o.alias("i"), (-F.col("main_chunk") - 1).alias("j")))).alias("u"), "v", "known")
    main_counts = mains.select("cluster", F.col("chunks").alias("mains")).distinct()
    to_main = others.join(main_counts, "cluster").select("cluster", F.explode(F.transform(F.sequence(F.lit(0), F.col("mains") - 1), lambda m: F.struct(F.col("chunk").alias("i"), (-m - 1).alias("j")))).alias("u"), "v", "known")
    units = reduce(DataFrame.unionByName, [among, of_main, to_main]).select("cluster", "u.i", "u.j", "v", F.col("known").alias("part"))
    more = settle(resolve_units(docs, units, words_each, similarity), "cluster-links")
    return components(links.unionByName(more))


def near_duplicates(docs: DataFrame, words_each: int = SHINGLE_WORDS, similarity: tuple[int, int] = SIMILARITY) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row."""
    depth, trees = depth_and_trees(docs.count(), similarity)
    traced = settle(traces(docs, words_each, depth, trees), "traces")
    linkable = traced.where(F.col("trace").isNotNull() & F.col("doc_id").isNotNull())
    sets = settle(linkable.groupBy("d1", "d2").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"), F.min("n_shingles").alias("n_shingles"), F.min_by("trace", "doc_id").alias("trace")), "sets")
    coarse = components(candidate_links(sets, trees)).withColumnRenamed("component", "cluster")
    sized = coarse.join(sets.groupBy(F.col("doc_id").alias("v")).agg(F.sum("n_shingles").alias("n_shingles")), "v")
    exact = resolve_clusters(docs, settle(sized, "clusters"), words_each, similarity)
    named = sets.select("d1", "d2", "copies", F.col("doc_id").alias("v")).join(exact, "v", "left")
    entries = settle(named.select("d1", "d2", "copies", F.coalesce("component", "v").alias("component")), "classes")
    found = look_up(traced.select("doc_id", "n_shingles", "d1", "d2"), entries, ["d1", "d2"], "copies", "class")
    own = F.when(F.col("n_shingles") == 0, F.col("doc_id")).otherwise(F.coalesce(F.col("class.component"), F.col("doc_id")))
    whole = found.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), own).alias("component_id"))
    return whole.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one_each(docs: DataFrame, words_each: int = SHINGLE_WORDS, similarity: tuple[int, int] = SIMILARITY) -> DataFrame:
    """The rows of ``docs`` that stay, one document of each group; all columns as they are. A document with several texts stays if one of them does."""
    judged = near_duplicates(docs, words_each, similarity).groupBy(F.col("doc_id").alias("__dropped_id")).agg(F.max("kept").alias("__kept"))
    dropped = judged.where("NOT __kept").select("__dropped_id")
    return docs.join(dropped, docs["doc_id"].cast("long") == dropped["__dropped_id"], "left_anti")


#: Pairs of words; the set of a text with one word is that word.
SQL = r"""
WITH RECURSIVE words AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
sets AS (SELECT doc_id, CASE WHEN len(w) < 2 THEN w ELSE list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) END AS s FROM words),
items AS (SELECT doc_id, len(s) AS n, unnest(s) AS item FROM sets),
links AS (SELECT a.doc_id AS a, b.doc_id AS b FROM items a JOIN items b ON a.item = b.item AND a.doc_id <> b.doc_id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
least_reached AS (SELECT a, min(b) AS component_id FROM reach GROUP BY a)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, component_id, s.doc_id = component_id AS kept FROM sets s JOIN least_reached ON s.doc_id = a
"""
