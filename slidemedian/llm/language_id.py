"""Language identification by segmentation-marginalised unigram pieces.

Each language has a probability for every piece of a fixed public vocabulary.
The probability of a word is the sum over all ways to cut it into pieces,
computed by a forward pass; a text's score is the product over its words. The
piece probabilities come from expectation maximisation over the same forward
pass and its backward twin, on a bounded sample of labelled texts.

Words are runs between white space, lower-cased, with the characters that are
no letters taken out. Arrow numbers the different words of a slice of texts;
the passes run on thousands of words in lockstep, all languages at once, and
workers remember words. A word may be of any length: the pass carries the
masses of its last prefixes on, scaled, from one run of letters to the next.

A text that fits no learned language has fewer nats a letter than any labelled
one: ``keep_known`` rejects it by a floor that held-out labelled texts set.

Defined cases: a text that is null or has no letter is ``und`` with score 0;
repeated rows are judged alike; ties go to the language that sorts first; with
no labelled text at all every row is ``und``; an empty table gives no rows.
"""

from __future__ import annotations

import uuid
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .encoding import WordMemo, slices
from .shared import bucket_of, worker_state

#: Bound of the training sample: labelled texts, over all languages together, at least so many for each, and the longest text that is drawn, in characters.
SAMPLE_TEXTS, LEAST_TEXTS, SAMPLE_CHARS = 1600, 40, 200_000
#: Letters that a pass takes before it scales its masses; longest run of letters in training; rounds of estimation.
RUN, TRAINING_RUN, ROUNDS = 32, 512, 3
#: Probability of a letter that no piece covers; weight of the languages' mean in each language's counts.
UNCOVERED, SMOOTHING = 1e-7, 0.02
#: Words that a worker remembers (some 60 bytes each); words in one pass.
MEMO_WORDS, PASS_WORDS = 250_000, 4000
#: Log-odds for each word are scaled by this in the reported score, which is else always 0 or 1.
TEMPER = 0.25
#: One in so many sampled texts sets the floor; letters that such a text needs; factor and nats that a text may lie below it.
FLOOR_SHARE, FLOOR_LETTERS, FLOOR_MARGIN, FLOOR_SLACK = 8, 200, 1.25, 30.0

_PRIME = np.uint64(0x9E3779B97F4A7C15)
START = "▁"


def public_pieces(path: str) -> list[str]:
    """The lower-cased text pieces of a sentencepiece vocabulary, each once."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = (model.id_to_piece(i).lower() for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i)))
    return sorted({p for p in texts if p and all(c.isalpha() or c == START for c in p)})


def _codes(words: list[str]) -> np.ndarray:
    """One row of code points for each word, 0 after its end."""
    width = max(map(len, words))
    flat = np.frombuffer("".join(w.ljust(width, "\0") for w in words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    return flat.reshape(len(words), width).astype(np.uint64)


def _hashes(codes: np.ndarray, longest: int):
    """Yield (length, hashes of the substrings of that length by their start)."""
    with np.errstate(over="ignore"):
        running = np.zeros_like(codes)
        for length in range(1, min(longest, codes.shape[1]) + 1):
            starts = codes.shape[1] - length + 1
            running = (running[:, :starts] ^ codes[:, length - 1 :]) * _PRIME
            running ^= running >> np.uint64(29)
            yield length, running


class Segmenter:
    """Piece numbers of all substrings of a batch of words, and passes over them."""

    def __init__(self, pieces: list[str]):
        self.size, self.longest = len(pieces), max(map(len, pieces))
        hashes = np.zeros(len(pieces), dtype=np.uint64)
        for size in {len(p) for p in pieces}:
            at = [i for i, p in enumerate(pieces) if len(p) == size]
            for length, values in _hashes(_codes([pieces[i] for i in at]), size):
                if length == size:
                    hashes[at] = values[:, 0]
        order = np.argsort(hashes)
        self.sorted, self.piece = hashes[order], order
        # Most substrings are no piece; their leading bits tell.
        self.maybe = np.zeros(1 << 20, dtype=bool)
        self.maybe[hashes >> np.uint64(44)] = True

    def lattice(self, codes: np.ndarray) -> list[np.ndarray]:
        """By length: piece number at each start, or ``size`` where there is none."""
        out = []
        for _, values in _hashes(codes, self.longest):
            number = np.full(values.shape, self.size, dtype=np.int32)
            hit = np.flatnonzero(self.maybe[values >> np.uint64(44)])
            wanted = values.ravel()[hit]
            place = np.minimum(np.searchsorted(self.sorted, wanted), self.size - 1)
            same = self.sorted[place] == wanted
            number.ravel()[hit[same]] = self.piece[place[same]]
            out.append(number)
        return out

    def log_mass(self, chance: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """(words, languages): logarithm of the mass of all segmentations of words of one length, in memory for ``RUN`` letters."""
        words, width = codes.shape
        before = [np.ones((words, chance.shape[1]))]  # masses of the last prefixes, newest last
        logs = np.zeros((words, chance.shape[1]))
        for low in range(0, width, RUN):
            begun = max(0, low - self.longest + 1)
            lattice = self.lattice(codes[:, begun : low + RUN])
            for end in range(low + 1, min(width, low + RUN) + 1):
                number = lattice[0][:, end - 1 - begun]
                mass = before[-1] * np.where((number == self.size)[:, None], UNCOVERED, chance[number])
                for length in range(2, min(len(before), len(lattice)) + 1):
                    number = lattice[length - 1][:, end - length - begun]
                    rows = np.flatnonzero(number < self.size)
                    if len(rows):
                        mass[rows] += before[-length][rows] * chance[number[rows]]
                before = [*before[1 - self.longest :], mass] if self.longest > 1 else [mass]
            scale = np.maximum(before[-1], 1e-300)
            logs += np.log(scale)
            before = [mass / scale for mass in before]
        return logs

    def weights(self, chance: np.ndarray, lattice: list[np.ndarray], length: int) -> np.ndarray:
        """Probabilities (words, starts, languages) of the pieces of one length."""
        number = lattice[length - 1]
        found = chance[number]
        return np.where((number == self.size)[..., None], chance.dtype.type(UNCOVERED), found) if length == 1 else found

    def prefixes(self, chance: np.ndarray, lattice: list[np.ndarray], width: int) -> np.ndarray:
        """(words, width + 1, languages): mass of all segmentations of each prefix, in the type of ``chance``."""
        mass = np.zeros((lattice[0].shape[0], width + 1, chance.shape[1]), dtype=chance.dtype)
        mass[:, 0] = 1
        by_length = [self.weights(chance, lattice, length) for length in range(1, len(lattice) + 1)]
        for end in range(1, width + 1):
            for length in range(1, min(end, len(lattice)) + 1):
                mass[:, end] += mass[:, end - length] * by_length[length - 1][:, end - length]
        return mass

    def suffixes(self, chance: np.ndarray, lattice: list[np.ndarray], width: int) -> np.ndarray:
        mass = np.zeros((lattice[0].shape[0], width + 1, chance.shape[1]), dtype=chance.dtype)
        mass[:, width] = 1
        by_length = [self.weights(chance, lattice, length) for length in range(1, len(lattice) + 1)]
        for start in range(width - 1, -1, -1):
            for length in range(1, min(width - start, len(lattice)) + 1):
                mass[:, start] += mass[:, start + length] * by_length[length - 1][:, start]
        return mass


@dataclass
class SplitTexts:
    """The words of some texts: letters of the different ones, and for each word of the texts its text and its number among them."""

    letters: pa.Array
    owner: np.ndarray
    number: np.ndarray
    texts: int


def split_texts(texts: pa.Array) -> SplitTexts:
    lists = pc.utf8_split_whitespace(pc.utf8_lower(pc.fill_null(texts, "")))
    words = lists.flatten().dictionary_encode()
    letters = pc.replace_substring_regex(words.dictionary, r"\PL+", "").dictionary_encode()
    number = np.asarray(letters.indices)[np.asarray(words.indices)]
    owner = np.repeat(np.arange(len(texts)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))
    return SplitTexts(letters.dictionary, owner, number, len(texts))


def by_length(words: list[str]) -> dict[int, list[int]]:
    """Places of the words of each length; empty words are left out."""
    out: dict[int, list[int]] = {}
    for i, word in enumerate(words):
        if word:
            out.setdefault(len(word), []).append(i)
    return out


@dataclass
class LanguageModel:
    languages: list[str]
    pieces: list[str]
    chance: np.ndarray  # (pieces + 1, languages); the last row is zero
    floor: float = -np.inf  # nats a letter
    name: str = field(default_factory=lambda: uuid.uuid4().hex)


class WordScorer(WordMemo):
    """Log-probabilities of words in each language, remembered."""

    def __init__(self, model: LanguageModel, limit: int = MEMO_WORDS):
        super().__init__(limit)
        self.model, self.segmenter = model, Segmenter(model.pieces)
        self.table = np.zeros((0, len(model.languages)))

    def keep(self, places: np.ndarray) -> None:
        self.table = self.table[places]

    def log_chances(self, words: list[str]) -> np.ndarray:
        """(words, languages); a word without letters has 0."""
        out = np.zeros((len(words), len(self.model.languages)))
        for length, members in by_length(words).items():
            each = max(1, PASS_WORDS * RUN // max(RUN, length))
            for low in range(0, len(members), each):
                part = members[low : low + each]
                out[part] = self.segmenter.log_mass(self.model.chance, _codes([START + words[i] for i in part]))
        return out

    def rows(self, letters: pa.Array) -> np.ndarray:
        """Of different words."""
        place = self.find(letters)
        known = place >= 0
        out = np.empty((len(letters), len(self.model.languages)))
        out[known] = self.table[place[known]]
        if not known.all():
            missing = letters.filter(pa.array(~known))
            fresh = out[~known] = self.log_chances(missing.to_pylist())
            held = self.admit(missing)
            self.table = np.concatenate([self.table, fresh[held]])
        return out

    def totals(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(texts, languages) sums of log-probabilities, and the letters of each text."""
        split = split_texts(texts)
        rows, letters = self.rows(split.letters), pc.utf8_length(split.letters).to_numpy(zero_copy_only=False)
        add = lambda column: np.bincount(split.owner, column[split.number], split.texts)
        return np.stack([add(column) for column in rows.T], axis=1), add(letters)


def estimate(texts: list[tuple[str, str]], pieces: list[str]) -> LanguageModel:
    """Expectation maximisation of the piece probabilities of each language; longer runs of letters are cut at ``TRAINING_RUN``."""
    languages = sorted({lang for _, lang in texts})
    counts: dict[str, np.ndarray] = {}
    for at, lang in enumerate(languages):
        split = split_texts(pa.array([t for t, own in texts if own == lang], pa.string()))
        for word, n in zip(split.letters.to_pylist(), np.bincount(split.number, minlength=len(split.letters)).tolist(), strict=True):
            marked = START + word
            for low in range(0, len(marked) if word else 0, TRAINING_RUN):
                counts.setdefault(marked[low : low + TRAINING_RUN], np.zeros(len(languages)))[at] += n
    segmenter = Segmenter(pieces)
    chance = np.full((len(pieces) + 1, len(languages)), 1 / len(pieces))
    chance[-1] = 0
    words = list(counts)
    for _ in range(ROUNDS):
        expected = np.zeros_like(chance)
        for width, members in by_length(words).items():
            # Masses of long runs are beyond the range of doubles.
            held = chance if width <= RUN else chance.astype(np.longdouble)
            each = max(1, PASS_WORDS * RUN // max(RUN, width))
            for low in range(0, len(members), each):
                part = [words[i] for i in members[low : low + each]]
                weight = np.stack([counts[w] for w in part])
                lattice = segmenter.lattice(_codes(part))
                ahead = segmenter.prefixes(held, lattice, width)
                behind = segmenter.suffixes(held, lattice, width)
                share = weight / np.maximum(ahead[:, width], np.finfo(held.dtype).tiny)
                for length in range(1, len(lattice) + 1):
                    number = lattice[length - 1]
                    starts = number.shape[1]
                    mass = ahead[:, :starts] * segmenter.weights(held, lattice, length) * behind[:, length : length + starts] * share[:, None]
                    for k in range(len(languages)):
                        expected[:, k] += np.bincount(number.ravel(), mass[..., k].ravel().astype(np.float64), len(pieces) + 1)
        expected[-1] = 0
        own = expected / np.maximum(expected.sum(axis=0), 1e-300)
        shared = (own.mean(axis=1, keepdims=True) + 1 / len(pieces)) / 2
        shared[-1] = 0
        chance = (1 - SMOOTHING) * own + SMOOTHING * shared
    return LanguageModel(languages, pieces, chance)


def with_floor(model: LanguageModel, texts: list[str]) -> LanguageModel:
    """Set the floor by labelled texts that the model has not seen."""
    if texts:
        totals, letters = WordScorer(model).totals(pa.array(texts, pa.string()))
        enough = letters >= FLOOR_LETTERS
        if enough.any():
            model.floor = FLOOR_MARGIN * float((totals.max(axis=1)[enough] / letters[enough]).min())
    return model


def learn(docs: DataFrame, vocabulary: str) -> LanguageModel | None:
    """Learn from ``text`` and ``lang`` of ``docs``, on a sample bounded by ``SAMPLE_TEXTS`` and ``SAMPLE_CHARS``.

    The sample is the texts with the least hash of their ``doc_id`` and text,
    about equally many of each language.
    """
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.length("text") <= SAMPLE_CHARS))
    sizes = {row["lang"]: row["count"] for row in labelled.groupBy("lang").count().collect()}
    if not sizes:
        return None
    each = max(LEAST_TEXTS, SAMPLE_TEXTS // len(sizes))
    share = F.create_map(*[F.lit(x) for lang, n in sizes.items() for x in (lang, each / n)])
    draw = F.pmod(F.xxhash64(F.lit("language sample"), "doc_id", "text"), F.lit(1_000_000)) / share[F.col("lang")]
    # A little more than is wanted is sorted, so that no task sends more than its share.
    wanted = labelled.select("text", "lang", draw.alias("draw")).where(F.col("draw") < 1_200_000)
    sample = wanted.orderBy("draw", "lang", "text").limit(each * len(sizes)).collect()
    texts = [(row["text"], row["lang"]) for row in sample]
    fitted, aside = [t for i, t in enumerate(texts) if i % FLOOR_SHARE], [t for t, _ in texts[::FLOOR_SHARE]]
    if Counter(lang for _, lang in fitted).keys() != Counter(lang for _, lang in texts).keys():
        fitted, aside = texts, []
    return with_floor(estimate(fitted, public_pieces(vocabulary)), aside)


def judge(scorer: WordScorer | None, texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Language and score of each text, and whether the text is no stranger to that language."""
    if scorer is None:
        return ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts), dtype=bool)
    totals, letters = scorer.totals(texts)
    best = totals.argmax(axis=1)
    top = totals[np.arange(len(texts)), best]
    scores = np.where(letters > 0, 1 / np.exp((totals - top[:, None]) * TEMPER).sum(axis=1), 0.0)
    names = [scorer.model.languages[b] if n else "und" for b, n in zip(best.tolist(), letters.tolist(), strict=True)]
    return names, scores, top >= scorer.model.floor * letters - FLOOR_SLACK


def _scorer(model: LanguageModel | None) -> WordScorer | None:
    return None if model is None else worker_state("language", model.name, lambda: WordScorer(model))


def predict(docs: DataFrame, vocabulary: str, folds: int = 5) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every whole text; learns from the rows outside fold 0."""
    model = _broadcast(docs.where(bucket_of("doc_id", folds) != 0), vocabulary)

    def mark(batches):
        scorer = _scorer(model.value)
        for batch in batches:
            low = 0
            for texts in slices(batch.column(2)):
                names, scores, _ = judge(scorer, texts)
                part = batch.slice(low, len(texts))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])
                low += len(texts)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(bucket_of("doc_id", folds) == 0, F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(mark, "doc_id long, held_out boolean, lang_pred string, score double")


def _broadcast(docs: DataFrame, vocabulary: str):
    return docs.sparkSession.sparkContext.broadcast(learn(docs, vocabulary))


def keep_known(docs: DataFrame, vocabulary: str, least: float = 0.5, folds: int = 5) -> DataFrame:
    """The rows of ``docs`` whose language is recognised with at least ``least`` and that fit it; all columns stay as they are."""
    model = _broadcast(docs.where(bucket_of("doc_id", folds) != 0), vocabulary)
    at = docs.columns.index("text")

    def keep(batches):
        scorer = _scorer(model.value)
        for batch in batches:
            low = 0
            for texts in slices(batch.column(at)):
                names, scores, fits = judge(scorer, texts)
                known = np.array([n != "und" for n in names], dtype=bool) & (scores >= least) & fits
                yield batch.slice(low, len(texts)).filter(pa.array(known))
                low += len(texts)

    return docs.mapInArrow(keep, docs.schema)
