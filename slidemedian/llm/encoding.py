"""Whole texts to token ids, by a memo of space-delimited chunks.

A space that stands between two characters that are not white space always
starts a new match of the split pattern, so a text may be cut there and each
chunk encoded by itself. Chunks repeat far more often than texts: a slice of
texts is cut and its chunks numbered by Arrow, so that Python sees each
different chunk of a slice once, and the encoder behind (a library, or the
transducer of ``bpe_transducer``) only those that the worker does not remember.
Before the library, chunks are cut further, into letters and what stands
between them, and these units are what the worker remembers (``units``).
The ids of the texts are then gathered by array operations. Texts with other
white space next to a space go to the encoder whole.

Ids travel as unsigned 32-bit integers, little-endian where they are bytes.
"""

from __future__ import annotations

import os
from array import array
from collections.abc import Callable, Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .shared import worker_state

_SPACES = r"\x09-\x0d\x1c-\x20\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}"
#: A space next to other white space, or at the end.
_UNSAFE = rf" [{_SPACES}]|[{_SPACES}] | \z"

#: Chunks or units that a worker remembers at most, and the longest one that it remembers, in bytes (some 50 bytes each: 25 MB).
MEMO_CHUNKS, MEMO_LENGTH = 500_000, 64
#: Bytes of text that are encoded in one go, unless one text has more, and that are taken to words by other operators; arrays take up to twenty times as much.
ENCODED_BYTES, SLICE_BYTES = 8 << 20, 3 << 20
#: New chunks that the library sees as one text.
CHUNKS_A_CALL = 256

#: Ids of some texts one after the other, and the number of ids of each.
Encoded = tuple[np.ndarray, np.ndarray]


def gathered(ids: np.ndarray, sizes: np.ndarray, wanted: np.ndarray) -> Encoded:
    """The parts numbered ``wanted`` of ids that are given with the size of each part."""
    length = sizes[wanted]
    total = int(length.sum())
    kind = np.int32 if max(total, len(ids)) < 1 << 31 else np.int64
    place = np.repeat(((np.cumsum(sizes) - sizes)[wanted] - (np.cumsum(length) - length)).astype(kind), length)
    place += np.arange(total, dtype=kind)
    return ids[place], length


class WordMemo:
    """Different strings, and what a subclass holds for each, in arrays.

    When it is full, the half that came up most often stays.
    """

    def __init__(self, limit: int):
        self.limit, self.words, self.hits = limit, pa.array([], pa.string()), np.zeros(0, dtype=np.int64)

    def find(self, words: pa.Array) -> np.ndarray:
        """The place of each word, -1 where it is not held."""
        if not len(self.words):
            return np.full(len(words), -1)
        found = pc.fill_null(pc.index_in(words, value_set=self.words), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        self.hits[found[found >= 0]] += 1
        return found

    def admit(self, words: pa.Array) -> np.ndarray:
        """Hold the short ones of new words, and make room for them; gives which ones they are."""
        short = np.flatnonzero(pc.binary_length(words).to_numpy(zero_copy_only=False) <= MEMO_LENGTH)[: self.limit // 2]
        if len(self.words) + len(short) > self.limit:
            often = np.sort(np.argsort(-self.hits, kind="stable")[: self.limit // 2])
            self.words, self.hits = self.words.take(pa.array(often)), self.hits[often] // 2
            self.keep(often)
        self.words = pa.concat_arrays([self.words, words.take(pa.array(short))])
        self.hits = np.concatenate([self.hits, np.zeros(len(short), dtype=np.int64)])
        return short

    def keep(self, places: np.ndarray) -> None:
        raise NotImplementedError


class ChunkMemo(WordMemo):
    """Chunks and their ids."""

    def __init__(self, limit: int):
        super().__init__(limit)
        self.ids, self.sizes = np.zeros(0, dtype="<u4"), np.zeros(0, dtype=np.int64)

    def keep(self, places: np.ndarray) -> None:
        self.ids, self.sizes = gathered(self.ids, self.sizes, places)

    def add(self, words: pa.Array, ids: np.ndarray, sizes: np.ndarray) -> None:
        ids, sizes = gathered(ids, sizes, self.admit(words))
        self.ids, self.sizes = np.concatenate([self.ids, ids]), np.concatenate([self.sizes, sizes])

    def recall(self, words: pa.Array, encode: Callable[[pa.Array], Encoded]) -> Encoded:
        """Of different words; ``encode`` gets those that are not held."""
        place = self.find(words)
        known = place >= 0
        ids, sizes = gathered(self.ids, self.sizes, place[known])
        if known.all():
            return ids, sizes
        missing = words.filter(pa.array(~known))
        fresh_ids, fresh_sizes = encode(missing)
        self.add(missing, fresh_ids, fresh_sizes)
        number = np.empty(len(words), dtype=np.int64)
        number[known], number[~known] = np.arange(len(sizes)), len(sizes) + np.arange(len(missing))
        return gathered(np.concatenate([ids, fresh_ids]), np.concatenate([sizes, fresh_sizes]), number)


def slices(texts: pa.Array, size: int = SLICE_BYTES) -> Iterator[pa.Array]:
    """Consecutive parts of about ``size`` bytes."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    low = 0
    while low < len(texts):
        high = max(low + 1, int(np.searchsorted(ends, (ends[low - 1] if low else 0) + size, side="right")))
        yield texts.slice(low, high - low)
        low = high


#: Kinds of bytes: ASCII letters, ASCII white space, other ASCII characters, and the first of two bytes of U+00C0 to U+027F, which are letters but for the signs of ``_SIGNS``.
_LETTER, _SPACE, _PLAIN, _LEAD = 1, 2, 3, 4
_KINDS = np.array(
    [_LETTER if chr(b).isalpha() else _SPACE if chr(b).isspace() else _PLAIN for b in range(128)] + [_LEAD if 0xC3 <= b <= 0xC9 else 0 for b in range(128, 256)],
    dtype=np.uint8,
)
_SIGNS = tuple("\u00d7\u00f7".encode()[1::2])
_LETTERS_ONLY = r"\A[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{27f}]+\z"


def units(words: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The parts of words without spaces, cut wherever the split pattern starts a new match whatever stands around, and the number of parts of each word.

    A match that has a letter ends with the letters, so a letter and an ASCII
    character that is none are cut apart. Letters start a match of their own
    behind any character that is neither a letter, a space nor an apostrophe;
    how white space of several characters is matched depends on what follows,
    so it stays together with that.
    """
    offsets = np.frombuffer(words.buffers()[1], dtype=np.int32, count=len(words) + 1, offset=4 * words.offset)
    data = np.frombuffer(words.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
    begins = offsets[:-1] - offsets[0]
    kinds = _KINDS[data]
    opens, closes = (kinds == _LETTER) | (kinds == _LEAD), kinds == _LETTER
    for sign in _SIGNS:
        opens[:-1] &= (data[:-1] != 0xC3) | (data[1:] != sign)
    closes[1:] |= opens[:-1] & (kinds[:-1] == _LEAD)
    space, plain = kinds == _SPACE, kinds == _PLAIN
    single = space.copy()
    single[:1] = False
    single[1:] &= plain[:-1] | closes[:-1]
    single[begins[begins < len(data)]] = False
    cut = np.zeros(len(data) + 1, dtype=bool)
    cut[1:-1] = (closes[:-1] & (plain | space)[1:]) | (((plain & (data != 0x27)) | single)[:-1] & opens[1:])
    cut[begins] = False
    before = np.concatenate([[0], np.cumsum(cut)])
    parts = 1 + before[offsets[1:] - offsets[0]] - before[begins]
    firsts = np.cumsum(parts) - parts
    starts = np.full(int(parts.sum()) + 1, len(data), dtype=np.int32)
    inner = np.ones(len(starts), dtype=bool)
    inner[firsts] = inner[-1] = False
    starts[firsts], starts[inner] = begins, np.flatnonzero(cut)
    return pa.Array.from_buffers(pa.string(), len(starts) - 1, [None, pa.py_buffer(starts), pa.py_buffer(data)]), parts


def joined(parts: Sequence[bytes]) -> Encoded:
    return np.frombuffer(b"".join(parts), dtype="<u4"), np.fromiter(map(len, parts), dtype=np.int64, count=len(parts)) // 4


class ChunkEncoder:
    """``encode_chunks`` encodes words, each of which stands behind a space; ``encode_whole`` encodes texts."""

    def __init__(self, encode_chunks: Callable[[pa.Array], Encoded], encode_whole: Callable[[list[str]], Encoded], whole_if: Sequence[str] = (), limit: int = MEMO_CHUNKS):
        self.encode_chunks, self.encode_whole, self.whole_if, self.memo = encode_chunks, encode_whole, whole_if, ChunkMemo(limit)

    def _regular(self, texts: pa.Array) -> Encoded:
        """Of texts that may be cut at every space."""
        if not len(texts):
            return np.zeros(0, dtype="<u4"), np.zeros(0, dtype=np.int64)
        lists = pc.split_pattern(texts, " ")
        words, firsts = lists.flatten(), np.asarray(lists.offsets)[:-1].astype(np.int64)
        behind = np.ones(len(words), dtype=bool)
        behind[firsts] = False
        numbered = words.filter(pa.array(behind)).dictionary_encode()
        ids, sizes = self.memo.recall(numbered.dictionary, self.encode_chunks)
        head_ids, head_sizes = self.encode_whole(words.take(pa.array(firsts)).to_pylist())
        number = np.empty(len(words), dtype=np.int64)
        number[behind], number[firsts] = np.asarray(numbered.indices), len(sizes) + np.arange(len(firsts))
        out, length = gathered(np.concatenate([ids, head_ids]), np.concatenate([sizes, head_sizes]), number)
        return out, np.add.reduceat(length, firsts)

    def _slice(self, texts: pa.Array) -> Encoded:
        whole = pc.match_substring_regex(texts, _UNSAFE)
        for content in self.whole_if:
            whole = pc.or_(whole, pc.match_substring(texts, content))
        odd = np.asarray(whole.to_numpy(zero_copy_only=False), dtype=bool)
        if not odd.any():
            return self._regular(texts)
        at = np.flatnonzero(odd)
        odd_ids, odd_sizes = self.encode_whole(texts.take(pa.array(at)).to_pylist())
        ids, sizes = self._regular(texts.filter(pa.array(~odd)))
        every = np.empty(len(texts), dtype=np.int64)
        every[odd], every[~odd] = odd_sizes, sizes
        out, from_odd = np.empty(int(every.sum()), dtype="<u4"), np.repeat(odd, every)
        out[from_odd], out[~from_odd] = odd_ids, ids
        return out, every

    def encode_slices(self, texts: pa.Array) -> Iterator[Encoded]:
        """(ids, number of ids of each text) of consecutive parts of ``texts``; a null text counts as empty."""
        for part in slices(texts, ENCODED_BYTES):
            yield self._slice(pc.fill_null(part, ""))

    def encode(self, text: str) -> bytes:
        return b"".join(ids.tobytes() for ids, _ in self.encode_slices(pa.array([text], pa.string())))


def with_end(ids: np.ndarray, sizes: np.ndarray, end_id: int) -> Encoded:
    """Append ``end_id`` to the ids of each text."""
    return np.insert(ids, np.cumsum(sizes), end_id), sizes + 1


def byte_lists(ids: np.ndarray, sizes: np.ndarray) -> list[memoryview]:
    """The ids of each text as bytes."""
    ends = np.cumsum(sizes) * ids.itemsize
    view = memoryview(np.ascontiguousarray(ids)).cast("B") if len(ids) else memoryview(b"")
    return [view[high - size : high] for high, size in zip(ends.tolist(), (sizes * ids.itemsize).tolist(), strict=True)]


def binary_array(ids: np.ndarray, sizes: np.ndarray) -> pa.Array:
    """The ids of each text as bytes, in Arrow."""
    offsets = np.concatenate([[0], np.cumsum(sizes * ids.itemsize)]).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(ids))])


def list_array(ids: np.ndarray, sizes: np.ndarray) -> pa.ListArray:
    """The ids of each text as Arrow lists of int32."""
    offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(ids.view("<i4")))


def piece_encoder(encode_piece: Callable[[str], Iterable[int]]) -> ChunkEncoder:
    """An encoder over single matches of the split pattern."""
    import public_tokenizers
    import regex

    split = regex.compile(public_tokenizers.PATTERN).findall

    def whole(texts: list[str]) -> Encoded:
        known: dict[str, bytes] = {}
        out = []
        for text in texts:
            for piece in (pieces := split(text)):
                if piece not in known:
                    known[piece] = array("I", encode_piece(piece)).tobytes()
            out.append(b"".join([known[piece] for piece in pieces]))
        return joined(out)

    return ChunkEncoder(lambda words: whole([" " + w for w in words.to_pylist()]), whole)


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabularies: printable Latin-1 characters stand for themselves, the others for 256 and up."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(own)]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


def _library(path: str, added: bool) -> ChunkEncoder:
    # Workers are forked; the library's own threads would not survive that.
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(path)
    library.encode_special_tokens = not added
    opens = {mark: np.zeros(library.get_vocab_size(), dtype=bool) for mark in (" ", "\n")}
    alphabet, vocabulary = byte_alphabet(), library.get_vocab()
    for mark, those in opens.items():
        those[[i for token, i in vocabulary.items() if token.startswith(alphabet[ord(mark)])]] = True

    def whole(texts: list[str]) -> Encoded:
        return joined([array("I", e.ids).tobytes() for e in library.encode_batch_fast(texts, add_special_tokens=False)])

    def many(words: pa.Array, mark: str) -> Encoded:
        """Many in a text of their own, each behind a mark that starts a token; that token's place tells where a word begins."""
        ends = pa.array([*range(0, len(words), CHUNKS_A_CALL), len(words)], pa.int32())
        texts = pc.binary_join(pa.ListArray.from_arrays(ends, words), mark)
        ids, _ = whole([mark + text for text in texts.to_pylist()])
        cuts = np.flatnonzero(opens[mark][ids])
        return ids, np.diff(cuts, append=len(ids))

    def heads(words: pa.Array) -> Encoded:
        """Words behind a space."""
        ids, sizes = many(words, " ")
        return (ids, sizes) if len(sizes) == len(words) else whole([" " + w for w in words.to_pylist()])

    def tails(words: pa.Array) -> Encoded:
        """Words behind another unit. Letters do not join a line feed, which has one token."""
        alone = pc.match_substring_regex(words, _LETTERS_ONLY)
        letters = np.asarray(alone.to_numpy(zero_copy_only=False), dtype=bool)
        other_ids, other_sizes = whole(words.filter(pc.invert(alone)).to_pylist())
        ids, sizes = many(words.filter(alone), "\n")
        number = np.empty(len(words), dtype=np.int64)
        number[letters], number[~letters] = np.arange(len(sizes)), len(sizes) + np.arange(len(other_sizes))
        ids = ids[~opens["\n"][ids]]
        return gathered(np.concatenate([ids, other_ids]), np.concatenate([sizes - 1, other_sizes]), number)

    held = {True: (ChunkMemo(MEMO_CHUNKS), heads), False: (ChunkMemo(MEMO_CHUNKS // 4), tails)}

    def chunks(words: pa.Array) -> Encoded:
        """By their units, which repeat more often than chunks do."""
        parts, counts = units(words)
        firsts = np.cumsum(counts) - counts
        first = np.zeros(len(parts), dtype=bool)
        first[firsts] = True
        number, ids, sizes = np.empty(len(parts), dtype=np.int64), [], []
        for wanted, (memo, encode) in held.items():
            numbered = parts.filter(pa.array(first == wanted)).dictionary_encode()
            number[first == wanted] = np.asarray(numbered.indices) + sum(map(len, sizes))
            for column, found in zip((ids, sizes), memo.recall(numbered.dictionary, encode), strict=True):
                column.append(found)
        out, length = gathered(np.concatenate(ids), np.concatenate(sizes), number)
        return out, np.add.reduceat(length, firsts)

    contents = [token.content for token in library.get_added_tokens_decoder().values()] if added else []
    return ChunkEncoder(chunks, whole, contents, limit=0)  # units are remembered, so chunks need not be


def library_encoder(path: str, added: bool = False) -> ChunkEncoder:
    """Encoder by a ``tokenizers`` file, one for each worker process.

    Special tokens are not appended; those written in texts are recognised only
    with ``added``, as the library does at its defaults.
    """
    return worker_state("tokens", (path, added), lambda: _library(path, added))


def id_type(path: str) -> str:
    """The narrowest type that holds every id of a ``tokenizers`` file."""
    from tokenizers import Tokenizer

    return "<u2" if Tokenizer.from_file(path).get_vocab_size() <= 1 << 16 else "<u4"


def public_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
