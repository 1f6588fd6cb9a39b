"""Byte-level BPE as a finite-state transducer, and streaming decoding.

The vocabulary's ranks define the merges. A sequence of tokens is the encoding
of its bytes exactly when every token encodes itself and every two neighbours
encode as themselves, so encodings are the accepting paths of a
non-deterministic machine whose states are (last token, place in the trie of
token bytes). Every prefix has one encoding, hence few states are alive at a
time. The machine is determinised as it meets input: a deterministic state is
the set of live states with the tokens each still owes, and a token is emitted
once all of them agree on it, which the longest token bounds.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .encoding import ChunkEncoder, byte_lists, gathered, list_array, piece_encoder
from .shared import worker_state

#: Deterministic transitions that a machine keeps before it starts anew, and borders of tokens that it remembers (with their states some 250 MB).
TRANSITIONS, BORDERS = 500_000, 300_000
#: Ids that the streaming decoder takes at a time.
DECODE_BLOCK = 1 << 16
#: Runs of bytes whose end state a decoder remembers, and the longest such run.
MOST_RUNS, LONGEST_RUN = 20_000, 24
#: A rank after all others.
NEVER = 1 << 40


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


class MergeTransducer:
    def __init__(self, ranks: dict[bytes, int], limit: int = TRANSITIONS):
        self.ranks, self.limit = ranks, limit
        self.tokens = [b""] * (max(ranks.values()) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token
        self.trie: dict[int, int] = {}
        self.token_at, self.inner = [-1], [True]
        for token, rank in ranks.items():
            node = 0
            for byte in token:
                self.inner[node] = True
                key = node << 8 | byte
                node = self.trie.get(key, 0)
                if not node:
                    node = self.trie[key] = len(self.token_at)
                    self.token_at.append(-1)
                    self.inner.append(False)
            self.token_at[node] = rank
        self.ends: dict[int, tuple[bool, list, list]] = {}
        self.borders: dict[int, bool] = {}
        self._restart()

    def _restart(self) -> None:
        self.states: list[tuple] = [((-1, 0, ()),)]
        self.number = {self.states[0]: 0}
        self.moves: dict[int, tuple[int, tuple]] = {}

    def _compile(self, token: int) -> tuple[bool, list, list]:
        """Merge the token's own bytes, lowest rank first.

        Gives whether that ends in the token, and the parts that stood at its
        left and its right end, each with the rank of the merge that ended it.
        """
        data = self.tokens[token]
        parts = [data[i : i + 1] for i in range(len(data))]
        left, right = [[parts[0], NEVER]], [[parts[-1], NEVER]]
        while len(parts) > 1:
            rank, at = min((self.ranks.get(a + b, NEVER), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)))
            if rank == NEVER:
                break
            if at == 0:
                left[-1][1] = rank
                left.append([parts[0] + parts[1], NEVER])
            if at == len(parts) - 2:
                right[-1][1] = rank
                right.append([parts[-2] + parts[-1], NEVER])
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return len(parts) == 1, left, right

    def _ends(self, token: int) -> tuple[bool, list, list]:
        known = self.ends.get(token)
        if known is None:
            known = self.ends[token] = self._compile(token)
        return known

    def _may_follow(self, last: int, token: int) -> bool:
        """No merge crosses the border between the two.

        Merges happen in ascending rank, so the parts at both sides of the
        border are known at each rank; a crossing merge wins when it ranks
        before the next change on its left, and no later than one on its right.
        """
        whole, left, _ = self._ends(token)
        if last < 0 or not whole:
            return whole
        right, ranks, i, j = self._ends(last)[2], self.ranks, 0, 0
        while True:
            (before, ends_before), (after, ends_after) = right[i], left[j]
            crossing = ranks.get(before + after, NEVER)
            if crossing < ends_before and crossing <= ends_after and crossing < NEVER:
                return False
            if ends_before == ends_after == NEVER:
                return True
            if ends_before <= ends_after:
                i += 1
            else:
                j += 1

    def _border(self, last: int, token: int) -> bool:
        key = (last + 1) << 32 | token
        known = self.borders.get(key)
        if known is None:
            if len(self.borders) >= BORDERS:
                self.borders.clear()
            known = self.borders[key] = self._may_follow(last, token)
        return known

    def _determinise(self, state: int, byte: int) -> tuple[int, tuple]:
        alive, trie, inner, token_at = [], self.trie, self.inner, self.token_at
        for last, node, owed in self.states[state]:
            child = trie.get(node << 8 | byte)
            if child is None:
                continue
            if inner[child]:
                alive.append((last, child, owed))
            token = token_at[child]
            if token >= 0 and self._border(last, token):
                alive.append((token, 0, (*owed, token)))
        shared = 0
        shortest = min((len(owed) for _, _, owed in alive), default=0)
        while shared < shortest and len({owed[shared] for _, _, owed in alive}) == 1:
            shared += 1
        emitted = alive[0][2][:shared] if alive else ()
        key = tuple((last, node, owed[shared:]) for last, node, owed in alive)
        target = self.number.get(key)
        if target is None:
            target = self.number[key] = len(self.states)
            self.states.append(key)
        self.moves[state << 8 | byte] = target, emitted
        return target, emitted

    def encode(self, data: bytes) -> list[int]:
        if len(self.moves) > self.limit:
            self._restart()
        state, out, moves = 0, [], self.moves
        for byte in data:
            move = moves.get(state << 8 | byte) or self._determinise(state, byte)
            state = move[0]
            if move[1]:
                out += move[1]
        for _, node, owed in self.states[state]:
            if node == 0:
                out += owed
        return out


def _utf8_steps() -> list[list[int]]:
    """The state behind each state and byte.

    0: between characters; 1 to 3: so many further bytes of any kind are due;
    4 to 7: the second byte of a character that starts with E0, ED, F0 or F4 is
    due, which no overlong form, surrogate or number beyond the last may take;
    8: no UTF-8.
    """
    steps = [[8] * 256 for _ in range(8)]
    allowed = [(0, 0x00, 0x7F, 0), (0, 0xC2, 0xDF, 1), (0, 0xE1, 0xEF, 2), (0, 0xF1, 0xF3, 3), (0, 0xE0, 0xE0, 4), (0, 0xED, 0xED, 5), (0, 0xF0, 0xF0, 6), (0, 0xF4, 0xF4, 7)]
    allowed += [(1, 0x80, 0xBF, 0), (2, 0x80, 0xBF, 1), (3, 0x80, 0xBF, 2), (4, 0xA0, 0xBF, 1), (5, 0x80, 0x9F, 1), (6, 0x90, 0xBF, 2), (7, 0x80, 0x8F, 2)]
    for state, low, high, after in allowed:
        steps[state][low : high + 1] = [after] * (high + 1 - low)
    return steps


_STEPS = _utf8_steps()
_BEYOND_ASCII = re.compile(rb"[\x80-\xff]+").finditer


class Utf8Machine:
    """Bytes in, text out, by a state machine over bytes; an incomplete character waits for its other bytes.

    ASCII leaves state 0 as it is, so only runs of other bytes are stepped
    through, and the end states of short runs are remembered. A byte at which
    no character can start or go on becomes a lone surrogate, so that nothing
    is lost, and the machine goes on behind it in state 0.
    """

    def __init__(self):
        self.state, self.waiting = 0, b""
        self.runs: dict[bytes, int] = {}

    def _run(self, data: bytes) -> int:
        state = 0
        for byte in data:
            state = _STEPS[state][byte]
            if state == 8:
                break
        if len(data) <= LONGEST_RUN and len(self.runs) < MOST_RUNS:
            self.runs[data] = state
        return state

    def _broken(self, data: bytes, at_end: bool) -> tuple[str, int]:
        """Text of a run of non-ASCII bytes that holds no UTF-8 or ends within a character, and bytes that wait."""
        out, begun, place, state = [], 0, 0, 0
        while place < len(data):
            state = _STEPS[state][data[place]]
            if state == 8:
                out.append(chr(0xDC00 + data[begun]))
                place = begun = begun + 1
                state = 0
                continue
            place += 1
            if state == 0:
                out.append(data[begun:place].decode())
                begun = place
            elif place == len(data) and not at_end:
                out.append(chr(0xDC00 + data[begun]))
                place = begun = begun + 1
                state = 0
        self.state = state
        return "".join(out), len(data) - begun

    def feed(self, data: bytes) -> str:
        data = self.waiting + data
        self.state, self.waiting = 0, b""
        out, done = [], 0
        for run in _BEYOND_ASCII(data):
            known = self.runs.get(run[0])
            if (self._run(run[0]) if known is None else known) == 0:
                continue
            low, high = run.span()
            text, waits = self._broken(run[0], high == len(data))
            out += [data[done:low].decode(), text]
            done, self.waiting = high, data[high - waits : high]
        out.append(data[done:].decode())
        return "".join(out)

    def close(self) -> str:
        rest, self.state, self.waiting = self.waiting, 0, b""
        return "".join(chr(0xDC00 + byte) for byte in rest)


class TokenBytes:
    """The bytes of all tokens, one after the other."""

    def __init__(self, tokens: list[bytes]):
        self.pool, self.sizes = np.frombuffer(b"".join(tokens), dtype=np.uint8), np.array([len(t) for t in tokens], dtype=np.int64)

    def of(self, ids: np.ndarray) -> bytes:
        return gathered(self.pool, self.sizes, ids)[0].tobytes()


def decode_stream(ids: np.ndarray, tokens: TokenBytes, machine: Utf8Machine | None = None) -> Iterator[str]:
    machine = machine or Utf8Machine()
    for low in range(0, len(ids), DECODE_BLOCK):
        yield machine.feed(tokens.of(ids[low : low + DECODE_BLOCK]))
    yield machine.close()


class Transducer:
    """What a worker keeps for a rank file."""

    def __init__(self, path: str):
        self.machine = MergeTransducer(read_ranks(path))
        self.encoder: ChunkEncoder = piece_encoder(lambda piece: self.machine.encode(piece.encode()))
        self.tokens, self.utf8 = TokenBytes(self.machine.tokens), Utf8Machine()

    def decode(self, ids: np.ndarray) -> Iterator[bytes]:
        """The decoded bytes, block by block."""
        for text in decode_stream(ids, self.tokens, self.utf8):
            yield text.encode("utf-8", "surrogateescape")


def transducer(path: str) -> Transducer:
    """The machine of a rank file, one for each worker process."""
    return worker_state("transducer", path, lambda: Transducer(path))


def encode_documents(docs: DataFrame, rank_file: str) -> DataFrame:
    """(doc_id, ids array<int>) of every whole text; a null text has no ids."""

    def encode(batches):
        encoder = transducer(rank_file).encoder
        for batch in batches:
            low = 0
            for ids, sizes in encoder.encode_slices(batch.column(1)):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, len(sizes)), list_array(ids, sizes)], names=["doc_id", "ids"])
                low += len(sizes)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text").mapInArrow(encode, "doc_id long, ids array<int>")


def decode_documents(rows: DataFrame, rank_file: str) -> DataFrame:
    """(doc_id, text) of rows (doc_id, ids)."""

    def decode(batches):
        own = transducer(rank_file)
        for batch in batches:
            for low in range(0, batch.num_rows, 500):
                part = batch.slice(low, 500)
                texts = [b"".join(own.decode(np.array(ids or (), dtype=np.int64))).decode("utf-8", "replace") for ids in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return rows.select("doc_id", "ids").mapInArrow(decode, "doc_id long, text string")


def round_trip_digests(docs: DataFrame, rank_file: str) -> DataFrame:
    """Encode and decode every whole text: (doc_id, n_tokens, ids_sha256, decoded_sha256).

    Defined cases: a null text counts as empty and has no tokens; repeated rows
    stay separate; an empty table gives no rows; other columns are not read.
    """

    def digest(batches):
        own = transducer(rank_file)
        for batch in batches:
            low = 0
            for ids, sizes in own.encoder.encode_slices(batch.column(1)):
                of_ids = [hashlib.sha256(part).hexdigest() for part in byte_lists(ids, sizes)]
                of_text = []
                for high, size in zip(np.cumsum(sizes).tolist(), sizes.tolist(), strict=True):
                    decoded = hashlib.sha256()
                    for part in own.decode(ids[high - size : high]):
                        decoded.update(part)
                    of_text.append(decoded.hexdigest())
                columns = [batch.column(0).slice(low, len(sizes)), pa.array(sizes, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
                low += len(sizes)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text").mapInArrow(digest, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
