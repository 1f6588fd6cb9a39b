"""Many block pairs at once: every pointer update is one array operation.

All blocks of a batch take the same step at the same time. Arrays are laid
out with the offset first, so a step touches contiguous memory, and links are
flat addresses (offset * pairs + pair), so that following one is one gather.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

#: Greater than or equal to every 64-bit code.
TOP = np.iinfo(np.int64).max


def top_of(codes: np.ndarray) -> int:
    """Greater than or equal to every code of that type."""
    return int(np.iinfo(codes.dtype).max)


class LinkedBlocks:
    """Sorted lists over the columns of ``values`` (k, pairs), with a marker for each of several ranks."""

    def __init__(self, values: np.ndarray, order: np.ndarray, small: Sequence[int], rewound: bool):
        self.k, self.pairs = values.shape
        kind = np.int64 if (self.k + 1) * self.pairs > np.iinfo(np.int32).max else np.int32
        self.lane = np.arange(self.pairs, dtype=kind)
        self.end = self.lane + self.k * self.pairs
        self.values = np.concatenate([values.ravel(), np.full(self.pairs, top_of(values), dtype=values.dtype)])
        chain = np.concatenate([self.end[None], order.astype(kind) * self.pairs + self.lane, self.end[None]])
        self.next = np.empty((self.k + 1) * self.pairs, dtype=kind)
        self.prev = np.empty_like(self.next)
        self.next[chain[:-1]] = chain[1:]
        self.prev[chain[1:]] = chain[:-1]
        if rewound:
            for t in range(self.k - 1, -1, -1):
                self._unlink(slice(t * self.pairs, (t + 1) * self.pairs))
            self.marker = [self.end.copy() for _ in small]
            self.small = [np.zeros(self.pairs, dtype=np.int32) for _ in small]
        else:
            self.marker = [chain[1 + r].copy() for r in small]
            self.small = [np.full(self.pairs, r, dtype=np.int32) for r in small]

    def _unlink(self, at: slice) -> None:
        before, after = self.prev[at], self.next[at]
        self.next[before] = after
        self.prev[after] = before

    def _address(self, t: int) -> np.ndarray:
        return self.lane + t * self.pairs

    def _before(self, own: np.ndarray, address: np.ndarray, marker: np.ndarray) -> np.ndarray:
        bound = self.values[marker]
        return (own < bound) | ((own == bound) & (address < marker))

    def drop(self, t: int) -> None:
        at = slice(t * self.pairs, (t + 1) * self.pairs)
        address, own, after = self._address(t), self.values[at], self.next[at]
        was_small = [self._before(own, address, m) for m in self.marker]
        self._unlink(at)
        for i, small in enumerate(was_small):
            marker = np.where(self.marker[i] == address, after, self.marker[i])
            back = ~small & (self.small[i] > 0)
            self.marker[i] = np.where(back, self.prev[marker], marker)
            self.small[i] = np.maximum(self.small[i] - 1, 0)

    def restore(self, t: int) -> None:
        at = slice(t * self.pairs, (t + 1) * self.pairs)
        address, own = self._address(t), self.values[at]
        self.next[self.prev[at]] = address
        self.prev[self.next[at]] = address
        for i, marker in enumerate(self.marker):
            self.marker[i] = np.where(self._before(own, address, marker), self.prev[marker], marker)


def walk_pairs(old: np.ndarray, old_order: np.ndarray, new: np.ndarray, new_order: np.ndarray, ranks: Sequence[int], lower: bool = False) -> tuple[np.ndarray, np.ndarray | None]:
    """Slide from old to new blocks, (k, pairs) each.

    Gives (ranks, k, pairs) codes of the item of each rank after each step, and
    with ``lower`` also the item before it.
    """
    k, pairs = old.shape
    a, b = LinkedBlocks(old, old_order, ranks, rewound=False), LinkedBlocks(new, new_order, ranks, rewound=True)
    upper, least = np.empty((len(ranks), k, pairs), dtype=old.dtype), -top_of(old) - 1
    below = np.empty_like(upper) if lower else None
    for t in range(k):
        a.drop(t)
        b.restore(t)
        for i, rank in enumerate(ranks):
            front_a, front_b = a.values[a.marker[i]], b.values[b.marker[i]]
            short = a.small[i] + b.small[i] < rank
            if short.any():
                # Never an exhausted list: a value may equal what stands at its end.
                from_a = ((front_a <= front_b) & (a.marker[i] != a.end)) | (b.marker[i] == b.end)
                for part, chosen in ((a, short & from_a), (b, short & ~from_a)):
                    part.marker[i] = np.where(chosen, part.next[part.marker[i]], part.marker[i])
                    part.small[i] += chosen
                front_a, front_b = a.values[a.marker[i]], b.values[b.marker[i]]
            upper[i, t] = np.minimum(front_a, front_b)
            if below is not None:
                last_a = np.where(a.small[i] > 0, a.values[a.prev[a.marker[i]]], least)
                last_b = np.where(b.small[i] > 0, b.values[b.prev[b.marker[i]]], least)
                below[i, t] = np.maximum(last_a, last_b)
    return upper, below
