"""One block as a doubly linked sorted list: the plain form of the kernel.

Lists live in index arrays with one more slot, the end, which compares as
greater than everything. Items can be dropped, and dropped items restored in
the reverse order, since a dropped slot still knows its neighbours. A marker
splits the list into its s smallest items and the rest.
"""

from __future__ import annotations

from collections.abc import Sequence


class NestingError(RuntimeError):
    """Items were restored in an order that does not mirror the drops."""


class LinkedBlock:
    """Sorted list over ``values`` with a marker after ``small`` items.

    ``order`` lists the offsets in ascending order of (value, offset); ``rank``
    (the inverse permutation), when given, is compared instead of that pair, so
    that a sort need not be stable. ``debug`` checks the nesting.
    """

    def __init__(self, values: Sequence, order: Sequence[int], small: int, *, rank: Sequence[int] | None = None, debug: bool = False):
        self.values, self.rank, self.end, self.debug = values, rank, len(values), debug
        self.prev, self.next = [0] * (self.end + 1), [0] * (self.end + 1)
        last = self.end
        for offset in order:
            self.next[last], self.prev[offset] = offset, last
            last = offset
        self.next[last], self.prev[self.end] = self.end, last
        self.small = small
        self.marker = order[small] if small < self.end else self.end
        self.dropped: list[int] = []

    def rewind(self) -> None:
        """Drop everything, last offset first."""
        for offset in range(self.end - 1, -1, -1):
            self._unlink(offset)
        self.small, self.marker = 0, self.end

    def _unlink(self, offset: int) -> None:
        before, after = self.prev[offset], self.next[offset]
        self.next[before], self.prev[after] = after, before
        if self.debug:
            self.dropped.append(offset)

    def is_small(self, offset: int) -> bool:
        return self._before(offset, self.marker)

    def _before(self, one: int, other: int) -> bool:
        if other == self.end:
            return one != self.end
        if self.rank is not None:
            return self.rank[one] < self.rank[other]
        return (self.values[one], one) < (self.values[other], other)

    def drop(self, offset: int) -> None:
        """Take an item out; one item fewer is small, if any was."""
        small = self.is_small(offset)
        self._unlink(offset)
        if small:
            self.small -= 1
            return
        if offset == self.marker:
            self.marker = self.next[offset]
        if self.small:
            self.marker = self.prev[self.marker]
            self.small -= 1

    def restore(self, offset: int) -> None:
        """Put the item back that was dropped last; as many items are small as before."""
        if self.debug and (not self.dropped or self.dropped.pop() != offset):
            raise NestingError(f"offset {offset} was not the last one dropped")
        self.next[self.prev[offset]] = self.prev[self.next[offset]] = offset
        if self._before(offset, self.marker):
            self.marker = self.prev[self.marker]

    def promote(self) -> None:
        """The least large item becomes small."""
        self.marker = self.next[self.marker]
        self.small += 1

    @property
    def exhausted(self) -> bool:
        return self.marker == self.end

    def front(self):
        """The least large value; meaningless if the list is exhausted."""
        return self.values[self.marker]

    def last_small(self):
        return self.values[self.prev[self.marker]] if self.small else None

    def members(self) -> list[int]:
        out, at = [], self.next[self.end]
        while at != self.end:
            out.append(at)
            at = self.next[at]
        return out

    def small_set(self) -> set[int]:
        return set(self.members()[: self.small])


class CountedBlock(LinkedBlock):
    """The same, which adds up pointer writes and marker moves in ``counts``."""

    def __init__(self, *args, counts: dict[str, int], **options):
        self.counts = counts
        super().__init__(*args, **options)
        counts["writes"] += 2 * (self.end + 1)

    def _unlink(self, offset: int) -> None:
        super()._unlink(offset)
        self.counts["writes"] += 2

    def drop(self, offset: int) -> None:
        self.counts["moves"] += 0 if self.is_small(offset) else (offset == self.marker) + (self.small > 0)
        super().drop(offset)

    def restore(self, offset: int) -> None:
        before = self.marker
        super().restore(offset)
        self.counts["writes"] += 2
        self.counts["moves"] += self.marker != before

    def promote(self) -> None:
        super().promote()
        self.counts["moves"] += 1


def stable_order(values: Sequence) -> list[int]:
    return sorted(range(len(values)), key=lambda i: (values[i], i))


def lower_front(old: LinkedBlock, new: LinkedBlock) -> LinkedBlock:
    """The list with the least large item; the old one on ties, never an exhausted one."""
    if old.exhausted or new.exhausted:
        return new if old.exhausted else old
    return old if old.front() <= new.front() else new


def walk_pair(old: LinkedBlock, new: LinkedBlock, rank: int, steps: int, emit) -> None:
    """Slide from the full ``old`` to the full ``new`` block, which is rewound; ``emit(upper, lower)`` after each step."""
    for t in range(steps):
        old.drop(t)
        new.restore(t)
        while old.small + new.small < rank:
            lower_front(old, new).promote()
        lasts = [x for x in (old.last_small(), new.last_small()) if x is not None]
        emit(lower_front(old, new).front() if not (old.exhausted and new.exhausted) else None, max(lasts) if lasts else None)


def walk_series(values: Sequence, window: int, rank: int | None = None, *, orders=None, use_rank: bool = False, counts: dict[str, int] | None = None, debug: bool = False) -> list[tuple]:
    """(upper, lower) of every full window: the item of 0-based rank ``rank``, and the one before it.

    The chain of block pairs in one go: each block is built once as the new
    and once, full again, as the old one of the next pair.
    """
    n, rank = len(values), window // 2 if rank is None else rank
    out: list[tuple] = []
    if n < window:
        return out
    blocks = [list(values[i : i + window]) for i in range(0, n, window)]
    tail = len(blocks[-1])
    if tail < window:  # pads come after all real items and are never reached
        blocks[-1] += [blocks[-1][-1]] * (window - tail)

    def build(block: list, last: bool) -> LinkedBlock:
        order = (orders or stable_order)(block)
        if last and tail < window:
            order = [o for o in order if o < tail] + list(range(tail, window))
        positions = [0] * window
        for place, offset in enumerate(order):
            positions[offset] = place
        plain = use_rank or (last and tail < window)
        options = {"rank": positions if plain else None, "debug": debug}
        return LinkedBlock(block, order, rank, **options) if counts is None else CountedBlock(block, order, rank, counts=counts, **options)

    old = build(blocks[0], len(blocks) == 1)
    lower = old.last_small()
    out.append((old.front(), lower))
    for j in range(1, len(blocks)):
        new = build(blocks[j], j == len(blocks) - 1)
        new.rewind()
        walk_pair(old, new, rank, tail if j == len(blocks) - 1 else window, lambda upper, low: out.append((upper, low)))
        old = new
    return out
