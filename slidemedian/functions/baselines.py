"""Other ways to slide a median over one array, each with its own window structure.

All take a list of comparable codes, the window k and the rank r, and return
the item of rank r of every full window.
"""

from __future__ import annotations

import bisect
import heapq
from collections.abc import Callable, Sequence

import numpy as np

from .links import walk_series


def sorted_blocks_scalar(values: Sequence[int], k: int, r: int) -> list[int]:
    return [upper for upper, _ in walk_series(values, k, r)]


def shifted_array(values: Sequence[int], k: int, r: int) -> list[int]:
    """One sorted array; binary search finds the gap to open and the one to close."""
    if len(values) < k:
        return []
    held = sorted(values[:k])
    out = [held[r]]
    for old, new in zip(values, values[k:], strict=False):
        leave, enter = bisect.bisect_left(held, old), bisect.bisect_left(held, new)
        if leave < enter:
            held[leave : enter - 1] = held[leave + 1 : enter]
            held[enter - 1] = new
        else:
            held[enter + 1 : leave + 1] = held[enter:leave]
            held[enter] = new
        out.append(held[r])
    return out


def resort_window(values: Sequence[int], k: int, r: int) -> list[int]:
    """Every window sorted afresh."""
    if len(values) < k:
        return []
    view = np.lib.stride_tricks.sliding_window_view(np.asarray(values), k)
    step = max(1, (1 << 22) // k)
    return [x for low in range(0, len(view), step) for x in np.sort(view[low : low + step], axis=1)[:, r].tolist()]


def select_window(values: Sequence[int], k: int, r: int) -> list[int]:
    """The item of every window by selection, without a full sort."""
    if len(values) < k:
        return []
    view = np.lib.stride_tricks.sliding_window_view(np.asarray(values), k)
    step = max(1, (1 << 22) // k)
    return [x for low in range(0, len(view), step) for x in np.partition(view[low : low + step], r, axis=1)[:, r].tolist()]


class _Heap:
    """Binary heap of (key, id) that knows where each id lies."""

    def __init__(self, sign: int, place: dict[int, tuple[object, int]]):
        self.sign, self.items, self.place = sign, [], place

    def _less(self, a, b) -> bool:
        return a < b if self.sign > 0 else b < a

    def _put(self, i: int, item) -> None:
        self.items[i] = item
        self.place[item[1]] = (self, i)

    def _settle(self, i: int) -> None:
        items, item = self.items, self.items[i]
        while i and self._less(item, items[(i - 1) // 2]):
            self._put(i, items[(i - 1) // 2])
            i = (i - 1) // 2
        while True:
            child = 2 * i + 1
            if child + 1 < len(items) and self._less(items[child + 1], items[child]):
                child += 1
            if child >= len(items) or not self._less(items[child], item):
                break
            self._put(i, items[child])
            i = child
        self._put(i, item)

    def push(self, item) -> None:
        self.items.append(item)
        self._settle(len(self.items) - 1)

    def remove(self, i: int):
        gone, last = self.items[i], self.items.pop()
        if i < len(self.items):
            self.items[i] = last
            self._settle(i)
        return gone

    def replace(self, i: int, item) -> None:
        self.items[i] = item
        self._settle(i)


def double_heap(values: Sequence[int], k: int, r: int) -> list[int]:
    """Greatest-first heap of the r smaller items, least-first heap of the others; the leaving item is replaced in place."""
    if len(values) < k:
        return []
    place: dict[int, tuple[_Heap, int]] = {}
    small, large = _Heap(-1, place), _Heap(1, place)
    for n, item in enumerate(sorted((v, i) for i, v in enumerate(values[:k]))):
        (small if n < r else large).push(item)
    out = [large.items[0][0]]
    for i in range(k, len(values)):
        heap, at = place.pop(i - k)
        heap.replace(at, (values[i], i))
        if small.items and large.items[0] < small.items[0]:
            down, up = large.items[0], small.items[0]
            small.replace(0, down)
            large.replace(0, up)
        out.append(large.items[0][0])
    return out


def double_heap_lazy(values: Sequence[int], k: int, r: int) -> list[int]:
    """Two heaps whose leaving items stay until they surface."""
    if len(values) < k:
        return []
    first = sorted((v, i) for i, v in enumerate(values[:k]))
    small = [(-v, -i) for v, i in first[:r]]
    large = first[r:]
    heapq.heapify(small)
    in_small = {i for _, i in first[:r]}
    out = [large[0][0]]
    for i in range(k, len(values)):
        gone, item = i - k, (values[i], i)
        while small and -small[0][1] <= gone:
            heapq.heappop(small)
        room = gone in in_small
        in_small.discard(gone)
        if small and item < (-small[0][0], -small[0][1]):
            heapq.heappush(small, (-item[0], -item[1]))
            in_small.add(i)
            surplus = 0 if room else 1
        else:
            heapq.heappush(large, item)
            surplus = -1 if room else 0
        while large and large[0][1] <= gone:
            heapq.heappop(large)
        if surplus > 0:
            while -small[0][1] <= gone:
                heapq.heappop(small)
            v, j = heapq.heappop(small)
            in_small.discard(-j)
            heapq.heappush(large, (-v, -j))
        elif surplus < 0:
            v, j = heapq.heappop(large)
            in_small.add(j)
            heapq.heappush(small, (-v, -j))
        while large[0][1] <= gone:
            heapq.heappop(large)
        out.append(large[0][0])
    return out


class _Tree:
    """Balanced search tree (treap) of distinct items with its least and greatest ones."""

    def __init__(self):
        self.root, self.state = None, 88172645463325252

    def _priority(self) -> int:
        x = self.state
        x ^= (x << 13) & 0xFFFFFFFFFFFFFFFF
        x ^= x >> 7
        x ^= (x << 17) & 0xFFFFFFFFFFFFFFFF
        self.state = x
        return x

    def add(self, item) -> None:
        fresh, node, at = [item, self._priority(), None, None], self.root, [None, None, self.root, None]
        parent, side = at, 2
        while node is not None and node[1] > fresh[1]:
            parent, side = node, 2 if item < node[0] else 3
            node = node[side]
        parent[side] = fresh
        low, high = (fresh, 2), (fresh, 3)
        while node is not None:
            if node[0] < item:
                low[0][low[1]] = node
                low, node = (node, 3), node[3]
            else:
                high[0][high[1]] = node
                high, node = (node, 2), node[2]
        low[0][low[1]] = high[0][high[1]] = None
        self.root = at[2]

    def remove(self, item) -> None:
        at = [None, None, self.root, None]
        parent, side, node = at, 2, self.root
        while node[0] != item:
            parent, side = node, 2 if item < node[0] else 3
            node = node[side]
        left, right = node[2], node[3]
        while left is not None and right is not None:
            if left[1] > right[1]:
                parent[side] = left
                parent, side, left = left, 3, left[3]
            else:
                parent[side] = right
                parent, side, right = right, 2, right[2]
        parent[side] = left if left is not None else right
        self.root = at[2]

    def end(self, side: int):
        node = self.root
        while node[side] is not None:
            node = node[side]
        return node[0]


def two_trees(values: Sequence[int], k: int, r: int) -> list[int]:
    """The window as two search trees: the r smaller items, and the others."""
    if len(values) < k:
        return []
    small, large, bound = _Tree(), _Tree(), None
    for n, item in enumerate(sorted((v, i) for i, v in enumerate(values[:k]))):
        (small if n < r else large).add(item)
    bound = large.end(2)
    out = [bound[0]]
    for i in range(k, len(values)):
        old, new = (values[i - k], i - k), (values[i], i)
        spare = 0
        if old < bound:
            small.remove(old)
            spare = 1
        if new < bound:
            small.add(new)
            spare -= 1
        else:
            large.add(new)
        if spare > 0:
            item = large.end(2)
            large.remove(item)
            small.add(item)
        elif spare < 0:
            item = small.end(3)
            small.remove(item)
            large.add(item)
        if not old < bound:
            large.remove(old)
        bound = large.end(2)
        out.append(bound[0])
    return out


METHODS: dict[str, Callable[[Sequence[int], int, int], list[int]]] = {
    "sorted_blocks_scalar": sorted_blocks_scalar,
    "two_trees": two_trees,
    "shifted_array": shifted_array,
    "double_heap": double_heap,
    "double_heap_lazy": double_heap_lazy,
    "resort_window": resort_window,
    "select_window": select_window,
}
