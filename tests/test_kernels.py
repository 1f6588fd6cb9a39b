"""Kernels against brute force: exhaustive small cases, ties, extremes, invariants and costs."""

from itertools import permutations, product

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from slidemedian.functions import baselines, codes, sorting
from slidemedian.functions.kernels import window_ranks
from slidemedian.functions.links import LinkedBlock, NestingError, lower_front, stable_order, walk_series
from slidemedian.functions.lockstep import TOP, walk_pairs
from slidemedian.measures import walk_counts


def brute(values, k, r):
    return [sorted(values[i : i + k])[r] for i in range(len(values) - k + 1)]


def test_traced_example():
    assert [u for u, _ in walk_series([5, 1, 4, 2, 8, 3], 3)] == [4, 2, 4, 3]


def test_every_permutation_of_up_to_six():
    for n in range(1, 7):
        for values in permutations(range(n)):
            for k in range(1, n + 1):
                for r in range(k):
                    assert [u for u, _ in walk_series(values, k, r)] == brute(values, k, r)


def test_every_ternary_vector():
    for n in range(0, 8):
        for values in product(range(3), repeat=n):
            for k in range(1, n + 2):
                assert [u for u, _ in walk_series(values, k)] == brute(values, k, k // 2)


def test_reachable_branches():
    """The combinations of what leaves and what arrives, exhaustively: fourteen are reachable."""
    seen = set()
    for n, k in ((4, 2), (6, 3), (8, 4)):
        for values in product(range(3), repeat=n):
            for r in range(k):
                old = LinkedBlock(values[:k], stable_order(values[:k]), r)
                new = LinkedBlock(values[k:], stable_order(values[k:]), r)
                new.rewind()
                for t in range(k):
                    had = old.small > 0
                    leaving = "small" if old.is_small(t) else "marker" if t == old.marker else "large"
                    old.drop(t)
                    before = new.marker
                    arrives_small = new._before(t, before)
                    new.restore(t)
                    promoted = "none"
                    if old.small + new.small < r:
                        part = lower_front(old, new)
                        promoted = "old" if part is old else "new"
                        part.promote()
                    assert old.small + new.small == r
                    seen.add((had, leaving, arrives_small and new.small > 0 if had else arrives_small, promoted))
    with_small = {c for c in seen if c[0]}
    assert {c[1] for c in with_small} == {"small", "large", "marker"}
    assert all(c[3] != "none" for c in with_small), "one item is promoted whenever one small item was lost"
    assert all(c[3] == "none" for c in seen if not c[0]), "nothing is promoted when the old block held no small item"


def test_invariants_of_the_walk():
    rng = np.random.default_rng(2)
    for _ in range(200):
        k = int(rng.integers(1, 8))
        h, values = k // 2, rng.integers(0, 6, 2 * k).tolist()
        old, new = (LinkedBlock(v, stable_order(v), h, debug=True) for v in (values[:k], values[k:]))
        new.rewind()
        for t in range(k):
            old.drop(t)
            new.restore(t)
            while old.small + new.small < h:
                lower_front(old, new).promote()
            items = sorted([(values[i], 0, i) for i in old.members()] + [(values[k + i], 1, i) for i in new.members()])
            assert len(items) == k
            small = {(values[i], 0, i) for i in old.small_set()} | {(values[k + i], 1, i) for i in new.small_set()}
            assert small == set(items[:h])


def test_structure_after_build_and_rewind():
    block = LinkedBlock([3, 1, 2], [1, 2, 0], 1)
    assert block.members() == [1, 2, 0] and block.front() == 2 and block.small_set() == {1}
    block.rewind()
    assert block.members() == [] and block.small == 0 and block.exhausted


def test_restores_must_mirror_drops():
    block = LinkedBlock([3, 1, 2], [1, 2, 0], 1, debug=True)
    block.drop(0)
    block.drop(2)
    with pytest.raises(NestingError):
        block.restore(0)


def test_order_need_not_be_stable_when_ranks_are_compared():
    rng = np.random.default_rng(3)

    def shuffled(block):
        return sorted(range(len(block)), key=lambda i: (block[i], rng.random()))

    for _ in range(300):
        k = int(rng.integers(1, 7))
        values = rng.integers(0, 3, int(rng.integers(k, 25))).tolist()
        assert [u for u, _ in walk_series(values, k, orders=shuffled, use_rank=True)] == brute(values, k, k // 2)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.one_of(st.integers(-3, 3), st.sampled_from([TOP, -TOP - 1])), max_size=40), st.integers(1, 9), st.data())
def test_lockstep_over_many_series(values, k, data):
    cuts = sorted(data.draw(st.lists(st.integers(0, len(values)), max_size=4)))
    starts = np.array([0, *cuts, len(values)])
    ranks = sorted({data.draw(st.integers(0, k - 1)) for _ in range(2)})
    for kernel in ("lockstep", "scalar"):
        upper, below = window_ranks(np.array(values, dtype=np.int64), starts, k, ranks, lower=True, kernel=kernel)
        for a, b in zip(starts, starts[1:], strict=False):
            for end in range(a + k - 1, b):
                window = sorted(values[end - k + 1 : end + 1])
                for i, r in enumerate(ranks):
                    assert upper[i, end] == window[r]
                    if r:
                        assert below[i, end] == window[r - 1]


def test_exhausted_list_is_never_promoted():
    old, new = np.full((3, 1), TOP), np.full((3, 1), TOP)
    order = np.arange(3)[:, None]
    upper, _ = walk_pairs(old, order, new, order, [0, 1, 2])
    assert (upper == TOP).all()


@pytest.mark.parametrize("method", list(baselines.METHODS))
def test_contenders_agree(method):
    rng = np.random.default_rng(4)
    for _ in range(200):
        k = int(rng.integers(1, 9))
        values = rng.integers(0, int(rng.choice([3, 1000])), int(rng.integers(0, 40))).tolist()
        r = int(rng.integers(0, k))
        expected = brute(values, k, r) if len(values) >= k else []
        assert baselines.METHODS[method](values, k, r) == expected


@pytest.mark.parametrize("sorter", list(sorting.ORDERS))
def test_sorters_are_stable(sorter):
    rng = np.random.default_rng(5)
    for high in (2, 1000, 1 << 40):
        for matrix in (rng.integers(-high, high, (17, 9)), np.sort(rng.integers(0, high, (17, 9)), axis=0), -np.sort(rng.integers(0, 1 << 50, (17, 9)), axis=0)):
            assert (sorting.ORDERS[sorter](matrix) == matrix.argsort(axis=0, kind="stable")).all()


def test_radix_of_the_whole_range():
    matrix = np.array([[TOP], [-TOP - 1], [0], [TOP], [-1]])
    assert (sorting.radix_order(matrix) == matrix.argsort(axis=0, kind="stable")).all()


@settings(max_examples=100, deadline=None)
@given(st.lists(st.floats(width=64), min_size=2, max_size=20))
def test_codes_of_doubles_keep_order(values):
    coded = codes.encode(pa.array(values, pa.float64()))
    ordered = [values[i] for i in np.argsort(coded.codes, kind="stable")]
    finite = [v for v in ordered if v == v]
    assert finite == sorted(finite) and all(v != v for v in ordered[len(finite) :])
    back = coded.back(coded.codes).to_pylist()
    assert all(a == b or (a != a and b != b) for a, b in zip(values, back, strict=True))


@pytest.mark.parametrize(
    "array",
    [
        pa.array([3, -1, 7], pa.int32()),
        pa.array([1.5, -2.25], pa.float32()),
        pa.array(["b", "a", "ä"]),
        pa.array([True, False]),
        pa.array([10, 5], pa.timestamp("us")),
        pa.array([10, -5], pa.duration("us")),
        pa.array([3, 1], pa.date32()),
        pa.array(["1.25", "-3.50"]).cast(pa.decimal128(12, 2)),
    ],
)
def test_codes_round_trip(array):
    coded = codes.encode(array)
    assert coded.back(coded.codes).equals(array)


def test_costs_are_linear_and_bounded():
    rng = np.random.default_rng(6)
    for k in (3, 31, 301):
        counts = walk_counts(rng.integers(0, 1000, 3010).tolist(), k)
        assert counts["writes"] <= counts["write_bound"] and counts["moves"] <= counts["move_bound"]
