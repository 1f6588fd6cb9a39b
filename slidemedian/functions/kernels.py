"""Filters over whole ordered series held as arrays, and their Arrow form.

A task sees rows sorted by (series, order) in Arrow batches whose borders mean
nothing. The cutter collects rows up to a budget, never across a series, and
hands whole series on; all their blocks walk together.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from ..plans.spec import SlidingSpec
from .codes import encode
from .links import walk_series
from .lockstep import TOP, top_of, walk_pairs
from .sorting import ORDERS

#: Rows that the cutter collects before it runs the kernel; values in one lockstep call.
BATCH_ROWS, CALL_VALUES = 1 << 17, 1 << 20
#: Pairs from which all of them advance together.
LOCKSTEP_PAIRS = 16


def window_ranks(codes: np.ndarray, starts: np.ndarray, window: int, ranks: Sequence[int], *, lower: bool = False, kernel: str = "auto", sorter: str = "auto", ties: str = "stable", orders: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray | None]:
    """Codes (ranks, rows) of the window that *ends* at each row, for concatenated series.

    ``starts`` are the first rows of the series, and the number of rows at the
    end. Rows before the first full window of their series keep the greatest
    code. Codes are of 64 or 32 bits; the latter take half the memory.
    ``orders``, if given, are offsets in sorted order, block by block, so that
    nothing is sorted here.
    """
    rows, top = len(codes), top_of(codes)
    upper = np.full((len(ranks), rows), top, dtype=codes.dtype)
    below = upper.copy() if lower else None
    lengths = np.diff(starts)
    blocks = -(-lengths // window) * (lengths >= window)
    total = int(blocks.sum())
    if not total:
        return upper, below
    if window == 1:
        upper[:] = codes
        return upper, below
    first = np.repeat(starts[:-1], blocks)
    number = np.arange(total) - np.repeat(np.cumsum(blocks) - blocks, blocks)
    left = np.repeat(lengths, blocks) - number * window
    at = first + number * window
    # Longest series first would mix; blocks keep their place, pads follow the real rows of a last block.
    per_call = max(1, CALL_VALUES // window)
    low = 0
    while low < total:
        high = min(total, low + per_call)
        begin = low - 1 if low and number[low] else low
        place = at[begin:high] + np.arange(window)[:, None]
        real = np.arange(window)[:, None] < left[begin:high]
        matrix = np.where(real, codes[np.minimum(place, rows - 1)], codes.dtype.type(top))
        if orders is None:
            order = ORDERS[sorter](matrix)
        else:
            order = np.where(real, orders[np.minimum(place, rows - 1)], np.arange(window)[:, None])
        fresh = np.flatnonzero(number[low:high] == 0) + low - begin
        for i, rank in enumerate(ranks):
            lanes = at[begin:high][fresh] + window - 1
            upper[i, lanes] = matrix[order[rank, fresh], fresh]
            if below is not None and rank:
                below[i, lanes] = matrix[order[rank - 1, fresh], fresh]
        later = np.flatnonzero(number[begin:high] > 0)
        later = later[later > 0]
        if len(later):
            if kernel == "scalar" or (kernel == "auto" and len(later) < LOCKSTEP_PAIRS and window > 64):
                _scalar_pairs(codes, at[begin:high][later], np.minimum(left[begin:high][later], window), window, ranks, upper, below, ties)
            else:
                up, under = walk_pairs(matrix[:, later - 1], order[:, later - 1], matrix[:, later], order[:, later], ranks, lower)
                inside = real[:, later]
                target = place[:, later][inside]
                for i in range(len(ranks)):
                    upper[i, target] = up[i][inside]
                    if below is not None:
                        below[i, target] = under[i][inside]
        low = high
    return upper, below


def _scalar_pairs(codes, at, counts, window, ranks, upper, below, ties) -> None:
    for begin, count in zip(at, counts, strict=True):
        values = codes[begin - window : begin + count].tolist()
        for i, rank in enumerate(ranks):
            pairs = walk_series(values, window, rank, use_rank=ties == "rank")[1:]
            upper[i, begin : begin + count] = [p[0] for p in pairs]
            if below is not None and rank:
                below[i, begin : begin + count] = [p[1] for p in pairs]


def partial_ranks(codes: np.ndarray, window: int, share_rank, at_start: bool) -> list[tuple[int, int | None]]:
    """(upper, lower) of the incomplete windows at one end of a series, shortest last at the end."""
    inside = min(window - 1, len(codes))
    part = codes[:inside] if at_start else codes[len(codes) - inside :][::-1]
    held: list[int] = []
    out = []
    for code in part.tolist():
        bisect.insort(held, code)
        rank = share_rank(len(held))
        out.append((held[rank], held[rank - 1] if rank else None))
    return out if at_start else out[::-1]


def _extended(codes: np.ndarray, spec: SlidingSpec, constant: int | None) -> tuple[np.ndarray, int]:
    """A series with the rows that the edge policy puts around it, and how many come before."""
    before, after = spec.shift(), spec.window - 1 - spec.shift()
    if spec.edges == "pad":
        return np.concatenate([np.full(before, constant), codes, np.full(after, constant)]), before
    return np.pad(codes, (before, after), mode="symmetric"), before


def _scaled_rank(spec: SlidingSpec, i: int):
    """Rank among p members for incomplete windows, as for the full one."""
    full, share, window = spec.ranks[i], spec.shares[i], spec.window
    if share == 0.5 or full == window // 2:
        return lambda p: p // 2
    return lambda p: min(p - 1, round(full * (p - 1) / max(1, window - 1)))


def filter_series(table: pa.Table, cuts: np.ndarray, spec: SlidingSpec, halo: np.ndarray | None = None) -> pa.Table:
    """Rows of ``table`` that carry a result, with ``pos`` and the outputs added.

    ``cuts`` bound the series. Where ``halo`` is true for a series, its first
    window belongs to the tile before and is not given; ``pos`` then comes from
    the table.
    """
    column = table.column(spec.value)
    poisoned = padding = None
    if spec.pads:
        padding = np.asarray(table.column(spec.pads))
        if column.null_count != np.count_nonzero(padding):
            raise ValueError(f"rows without {spec.value} must be pads, and no others")
        some = column.drop_null()
        column = pc.fill_null(column, some[0]) if len(some) else pa.chunked_array([pa.array([0] * len(column)).cast(column.type)])
    elif column.null_count:
        if spec.nulls == "error":
            raise ValueError(f"column {spec.value} holds nulls; choose nulls='drop' or 'poison'")
        gone = np.asarray(pc.is_null(column))
        running = np.concatenate([[0], np.cumsum(gone)])
        poisoned = running[1:] - running[np.maximum(0, np.arange(len(gone)) - spec.window + 1)] > 0
        column = pc.fill_null(column, pc.min(column)) if pc.min(column).is_valid else pa.chunked_array([pa.array([0] * len(column)).cast(column.type)])
    coded = encode(column)
    codes, rows = coded.codes, table.num_rows
    if padding is not None:
        # The ends of the code range: a value with the same code is that extreme itself.
        codes = np.where(padding < 0, -TOP - 1, np.where(padding > 0, TOP, codes))
    starts = np.asarray(cuts)
    lengths = np.diff(starts)
    series_start = np.repeat(starts[:-1], lengths)
    inner = np.arange(rows) - series_start
    need_lower = any(s != 1.0 for s in spec.shares)
    shift, window = spec.shift(), spec.window
    if spec.edges in ("pad", "reflect"):
        constant = int(encode(pa.array([spec.constant], coded.kind)).codes[0]) if spec.edges == "pad" else None
        parts = [_extended(codes[a:b], spec, constant) for a, b in zip(starts, starts[1:], strict=False)]
        long_starts = np.concatenate([[0], np.cumsum([len(p) for p, _ in parts])])
        upper, below = window_ranks(np.concatenate([p for p, _ in parts]), long_starts, window, spec.ranks, lower=need_lower, kernel=spec.kernel, sorter=spec.sorter, ties=spec.ties)
        ends = np.concatenate([long_starts[i] + window - 1 + np.arange(n) for i, n in enumerate(lengths)]).astype(np.int64) if rows else np.zeros(0, np.int64)
        upper, below = upper[:, ends], None if below is None else below[:, ends]
        carries = np.arange(rows)
        whole = np.ones(rows, dtype=bool)
    else:
        upper, below = window_ranks(codes, starts, window, spec.ranks, lower=need_lower, kernel=spec.kernel, sorter=spec.sorter, ties=spec.ties)
        ends = np.flatnonzero(inner >= window - 1)
        if halo is not None:
            ends = ends[(inner[ends] > window - 1) | ~np.repeat(halo, lengths)[ends]]
        carries = ends - (window - 1) + shift
        whole = np.ones(len(ends), dtype=bool)
        upper, below = upper[:, ends], None if below is None else below[:, ends]
        if spec.edges in ("partial", "keep"):
            extra_rows, extra_upper, extra_below = [], [[] for _ in spec.ranks], [[] for _ in spec.ranks]
            for a, b in zip(starts, starts[1:], strict=False):
                series = codes[a:b]
                if b - a < window:
                    # No full window: a row's window is what of it lies in the series.
                    spans = [(max(0, i - shift), min(b - a, i - shift + window)) for i in range(b - a)]
                    targets = list(range(b - a))
                else:
                    head = [(0, i - shift + window) for i in range(shift)]
                    tail = [(i - shift, b - a) for i in range(b - a - (window - 1 - shift), b - a)]
                    spans, targets = head + tail, [*range(shift), *range(b - a - (window - 1 - shift), b - a)]
                ordered = _span_items(series, spans, spec) if spec.edges == "partial" else None
                for n, row in enumerate(targets):
                    extra_rows.append(a + row)
                    for i in range(len(spec.ranks)):
                        up, low = ordered[i][n] if ordered is not None else (int(series[row]), int(series[row]))
                        extra_upper[i].append(up)
                        extra_below[i].append(low if low is not None else up)
            if extra_rows:
                carries = np.concatenate([carries, extra_rows])
                upper = np.concatenate([upper, np.array(extra_upper)], axis=1)
                below = None if below is None else np.concatenate([below, np.array(extra_below)], axis=1)
                whole = np.ones(len(carries), dtype=bool)
                order = np.argsort(carries, kind="stable")
                carries, upper, below = carries[order], upper[:, order], None if below is None else below[:, order]
    position = np.asarray(table.column("pos")) if halo is not None else inner
    pick = np.arange(len(carries))
    if spec.stride > 1:
        window_start = position[carries] - shift if spec.edges == "valid" else position[carries]
        pick = np.flatnonzero(window_start % spec.stride == 0)
        carries, upper, below = carries[pick], upper[:, pick], None if below is None else below[:, pick]
    if poisoned is not None:
        whole = ~poisoned[np.minimum(carries - shift + window - 1, rows - 1)]
    out = table.select([*spec.partition_by, *spec.order_by, *spec.extra]).take(pa.array(carries))
    out = out.append_column("pos", pa.array(position[carries].astype(np.int64)))
    mask = whole if poisoned is not None else None
    for i, name in enumerate(spec.outputs):
        share = spec.shares[i]
        if share == 1.0:
            out = out.append_column(name, coded.back(upper[i], mask))
        else:
            up, low = coded.as_double(upper[i]), coded.as_double(below[i])
            result = low + (up - low) * share if share != 0.5 else (low + up) / 2
            # A partial window of odd length has one middle item.
            if spec.edges == "partial" and share == 0.5:
                odd = _member_counts(carries, starts, shift, window) % 2 == 1
                result = np.where(odd, up, result)
            out = out.append_column(name, pa.array(result, pa.float64(), mask=None if mask is None else ~mask))
    return out


def _member_counts(rows: np.ndarray, starts: np.ndarray, shift: int, window: int) -> np.ndarray:
    series = np.searchsorted(starts, rows, side="right") - 1
    low = np.maximum(starts[series], rows - shift)
    return np.minimum(starts[series + 1], rows - shift + window) - low


def _span_items(series: np.ndarray, spans: list[tuple[int, int]], spec: SlidingSpec) -> list[list[tuple[int, int | None]]]:
    """Items of incomplete windows, whose bounds move on one by one."""
    rankings = [_scaled_rank(spec, i) for i in range(len(spec.ranks))]
    out: list[list[tuple[int, int | None]]] = [[] for _ in rankings]
    held, a, b = [], 0, 0
    for low, high in spans:
        if low >= b or low < a:
            held, a, b = sorted(series[low:high].tolist()), low, high
        while b < high:
            bisect.insort(held, int(series[b]))
            b += 1
        while a < low:
            held.pop(bisect.bisect_left(held, int(series[a])))
            a += 1
        for items, ranking in zip(out, rankings, strict=True):
            rank = ranking(len(held))
            items.append((held[rank], held[rank - 1] if rank else None))
    return out


def series_cuts(table: pa.Table, keys: Sequence[str]) -> np.ndarray:
    """First rows of the series of a sorted table, and its length."""
    rows = table.num_rows
    if not keys or rows == 0:
        return np.array([0, rows] if rows else [0])
    change = np.zeros(rows, dtype=bool)
    change[0] = True
    for key in keys:
        column = table.column(key).combine_chunks()
        same = pc.fill_null(pc.equal(column[1:], column[:-1]), False)
        both = pc.and_(pc.is_null(column[1:]), pc.is_null(column[:-1]))
        change[1:] |= ~np.asarray(pc.or_(same, both))
    return np.append(np.flatnonzero(change), rows)


def whole_series(batches: Iterator[pa.RecordBatch], keys: Sequence[str], budget: int = BATCH_ROWS) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables of whole series with their cuts, from batches cut anywhere."""
    waiting: list[pa.RecordBatch] = []
    count = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        waiting.append(batch)
        count += batch.num_rows
        if count < budget:
            continue
        table = pa.Table.from_batches(waiting)
        cuts = series_cuts(table, keys)
        if len(cuts) > 2:
            last = int(cuts[-2])
            yield table.slice(0, last), cuts[:-1]
            waiting, count = table.slice(last).to_batches(), table.num_rows - last
        budget = max(budget, count + budget // 2) if count >= budget else BATCH_ROWS
    if waiting:
        table = pa.Table.from_batches(waiting)
        yield table, series_cuts(table, keys)


def filter_batches(spec: SlidingSpec, keys: Sequence[str], halo_column: str | None = None):
    """The function for ``mapInArrow`` over rows sorted by series and order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, cuts in whole_series(batches, keys):
            halo = None if halo_column is None else np.asarray(table.column(halo_column))[cuts[:-1]].astype(bool)
            yield from filter_series(table, cuts, spec, halo).combine_chunks().to_batches()

    return run
