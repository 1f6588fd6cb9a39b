"""Order-preserving 64-bit codes.

The kernels compare and copy integers only. Every type with an order gets a
code: integers and times their own number, floating point its sign-folded bit
pattern (NaN greatest, both zeros equal), decimals their unscaled number, other
types their rank among the values at hand.
"""

from __future__ import annotations

from dataclasses import dataclass
from decimal import Decimal

import numpy as np
import pyarrow as pa

_SIGN_OFF = np.int64(0x7FFFFFFFFFFFFFFF)


def fold_doubles(values: np.ndarray) -> np.ndarray:
    """Monotone and invertible map of doubles to integers."""
    clean = np.where(np.isnan(values), np.nan, values + 0.0)
    bits = clean.view(np.int64).copy()
    bits[np.isnan(clean)] = np.float64(np.nan).view(np.int64) & _SIGN_OFF
    return np.where(bits < 0, bits ^ _SIGN_OFF, bits)


def unfold_doubles(codes: np.ndarray) -> np.ndarray:
    return np.where(codes < 0, codes ^ _SIGN_OFF, codes).view(np.float64)


@dataclass
class Coded:
    """Codes of a column and the way back."""

    codes: np.ndarray
    kind: pa.DataType
    lookup: list | None = None

    @property
    def averages(self) -> bool:
        """The mean of two values has a meaning in floating point."""
        return pa.types.is_integer(self.kind) or pa.types.is_floating(self.kind) or pa.types.is_decimal(self.kind)

    def back(self, codes: np.ndarray, valid: np.ndarray | None = None) -> pa.Array:
        """Values of codes, null where not valid."""
        mask = None if valid is None else ~valid
        if self.lookup is not None:
            usable = np.clip(codes, 0, max(0, len(self.lookup) - 1))
            values = [self.lookup[i] if mask is None or not mask[n] else None for n, i in enumerate(usable)]
            return pa.array(values, self.kind)
        if pa.types.is_floating(self.kind):
            return pa.array(unfold_doubles(codes), pa.float64(), mask=mask).cast(self.kind)
        if pa.types.is_decimal(self.kind):
            scale = Decimal(1).scaleb(-self.kind.scale)
            return pa.array([None if mask is not None and mask[i] else int(c) * scale for i, c in enumerate(codes)], self.kind)
        if pa.types.is_integer(self.kind):
            return pa.array(np.where(mask, 0, codes) if mask is not None else codes, pa.int64(), mask=mask).cast(self.kind)
        if pa.types.is_date32(self.kind):
            return pa.array(np.where(mask, 0, codes) if mask is not None else codes, pa.int64(), mask=mask).cast(pa.int32()).cast(self.kind)
        return pa.array(codes, pa.int64(), mask=mask).cast(self.kind)

    def as_double(self, codes: np.ndarray) -> np.ndarray:
        if pa.types.is_floating(self.kind):
            return unfold_doubles(codes)
        if pa.types.is_decimal(self.kind):
            return codes / 10.0**self.kind.scale
        return codes.astype(np.float64)


def encode(column: pa.Array | pa.ChunkedArray) -> Coded:
    """Codes of a column without nulls."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    kind = column.type
    if pa.types.is_floating(kind):
        return Coded(fold_doubles(np.asarray(column.cast(pa.float64()))), kind)
    if pa.types.is_integer(kind):
        return Coded(np.asarray(column.cast(pa.int64())), kind)
    if pa.types.is_date32(kind):
        return Coded(np.asarray(column.cast(pa.int32())).astype(np.int64), kind)
    if pa.types.is_timestamp(kind) or pa.types.is_duration(kind):
        return Coded(np.asarray(column.cast(pa.int64())), kind)
    if pa.types.is_decimal(kind) and kind.precision <= 18:
        return Coded(np.array([int(v.scaleb(kind.scale)) for v in column.to_pylist()], dtype=np.int64), kind)
    values = column.to_pylist()
    lookup = sorted(set(values))
    rank = {v: i for i, v in enumerate(lookup)}
    return Coded(np.array([rank[v] for v in values], dtype=np.int64), kind, lookup)
