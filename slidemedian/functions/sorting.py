"""Piecewise sorts of a (k, blocks) matrix of codes: the exchangeable first phase.

Each gives the stable ascending order of every column.
"""

from __future__ import annotations

import numpy as np


def adaptive_order(codes: np.ndarray) -> np.ndarray:
    """A stable merge sort, which takes existing runs as they are."""
    return codes.argsort(axis=0, kind="stable")


def radix_order(codes: np.ndarray) -> np.ndarray:
    """Stable passes over 16-bit digits of the codes above the least one."""
    low = codes.min()
    reduced = codes.astype(np.uint64) - np.uint64(int(low) & 0xFFFFFFFFFFFFFFFF)
    span = int(codes.max()) - int(low)
    order = (reduced & np.uint64(0xFFFF)).astype(np.uint16).argsort(axis=0, kind="stable")
    for shift in range(16, 64, 16):
        if span >> shift == 0:
            break
        digit = np.take_along_axis((reduced >> np.uint64(shift)).astype(np.uint16), order, axis=0)
        order = np.take_along_axis(order, digit.argsort(axis=0, kind="stable"), axis=0)
    return order


def detected_order(codes: np.ndarray) -> np.ndarray:
    """Choose by the traits of the matrix: sorted, strictly descending, small range, or else."""
    k = codes.shape[0]
    if k == 1:
        return np.zeros_like(codes)
    rises = codes[1:] >= codes[:-1]
    if rises.all():
        return np.broadcast_to(np.arange(k)[:, None], codes.shape)
    if not rises.any():
        return np.broadcast_to(np.arange(k - 1, -1, -1)[:, None], codes.shape)
    descents = (~rises).sum()
    if descents * 8 < codes.size:
        return adaptive_order(codes)
    return radix_order(codes) if int(codes.max()) - int(codes.min()) < 1 << 16 else adaptive_order(codes)


ORDERS = {"adaptive": adaptive_order, "radix": radix_order, "auto": detected_order}


def disorder(codes: np.ndarray) -> dict[str, np.ndarray]:
    """Descents and ascending runs of each column."""
    descents = (codes[1:] < codes[:-1]).sum(axis=0)
    return {"descents": descents, "runs": descents + 1}
