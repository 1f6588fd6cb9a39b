"""What a sliding filter is asked for."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import types as T

ALIGN = ("leading", "trailing", "centered")
EDGES = ("valid", "partial", "pad", "reflect", "keep")
EVEN = ("mean", "lower", "upper")
NULLS = ("error", "drop", "poison")
KERNELS = ("auto", "scalar", "lockstep")
SORTERS = ("auto", "adaptive", "radix")
ROUTES = ("auto", "short_series", "blocks", "wide")


def names(columns: str | Sequence[str]) -> list[str]:
    return [columns] if isinstance(columns, str) else list(columns)


@dataclass(frozen=True)
class SlidingSpec:
    """One pass of the filter: order statistics ``ranks`` (0-based) of every window of ``window`` rows.

    ``outputs`` names one result column for each rank. A rank is *split* when
    its result is the mean of the item and the one before it (even medians and
    interpolated quantiles); ``shares`` holds the weight of the upper one.
    """

    value: str
    window: int
    order_by: tuple[str, ...]
    partition_by: tuple[str, ...] = ()
    ranks: tuple[int, ...] = ()
    outputs: tuple[str, ...] = ("med",)
    shares: tuple[float, ...] = (1.0,)
    align: str = "leading"
    edges: str = "valid"
    constant: object = None
    nulls: str = "error"
    kernel: str = "auto"
    sorter: str = "auto"
    route: str = "auto"
    ties: str = "stable"
    stride: int = 1
    extra: tuple[str, ...] = field(default=())
    #: Column that is -1 or 1 in rows without a value that come before or after all values, else 0.
    pads: str = ""

    def validate(self, schema: T.StructType) -> None:
        if self.window < 1:
            raise ValueError(f"window must be at least 1, not {self.window}")
        if not self.order_by:
            raise ValueError("a total order is needed: order_by names no column")
        for what, allowed in (("align", ALIGN), ("edges", EDGES), ("nulls", NULLS), ("kernel", KERNELS), ("sorter", SORTERS), ("route", ROUTES)):
            if getattr(self, what) not in allowed:
                raise ValueError(f"{what} must be one of {allowed}, not {getattr(self, what)!r}")
        if any(not 0 <= r < self.window for r in self.ranks):
            raise ValueError(f"ranks {self.ranks} do not fit a window of {self.window}")
        if self.stride < 1:
            raise ValueError("stride must be at least 1")
        if self.edges == "pad" and self.constant is None:
            raise ValueError("edges='pad' needs a constant")
        known = {f.name: f.dataType for f in schema}
        missing = [c for c in (self.value, *self.order_by, *self.partition_by, *self.extra) if c not in known]
        if missing:
            raise ValueError(f"no such columns: {missing}")
        kind = known[self.value]
        if isinstance(kind, (T.MapType, T.VariantType, T.BinaryType, T.ArrayType)):
            raise TypeError(f"{kind.simpleString()} has no order to filter by")
        if any(s != 1.0 for s in self.shares) and not isinstance(kind, T.NumericType):
            raise TypeError(f"values of type {kind.simpleString()} have no mean; use even='lower' or 'upper'")

    def result_type(self, schema: T.StructType, i: int) -> T.DataType:
        kind = schema[self.value].dataType
        return kind if self.shares[i] == 1.0 else T.DoubleType()

    def shift(self) -> int:
        """Rows from the first row of a window to the row that carries its result."""
        return {"leading": 0, "trailing": self.window - 1, "centered": self.window // 2}[self.align]


def median_rank(window: int, even: str) -> tuple[int, float]:
    """(rank, share of the upper item) of a window's median."""
    if window % 2 or even == "upper":
        return window // 2, 1.0
    return (window // 2 - 1, 1.0) if even == "lower" else (window // 2, 0.5)
