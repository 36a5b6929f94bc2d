"""Settings of an index and of a query."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class IndexConfig:
    """How an index is built; the defaults suit large sets."""

    base: str = "adaptive_linear"  # or btree, spline_radix; two_stage is refused
    leaf_policy: str = "fixed"  # blocks of global rank; adaptive: by model error; banded: blocks of a range partition, one pass
    leaf_cap: int = 4096
    max_err: int = 64
    fanout: int = 128
    radix_bits: int = 10
    fill: float = 0.7  # share of a leaf that a build uses; the rest is slack for inserts
    sort_key: str = "zmin"  # or zmax, for Contains without augmentation
    augment: bool = True
    m: int | None = 10_000  # intervals of a piece; None: one piece
    grouping: str = "count"  # or leaf: a piece covers one leaf
    outlier_q: float = 0.99
    exact_threshold: bool = True
    partitions: int | None = None
    units_per_cell: int = 1


@dataclass(frozen=True)
class QueryOptions:
    """Which filters a search uses, and where it is planned."""

    leaf_skip: bool = True
    mbr_filter: bool = False
    refine: bool = True
    resident: bool | None = None  # None: on the driver where windows and directory are within their bounds
