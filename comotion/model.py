"""Schemas and parameters shared by all modules."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

SAMPLES = "oid long, t long, x double, y double"
SEGMENTS = "oid long, seg_no int, t0 long, t1 long, x0 double, y0 double, x1 double, y1 double, tol double, n_src int"
CLUSTERS = "t long, cid long, members array<long>"
CONVOYS = "members array<long>, t_start long, t_end long, lifetime long"


@dataclass(frozen=True)
class ConvoyParams:
    """m objects at least, k consecutive ticks at least, density radius e."""

    m: int
    k: int
    e: float

    def __post_init__(self):
        if self.m < 1 or self.k < 1 or self.e < 0:
            raise ValueError("needs m >= 1, k >= 1 and e >= 0")

    def but(self, **changes) -> ConvoyParams:
        return replace(self, **changes)


def require(df: DataFrame, *columns: str) -> DataFrame:
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")
    return df
