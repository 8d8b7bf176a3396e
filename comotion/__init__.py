"""Groups of moving objects that stay density-connected, mined with Spark."""

from __future__ import annotations

from pyspark.sql import DataFrame

METHODS = ("auto", "exact", "classic", "balanced", "timed")
#: Dense rows to each sample from which the filter is worth its passes.
GAPPY = 20
#: Ticks to a task of the exact miner where histories are that gappy.
TICKS = 128


def convoys(samples: DataFrame, m: int, k: int, e: float, method: str = "auto", **settings) -> DataFrame:
    """(members, t_start, t_end, lifetime) of at least ``m`` objects over at least ``k`` ticks under radius ``e``.

    ``auto`` mines exactly where interpolation adds little, and filters with timed segments where histories are gappy (one
    pass over the samples decides); ``exact`` then interpolates inside the tasks. ``settings`` go to the method: delta, lam,
    tolerance, mode, clipped; semantics, engine, ticks.
    """
    from comotion.model import ConvoyParams
    from comotion.operators.measures import densify_growth
    from comotion.plans import sfr, snapshot_miner

    if method not in METHODS:
        raise ValueError(f"method is one of {METHODS}")
    p = ConvoyParams(m, k, e)
    if method in ("auto", "exact"):
        n = densify_growth(samples).first()
        gappy = bool(n.n_samples) and n.n_dense > GAPPY * n.n_samples
        method = "timed" if gappy and method == "auto" else "exact"
    if method == "exact":
        return snapshot_miner.mine(samples, p, **(({"ticks": TICKS} if gappy else {}) | settings))
    return sfr.mine(samples, p, method, **settings)
