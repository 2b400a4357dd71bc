"""Weights of candidate pairs, all closed-form expressions on tile ranges, boxes and point counts.

A box meets a rectangle of tiles, so the tiles that two boxes share need no counting.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SCHEMES = ("cf", "js", "chi2", "mbro", "isp")


def _n(p: str) -> Column:
    return (F.col(f"{p}_x2") - F.col(f"{p}_x1") + 1) * (F.col(f"{p}_y2") - F.col(f"{p}_y1") + 1)


def cf() -> Column:
    """Tiles that both boxes meet."""
    w = F.least("s_x2", "t_x2") - F.greatest("s_x1", "t_x1") + 1
    h = F.least("s_y2", "t_y2") - F.greatest("s_y1", "t_y1") + 1
    return F.greatest(F.lit(0), w) * F.greatest(F.lit(0), h)


def js() -> Column:
    """Shared tiles over all tiles of the two."""
    k = cf()
    return k.cast("double") / (_n("s") + _n("t") - k)


def chi2(universe: int, signed: bool = False) -> Column:
    """Pearson's test on tiles in both, one or none of the two; 0 where a margin is 0."""
    n = F.lit(float(universe))
    a = cf().cast("double")
    b, c = _n("s") - a, _n("t") - a
    d = n - _n("s") - _n("t") + a
    margins = (a + b) * (c + d) * (a + c) * (b + d)
    value = F.when(margins > 0, n * F.pow(a * d - b * c, F.lit(2)) / margins).otherwise(0.0)
    return F.when(a * n < _n("s") * _n("t"), -value).otherwise(value) if signed else value


def mbro() -> Column:
    """Area common to the boxes over the area of their union; 0 where the union has none."""
    w = F.greatest(F.lit(0.0), F.least("s_xmax", "t_xmax") - F.greatest("s_xmin", "t_xmin"))
    h = F.greatest(F.lit(0.0), F.least("s_ymax", "t_ymax") - F.greatest("s_ymin", "t_ymin"))
    area = lambda p: (F.col(f"{p}_xmax") - F.col(f"{p}_xmin")) * (F.col(f"{p}_ymax") - F.col(f"{p}_ymin"))
    union = area("s") + area("t") - w * h
    return F.when(union > 0, w * h / union).otherwise(0.0)


def isp() -> Column:
    """Inverse sum of the points of the two."""
    return 1.0 / (F.col("s_npoints") + F.col("t_npoints"))


def weight(scheme: str, universe: int = 0) -> Column:
    return {"cf": lambda: cf().cast("double"), "js": js, "chi2": lambda: chi2(universe), "mbro": mbro, "isp": isp}[scheme]()


def scored(pairs, primary: str = "js", secondary: str | None = None, universe: int = 0, keep: tuple[str, ...] = ()):
    """(sid, tid, weight, second, and the columns in keep): the primary scheme, ties broken by the secondary (0 without one)."""
    second = weight(secondary, universe) if secondary else F.lit(0.0)
    return pairs.select("sid", "tid", weight(primary, universe).alias("weight"), second.alias("second"), *keep)
