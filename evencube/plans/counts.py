"""How a box shares its points between two halves, and how deep that goes."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Sides this close to the longest, relatively, count as equally long.
TIE = 1e-12


def smaller_share(count: int, avoid_odd: bool = True) -> int:
    """Points of the smaller part; an even box of six or more does not split into two odd ones."""
    half = count // 2
    return half - (avoid_odd and count >= 6 and count % 2 == 0 and half % 2 == 1)


def smaller_share_np(count: np.ndarray, avoid_odd: bool = True) -> np.ndarray:
    half = count // 2
    return half - ((count >= 6) & (count % 2 == 0) & (half % 2 == 1)) if avoid_odd else half


def smaller_share_col(count: Column, avoid_odd: bool = True) -> Column:
    half = F.floor(count / 2)
    return half - F.when((count >= 6) & (count % 2 == 0) & (half % 2 == 1), F.lit(1)).otherwise(F.lit(0)) if avoid_odd else half


def smaller_share_sql(count: str, avoid_odd: bool = True) -> str:
    half = f"({count} // 2)"
    return f"({half} - CASE WHEN {count} >= 6 AND {count} % 2 = 0 AND {half} % 2 = 1 THEN 1 ELSE 0 END)" if avoid_odd else half


@lru_cache(maxsize=4096)
def depth(count: int, avoid_odd: bool = True) -> int:
    """Splits between the whole box and its deepest single-point box."""
    level, counts = 0, {count}
    while max(counts) > 1:
        counts = {part for c in counts if c > 1 for a in (smaller_share(c, avoid_odd),) for part in (a, c - a)}
        level += 1
    return level


def frontier(count: int, wanted: int, avoid_odd: bool = True) -> int:
    """Levels after which a tree of ``count`` leaves has at least ``wanted`` nodes, or is finished."""
    nodes, level = [count], 0
    while len(nodes) < wanted and max(nodes) > 1:
        nodes = [part for c in nodes for part in ((smaller_share(c, avoid_odd), c - smaller_share(c, avoid_odd)) if c > 1 else (c,))]
        level += 1
    return level
