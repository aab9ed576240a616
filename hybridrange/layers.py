"""Layer arithmetic by exact integer powers, as Python functions and as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Enough powers of 2 for any count of rows.
POWERS = 62


def top_layer(n_u: int, o: int) -> int:
    """The least layer whose window, 2 * o**layer values, covers all unique values."""
    layer = 0
    while 2 * o**layer < n_u:
        layer += 1
    return layer


def landing_layer(n: int, o: int, top: int) -> int | None:
    """The layer whose window size is closest in ratio to the n values in range; None for an empty range."""
    if n <= 0:
        return None
    low = 0
    while 2 * o ** (low + 1) <= n:
        low += 1
    # of two neighbouring layers the one whose ratio of the smaller to the larger size is greater, compared crosswise
    a, b = 2 * o**low, 2 * o ** (low + 1)
    best = low if min(a, n) * max(b, n) >= min(b, n) * max(a, n) else low + 1
    return max(0, min(best, top))


def _powers(o: int) -> list[int]:
    out, layer = [], 0
    while 2 * o**layer < 2**POWERS:
        out.append(2 * o**layer)
        layer += 1
    return out


def top_layer_col(n_u: Column, o: int) -> Column:
    """How many layers have a window below n_u."""
    return F.size(F.filter(F.array(*[F.lit(x).cast("long") for x in _powers(o)]), lambda w: w < n_u))


def layer_count_col(n_u: Column, o: int) -> Column:
    return top_layer_col(n_u, o) + 1


def landing_layer_col(n: Column, o: int, top: Column) -> Column:
    sizes = F.array(*[F.lit(x).cast("long") for x in _powers(o)])
    low = F.greatest(F.lit(0), F.size(F.filter(sizes, lambda w: w <= n)) - 1)
    a, b = F.get(sizes, low).cast("double"), F.get(sizes, low + 1).cast("double")
    ratio = lambda w: F.least(w, n) / F.greatest(w, n)
    best = F.when(ratio(a) >= ratio(b), low).otherwise(low + 1)
    return F.when(n > 0, F.greatest(F.lit(0), F.least(best, top)))
