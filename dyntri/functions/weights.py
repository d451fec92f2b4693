"""Inverse pair probabilities, as exact numerators over one denominator for each method."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Positions of a wedge's two edges: both in the open set, in one sealed set, in two sealed sets, one open and one sealed.
OPEN, SAME_SEALED, TWO_SEALED, OPEN_SEALED = 1, 2, 3, 4


def _big(x: Column | int) -> Column:
    return x.cast("decimal(18,0)") if isinstance(x, Column) else whole(x, 18)


def whole(x: int, digits: int = 38) -> Column:
    """An integer constant of any size; products of budgets pass 64 bits."""
    if abs(x) >= 10**digits:
        raise OverflowError(f"{x} has more than {digits} digits")
    return F.lit(str(x)).cast(f"decimal({digits},0)")


def seal_point(k: int, ratio_floor: float) -> int:
    """The last population size with k / size >= ratio_floor, by exact division."""
    return int(Fraction(k) / Fraction(str(ratio_floor)))


def fixed_weight(k: int, t: Column) -> Column:
    """Numerator over k (k - 1) of the inverse probability that a reservoir of k out of t holds two given edges."""
    return F.when(t > k, _big(t) * _big(t - 1)).otherwise(_big(k) * _big(k - 1)).cast("decimal(38,0)")


#: For random pairing, t is the number of slots opened so far.
paired_weight = fixed_weight


def pair_weight(kind: Column, k: int, t: Column, t_star: int) -> Column:
    """Numerator over k^2 (k - 1) for the adaptive pool: t is the population of the open set, t_star of a sealed one."""
    return (
        F.when(kind == OPEN, F.when(t > k, (_big(t) * _big(t - 1)).cast("decimal(26,0)") * whole(k, 12)).otherwise(whole(k * k * (k - 1))).cast("decimal(38,0)"))
        .when(kind == SAME_SEALED, whole(k * t_star * (t_star - 1)))
        .when(kind == TWO_SEALED, whole((k - 1) * t_star * t_star))
        .otherwise((F.greatest(_big(t), _big(k)).cast("decimal(13,0)") * whole((k - 1) * t_star, 25)).cast("decimal(38,0)"))
    )


def nominal_weight(kind: Column, k: int, t: Column, ratio_floor: float) -> Column:
    """The inverse probability with the floor itself as a sealed set's ratio."""
    r = float(ratio_floor)
    one = F.when(t > k, t * (t - 1) / F.lit(float(k * (k - 1)))).otherwise(1.0)
    return F.when(kind == OPEN, one).when(kind == SAME_SEALED, (k / r - 1) / (r * (k - 1))).when(kind == TWO_SEALED, 1 / r**2).otherwise(F.greatest(t / F.lit(float(k)), F.lit(1.0)) / r)
