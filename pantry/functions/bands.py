"""Tolerance bands, traffic lights and folds as Column functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values, g per 100 g: (upper end of a range, absolute tolerance or None, share of the truth or None).
BANDS: dict[str, tuple[tuple[float, float | None, float | None], ...]] = {
    "fat": ((10, 1.5, None), (40, None, 0.2), (float("inf"), 8, None)),
    "protein": ((10, 2, None), (40, None, 0.2), (float("inf"), 8, None)),
    "sugar": ((10, 2, None), (40, None, 0.2), (float("inf"), 8, None)),
    "satfat": ((4, 0.8, None), (float("inf"), None, 0.2)),
    "sodium": ((0.5, 0.15, None), (float("inf"), None, 0.2)),
}
#: Fixed values, g per 100 g: medium above the first, high above the second.
LIGHTS = {"fat": (3, 17.5), "satfat": (1.5, 5), "sugar": (5, 22.5), "salt": (0.3, 1.5)}


def tolerance(nutrient: str, y: Column, scale: float = 1.0, bands=None) -> Column:
    rows = (bands or BANDS)[nutrient]
    width = lambda a, share: F.lit(float(a) * scale) if a is not None else F.abs(y) * (share * scale)
    out = width(*rows[-1][1:])
    for end, a, share in reversed(rows[:-1]):
        # the range that ends the table's middle includes its end
        out = F.when(y < end if a is not None else y <= end, width(a, share)).otherwise(out)
    return out


def width(nutrient: str, y: np.ndarray) -> np.ndarray:
    """``tolerance`` of an array."""
    rows = BANDS[nutrient]
    of = lambda a, share: np.full(len(y), float(a)) if a is not None else np.abs(y) * share
    out = of(*rows[-1][1:])
    for end, a, share in reversed(rows[:-1]):
        out = np.where(y < end if a is not None else y <= end, of(a, share), out)
    return out


def hit(nutrient: str, y: Column, guess: Column, scale: float = 1.0) -> Column:
    return (F.abs(y - guess) <= tolerance(nutrient, y, scale)).cast("double")


def traffic_light(nutrient: str, value: Column) -> Column:
    low, high = LIGHTS[nutrient]
    return F.when(value <= low, "low").when(value <= high, "medium").otherwise("high")


def salt(sodium: Column) -> Column:
    return sodium * 2.5


def fold(key: Column, k: int = 5) -> Column:
    """A fold by integer arithmetic that cannot overflow and that any SQL engine can repeat."""
    mixed = F.pmod(F.pmod(key, F.lit(1 << 31)) * 2654435761, F.lit(1 << 32))
    return F.pmod(F.floor(mixed / 65536).cast("long"), F.lit(k)).cast("int")
