"""Column expressions of the relevance score and of reproducible coins.

Weights are held as integer millionths, distances and counts as integers, so that sums have no order and
every engine gets the same doubles.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MILLION = 1_000_000


def _share(alpha: float) -> tuple[float, float]:
    if not 0 <= alpha <= 1:
        raise ValueError(f"alpha must lie in [0, 1], not {alpha}")
    return alpha, 1 - alpha


def weight_millionths(tf: Column, idf_m: Column, norm2: Column) -> Column:
    """Site-normalised TF-IDF weight in millionths."""
    return F.round(F.lit(float(MILLION)) * (tf * idf_m) / F.sqrt(norm2)).cast("long")


def gain(social: Column, text_m: Column, alpha: float) -> Column:
    """alpha * social + (1 - alpha) * text, the text in millionths."""
    a, b = _share(alpha)
    return F.lit(a) * social + F.lit(b) * (text_m / F.lit(float(MILLION)))


def ratio_score(gained: Column, distance: Column, least: float = 1.0) -> Column:
    """Gain over distance; a distance below ``least`` counts as that."""
    return gained / F.greatest(distance, F.lit(least))


def linear_score(gained: Column, distance: Column, beta: float, farthest: Column) -> Column:
    """beta * gain + (1 - beta) * nearness, nearness falling from 1 to 0 at the farthest distance."""
    near, far = _share(beta)
    return F.lit(near) * gained + F.lit(far) * (F.lit(1.0) - distance / farthest)


def coin(*parts: Column) -> Column:
    """A 32-bit number from the md5 of the parts: the same in every engine, whatever the partitioning."""
    text = F.concat_ws("|", *(p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")
