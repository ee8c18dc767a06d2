"""From pair similarities or scores to matches, in both directions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def select(pairs: DataFrame, by: str, rule: str = "best", theta: float | None = None, m: int = 1, score: str = "sim", keys: tuple[str, ...] = ()) -> DataFrame:
    """Matches of each ``by`` ('u' or 'v'): pairs of at least theta (rule threshold), of those the best (ties stay) or the m first (ties by the smaller id)."""
    if theta is not None:
        pairs = pairs.where(F.col(score) >= theta)
    if rule == "threshold":
        return pairs
    other = "v" if by == "u" else "u"
    if rule == "best":
        place = F.rank().over(Window.partitionBy(*keys, by).orderBy(F.col(score).desc()))
        return pairs.withColumn("_place", place).where("_place = 1").drop("_place")
    if rule == "top":
        place = F.row_number().over(Window.partitionBy(*keys, by).orderBy(F.col(score).desc(), other))
        return pairs.withColumn("_place", place).where(F.col("_place") <= m).drop("_place")
    raise ValueError(f"no rule {rule}")


def forward(pairs: DataFrame, **how) -> DataFrame:
    """Matches of the left channel's entities."""
    return select(pairs, "u", **how)


def backward(pairs: DataFrame, **how) -> DataFrame:
    """Matches of the right channel's entities."""
    return select(pairs, "v", **how)


def reconcile(pairs: DataFrame, how: str = "intersect", rule: str = "best", theta: float | None = None, m: int = 1, score: str = "sim", keys: tuple[str, ...] = ()) -> DataFrame:
    """Pairs that both directions found (intersect), either (union), or one of them (forward, backward).

    Similarities are ranked both ways on one frame, so they are neither computed twice nor joined again.
    """
    if theta is not None:
        pairs = pairs.where(F.col(score) >= theta)
    if rule == "threshold":
        return pairs
    if rule == "best":
        fwd = F.rank().over(Window.partitionBy(*keys, "u").orderBy(F.col(score).desc()))
        bwd = F.rank().over(Window.partitionBy(*keys, "v").orderBy(F.col(score).desc()))
        m = 1
    elif rule == "top":
        fwd = F.row_number().over(Window.partitionBy(*keys, "u").orderBy(F.col(score).desc(), "v"))
        bwd = F.row_number().over(Window.partitionBy(*keys, "v").orderBy(F.col(score).desc(), "u"))
    else:
        raise ValueError(f"no rule {rule}")
    ranked = pairs.withColumn("_f", fwd)
    if how == "forward":
        return ranked.where(F.col("_f") <= m).drop("_f")
    if how == "intersect":
        # What the first direction drops must still be ranked against: the second rank is over all pairs.
        ranked = ranked.withColumn("_b", bwd).where((F.col("_f") <= m) & (F.col("_b") <= m))
    elif how == "union":
        ranked = ranked.withColumn("_b", bwd).where((F.col("_f") <= m) | (F.col("_b") <= m))
    elif how == "backward":
        ranked = ranked.withColumn("_b", bwd).where(F.col("_b") <= m)
    else:
        raise ValueError(f"no way {how}")
    return ranked.drop("_f", "_b")


def reconcile_sets(found_forward: DataFrame, found_backward: DataFrame) -> DataFrame:
    """The pairs of two match sets that are in both."""
    return found_forward.select("u", "v").intersect(found_backward.select("u", "v"))
