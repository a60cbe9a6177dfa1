"""Points, parameters and reports."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace
from fractions import Fraction
from functools import cache

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class TreeParams:
    """levels: skeleton height of one round; oversample: samples a bucket; leaf_capacity: most
    points of an ordinary leaf; alpha: slack of the weight balance (0.5: never rebuild);
    shard_rows: most points that one task holds; store_boxes: keep a tight box with every node;
    sampler: 'hash' (splitters from samples) or 'exact' (true medians); split_rule: 'widest' or 'cycle'.
    """

    levels: int = 6
    oversample: int = 32
    leaf_capacity: int = 32
    alpha: float = 0.3
    shard_rows: int = 1 << 18
    split_rule: str = "widest"
    sampler: str = "hash"
    store_boxes: bool = False
    seed: int = 1
    #: 'lazy': points are moved once, after all rounds; 'eager': after every round.
    movement: str = "lazy"

    @property
    def base_cutoff(self) -> int:
        """Fewer points than a skeleton has samples are built plainly."""
        return (1 << self.levels) * self.oversample

    def but(self, **changes) -> TreeParams:
        return replace(self, **changes)


def plain(**changes) -> TreeParams:
    """Split at true medians; one level a round, until a task can take an end's points ('eager': to the last)."""
    return TreeParams(levels=1, sampler="exact").but(**changes)


@cache
def _exact(alpha: float) -> Fraction:
    return Fraction(str(alpha))


def is_balanced(left: int, right: int, alpha: float) -> bool:
    """Whether each child holds between 0.5 - alpha and 0.5 + alpha of the points, in exact
    arithmetic; sizes that differ by one at most are always balanced."""
    a = _exact(alpha)
    total = left + right
    return abs(left - right) <= 1 or (Fraction(1, 2) - a) * total <= left <= (Fraction(1, 2) + a) * total


def strict_alpha(n: int, c: float = 1.0) -> float:
    """A slack in inverse proportion to the height, which keeps the height at log2(n) + O(1)."""
    return min(0.5, c / math.log2(1 + max(1, n)))


def oversample_for(n: int, eps: float, c: float = 1.0) -> int:
    """Samples a bucket with which every split of n points lies in child_bounds, but for a chance of 2 / n^c."""
    return math.ceil(6 * c * math.log2(1 + n) / eps**2)


def child_bounds(n: int, eps: float) -> tuple[float, float]:
    return (0.5 - eps / 4) * n, (0.5 + eps / 4) * n


def height_bound(n: int, eps: float) -> int:
    """Levels after which a tree with splits within child_bounds has leaves of one point."""
    return math.ceil(math.log2(max(2, n)) / -math.log2(0.5 + eps / 4))


@dataclass
class Report:
    """What an operation did: points that were moved or looked at, rounds over the data, points
    in rebuilt subtrees, shards written and untouched, and for deletions how many were found."""

    rounds: int = 0
    moved: int = 0
    scanned: int = 0
    rebuilt: int = 0
    shards_written: int = 0
    shards_kept: int = 0
    found: int = 0
    absent: DataFrame | None = field(default=None, repr=False)


def axes(dimensions: int, prefix: str = "c") -> list[str]:
    return [f"{prefix}{i}" for i in range(dimensions)]


def dimensions_of(points: DataFrame, prefix: str = "c") -> int:
    n = 0
    while f"{prefix}{n}" in points.columns:
        n += 1
    if not n:
        raise ValueError(f"no coordinate column {prefix}0")
    return n


def normal_points(points: DataFrame) -> DataFrame:
    """point_id and double coordinates with -0.0 as 0.0; rows with a null, NaN or infinite one are left out (see rejects)."""
    names = axes(dimensions_of(points))
    good = finite(names)
    return points.filter(good).select(F.col("point_id").cast("bigint").alias("point_id"), *[(F.col(c).cast("double") + F.lit(0.0)).alias(c) for c in names])


def finite(names: list[str]):
    good = F.lit(True)
    for c in names:
        x = F.col(c).cast("double")
        good = good & x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    return F.coalesce(good, F.lit(False))


def rejects(points: DataFrame) -> DataFrame:
    """The rows that normal_points leaves out."""
    return points.filter(~finite(axes(dimensions_of(points))))
