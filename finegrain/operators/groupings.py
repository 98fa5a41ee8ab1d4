"""Groupings: which members of a mode a coarse index adds up (or averages), also with overlaps and gaps."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Groupings live on the driver as three columns; a mode's dictionary is what bounds them.
MEMBERS = 50_000_000


@dataclass(frozen=True)
class Grouping:
    """A sparse aggregation matrix: group ``grp[n]`` takes ``weight[n]`` of member ``member[n]``."""

    member: np.ndarray
    grp: np.ndarray
    weight: np.ndarray
    n_members: int
    n_groups: int

    def __post_init__(self) -> None:
        if self.n_groups > self.n_members:
            raise ValueError("a grouping has at most as many groups as members")
        if len(self.member) > MEMBERS:
            raise ValueError(f"more than {MEMBERS} entries; join the grouping as a table instead")

    @staticmethod
    def of(grp: np.ndarray | list[int], n_groups: int | None = None, how: str = "sum") -> Grouping:
        """Each member n in group grp[n]; a negative group is none."""
        grp = np.asarray(grp, np.int64)
        member = np.flatnonzero(grp >= 0)
        n = int(n_groups if n_groups is not None else (grp.max(initial=-1) + 1))
        return Grouping(member, grp[member], np.ones(len(member)), len(grp), n).as_how(how)

    def as_how(self, how: str) -> Grouping:
        if how == "sum":
            return self
        if how != "avg":
            raise ValueError(f"how is sum or avg, not {how!r}")
        return Grouping(self.member, self.grp, self.weight / self.sizes()[self.grp], self.n_members, self.n_groups)

    def sizes(self) -> np.ndarray:
        """Members of each group."""
        return np.bincount(self.grp, minlength=self.n_groups)

    def times(self) -> np.ndarray:
        """How much of each member all groups take together (1 where groups partition the mode)."""
        return np.bincount(self.member, self.weight, self.n_members)

    def is_partition(self) -> bool:
        return bool(len(self.member) == self.n_members and (np.bincount(self.member, minlength=self.n_members) == 1).all())

    def apply(self, factor: np.ndarray) -> np.ndarray:
        """The coarse factor: group rows are weighted sums of member rows."""
        out = np.zeros((self.n_groups, *factor.shape[1:]))
        np.add.at(out, self.grp, factor[self.member] * self.weight.reshape(-1, *[1] * (factor.ndim - 1)))
        return out

    def back(self, coarse: np.ndarray) -> np.ndarray:
        """The transpose: what reaches each member from the groups it is in."""
        out = np.zeros((self.n_members, *coarse.shape[1:]))
        np.add.at(out, self.member, coarse[self.grp] * self.weight.reshape(-1, *[1] * (coarse.ndim - 1)))
        return out

    def frame(self, spark: SparkSession) -> DataFrame:
        """member, grp, weight."""
        import pyarrow as pa

        return spark.createDataFrame(pa.table({"member": self.member, "grp": self.grp, "weight": self.weight}))


def chunk(n: int, groups: int, how: str = "sum") -> Grouping:
    """Consecutive groups, ragged where n doesn't divide: member k is in group floor(k * groups / n)."""
    return Grouping.of(np.arange(n) * groups // n, groups, how)


def fixed_size(n: int, size: int, how: str = "sum") -> Grouping:
    """Groups of ``size`` members in order; the last may be smaller."""
    return Grouping.of(np.arange(n) // size, -(-n // size), how)


def period(n: int, width: int, offset: int = 0, how: str = "sum") -> Grouping:
    """Periods of ``width`` ticks; with an offset the first one is that much shorter."""
    grp = (np.arange(n) + offset) // width
    return Grouping.of(grp - grp[0], None, how)


def calendar(n: int, spec: list[tuple[int, int]], how: str = "sum") -> Grouping:
    """Periods [low, high) of ticks 0..n-1: of any widths, with gaps (ticks in none) and overlaps (ticks in several)."""
    member = np.concatenate([np.arange(max(a, 0), min(b, n)) for a, b in spec]) if spec else np.zeros(0, np.int64)
    grp = np.repeat(np.arange(len(spec)), [max(0, min(b, n) - max(a, 0)) for a, b in spec])
    return Grouping(member.astype(np.int64), grp, np.ones(len(member)), n, len(spec)).as_how(how)


def mixed_calendar(n: int, first: int, then: int) -> list[tuple[int, int]]:
    """The first half in periods of one width, the rest in another."""
    half = n // 2 // first * first
    return [(a, a + first) for a in range(0, half, first)] + [(a, min(a + then, n)) for a in range(half, n, then)]


def gapped_calendar(n: int, width: int, every: int = 5) -> list[tuple[int, int]]:
    """Periods of one width with each ``every``-th left out."""
    return [(a, min(a + width, n)) for p, a in enumerate(range(0, n, width)) if p % every != every - 1]


def overlapping_calendar(n: int, width: int) -> list[tuple[int, int]]:
    """Periods that overlap by half."""
    return [(a, a + width) for a in range(0, n - width + 1, width // 2)]


def dictionary(dim: DataFrame, *columns: str) -> list[np.ndarray]:
    """Columns of a mode's dictionary on the driver, in the order of idx; refused beyond MEMBERS rows, before any is collected."""
    n = dim.count()
    if n > MEMBERS:
        raise ValueError(f"a dictionary of {n} members: more than {MEMBERS}; join the grouping as a table instead")
    rows = dim.select("idx", *columns).toArrow().sort_by("idx")
    return [c.to_numpy() for c in rows.columns]


def by_column(dim: DataFrame, column: str, how: str = "sum") -> Grouping:
    """Members (column idx of a dictionary) by the sorted values of a column; null is no group."""
    _, value = dictionary(dim, column)
    known = np.array([x is not None and x == x for x in value.tolist()], bool)
    names, place = np.unique(value[known], return_inverse=True)
    grp = np.full(len(value), -1, np.int64)
    grp[known] = place.ravel()
    return Grouping.of(grp, len(names), how)


def by_ntile(dim: DataFrame, column: str, n: int, how: str = "sum") -> Grouping:
    """n size bands by an attribute, ties by idx; as SQL's ntile has it, the first bands are the larger ones, and nulls come first."""
    _, value = dictionary(dim.select("idx", F.col(column).cast("double").alias(column)), column)
    value = np.where(np.isnan(value.astype(float)), -np.inf, value.astype(float))
    grp = np.empty(len(value), np.int64)
    small, more = divmod(len(value), n)
    grp[np.argsort(value, kind="stable")] = np.repeat(np.arange(n), [small + (b < more) for b in range(n)])
    return Grouping.of(grp, n, how)


def by_similarity(dim: DataFrame, features: list[str], size: int, how: str = "sum", seed: int = 7) -> Grouping:
    """Groups of ``size`` members that are close in their features: in the order of one feature, or of k-means
    clusters of several."""
    if len(features) == 1:
        idx, value = dictionary(dim, features[0])
    else:
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.feature import VectorAssembler

        points = VectorAssembler(inputCols=features, outputCol="features").transform(dim)
        clusters = max(2, points.count() // size)
        placed = KMeans(k=clusters, seed=seed).fit(points).transform(points)
        idx, value = dictionary(placed, "prediction")
    grp = np.empty(len(idx), np.int64)
    grp[idx[np.argsort(value, kind="stable")]] = np.arange(len(idx)) // size
    return Grouping.of(grp, -(-len(idx) // size), how)


def from_table(df: DataFrame, member: str, grp: str, n_members: int, n_groups: int, weight: str | None = None) -> Grouping:
    """A grouping that a table holds, one row for each membership."""
    rows = df.select(F.col(member).cast("long").alias("idx"), F.col(grp).cast("long").alias("grp"), (F.lit(1.0) if weight is None else F.col(weight).cast("double")).alias("weight")).distinct()
    m, g, w = dictionary(rows, "grp", "weight")
    order = np.lexsort((g, m))
    m, g, w = m[order], g[order], w[order]
    return Grouping(m.astype(np.int64), g.astype(np.int64), w.astype(float), n_members, n_groups)
