"""Cubes: long tables of cells (i, j, k, v) built from facts, and their dictionaries.

A missing cell has no row (or a null value); a zero is a row with 0.0.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from finegrain import shared

MODES = ("i", "j", "k")


@dataclass(frozen=True)
class CubeSpec:
    """An N-mode cube of a fact query: a key expression for each mode, and the measure."""

    keys: dict[str, Column]
    measure: Column
    how: str = "sum"  # sum, money (exact to the cent), count, avg
    where: Column | None = None


def build_cube(facts: DataFrame, spec: CubeSpec) -> DataFrame:
    """One aggregation of the facts: map-side combined, one shuffle on the modes' keys."""
    rows = facts if spec.where is None else facts.where(spec.where)
    value = {
        "sum": F.sum(spec.measure.cast("double")),
        "money": F.sum(spec.measure.cast("decimal(18,2)")).cast("double"),
        "count": F.count("*").cast("double"),
        "avg": F.avg(spec.measure.cast("double")),
    }[spec.how]
    keys = [c.cast("long").alias(m) for m, c in spec.keys.items()]
    return rows.groupBy(*keys).agg(value.alias("v"))


def dimension(df: DataFrame, key: str, order: list[str] | None = None, attrs: list[str] | None = None) -> DataFrame:
    """idx, key and attributes of the distinct members, numbered in the order of their keys.

    Members are numbered by a range shuffle and offsets, so that a large dictionary isn't one task's sort; attributes take the
    least of a member's values.
    """
    attrs = attrs or []
    members = df.where(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("_n"), *(F.min(a).alias(a) for a in attrs)).drop("_n")
    return numbered(members, order or [key]).select("idx", F.col(key).cast("string").alias("key"), *attrs)


def numbered(rows: DataFrame, order: list[str | Column], name: str = "idx") -> DataFrame:
    """rows with ``name``, their place from 0 in an order (which must leave no ties): one range shuffle, and a count of each partition on the driver."""
    spark = rows.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    at = F.monotonically_increasing_id()
    placed = shared.table(rows.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_at", at))
    part = F.shiftright("_at", 33)
    counts = sorted(tuple(r) for r in placed.groupBy(part.alias("p")).count().collect())
    before = [0]
    for _, c in counts:
        before.append(before[-1] + c)
    starts = spark.createDataFrame([(p, b) for (p, _), b in zip(counts, before)] or [(0, 0)], "_p long, _before long")
    out = placed.withColumn("_p", part).join(F.broadcast(starts), "_p")
    return out.withColumn(name, F.col("_at").bitwiseAND(2**33 - 1) + F.col("_before")).drop("_at", "_p", "_before")


def ticks(spark: SparkSession, start: str, end: str) -> DataFrame:
    """A calendar dimension: a row for each day from start to end (included), with its place in days, weeks, months, quarters and half-years."""
    return _ticks(spark.range(1).select(F.lit(start).cast("date").alias("first"), F.lit(end).cast("date").alias("last")))


def calendar_of(df: DataFrame, column: str) -> DataFrame:
    """The calendar of the days from a column's first to its last."""
    day = F.col(column).cast("date")
    return _ticks(df.agg(F.min(day).alias("first"), F.max(day).alias("last")))


def _ticks(span: DataFrame) -> DataFrame:
    day, first = F.col("day"), F.col("first")
    months = (F.year(day) - F.year(first)) * 12 + F.month(day) - F.month(first)
    years = F.year(day) - F.year(first)
    days = span.select("first", F.explode(F.sequence("first", "last")).alias("day"))
    return days.select(
        "day", F.datediff(day, first).cast("long").alias("tick"), F.floor(F.datediff(day, first) / 7).alias("week"), months.cast("long").alias("month"),
        (years * 4 + F.quarter(day) - F.quarter(first)).cast("long").alias("quarter"),
        (years * 2 + F.floor((F.month(day) - 1) / 6) - F.floor((F.month(first) - 1) / 6)).cast("long").alias("half_year"),
    )


def unfold(cells: DataFrame, size: int, mode: str = "k") -> DataFrame:
    """The other modes by one column for each index of a (short) mode: c0, c1, ...; absent cells are null."""
    others = [c for c in cells.columns if c not in (mode, "v")]
    wide = cells.groupBy(*others).pivot(mode, list(range(size))).agg(F.first("v"))
    return wide.withColumnsRenamed({str(n): f"c{n}" for n in range(size)})


def fold(wide: DataFrame, size: int, mode: str = "k") -> DataFrame:
    """The cells of an unfolded cube again; null is no cell."""
    others = [c for c in wide.columns if c not in {f"c{n}" for n in range(size)}]
    long = wide.unpivot(others, [f"c{n}" for n in range(size)], "_c", "v").where("v IS NOT NULL")
    return long.select(*others, F.substring("_c", 2, 10).cast("long").alias(mode), "v")


def densify(cells: DataFrame, dims: dict[str, int], absent: str = "zero") -> DataFrame:
    """All cells of the cube of these sizes; absent ones are 0.0 or null. Made from one range, joined once."""
    spark, total = cells.sparkSession, 1
    for n in dims.values():
        total *= n
    every, below = spark.range(total), total
    keys = []
    for m, n in dims.items():
        below //= n
        keys.append(F.pmod(F.floor(F.col("id") / below), F.lit(n)).cast("long").alias(m))
    fill = F.lit(0.0) if absent == "zero" else F.lit(None).cast("double")
    return every.select(*keys).join(cells, list(dims), "left").withColumn("v", F.coalesce("v", fill))


def slice_cube(cells: DataFrame, **fixed: int) -> DataFrame:
    """Cells with these indexes; the filter reaches the scan."""
    for m, x in fixed.items():
        cells = cells.where(F.col(m) == x)
    return cells


def dice_cube(cells: DataFrame, **ranges: tuple[int, int]) -> DataFrame:
    """Cells with low <= index < high for each given mode."""
    for m, (low, high) in ranges.items():
        cells = cells.where((F.col(m) >= low) & (F.col(m) < high))
    return cells


def profile_cube(cells: DataFrame, dims: dict[str, int] | None = None) -> DataFrame:
    """Sizes, largest, mean and standard deviation of the observed values, percent missing and zero, as one row."""
    total = None
    if dims:
        total = F.lit(1)
        for n in dims.values():
            total = total * n
    modes = [c for c in cells.columns if c != "v"]
    seen = F.count("v")
    out = cells.agg(
        *(F.countDistinct(m).alias(f"n_{m}") for m in modes),
        seen.alias("observed"), F.max("v").alias("largest"), F.round(F.avg("v"), 6).alias("mean"), F.round(F.stddev_pop("v"), 6).alias("sd"),
        F.count(F.when(F.col("v") == 0, 1)).alias("zeros"),
    )
    whole = total if total is not None else F.expr(" * ".join(f"n_{m}" for m in modes))
    return out.withColumn("missing_percent", F.round(100 * (1 - F.col("observed") / whole), 6)).withColumn("zero_percent", F.round(100 * F.col("zeros") / whole, 6)).drop("zeros")


def top_items(facts: DataFrame, per: str, item: str, amount: str, n: int = 50) -> DataFrame:
    """The n items with the most in each category, ties by item, with their rank from 0."""
    sums = facts.groupBy(per, item).agg(F.sum(amount).alias("amount"))
    place = F.row_number().over(Window.partitionBy(per).orderBy(F.desc("amount"), item))
    return sums.withColumn("place", place - 1).where(F.col("place") < n)


def observed(cells: DataFrame) -> DataFrame:
    """Cells with a value; NaN is refused, since it would spoil every sum silently."""
    return cells.where(F.col("v").isNotNull()).withColumn("v", F.when(F.isnan("v"), F.raise_error(F.lit("a cell's value is NaN"))).otherwise(F.col("v")))


def spark_of(cells: DataFrame) -> SparkSession:
    return cells.sparkSession
