"""Partitions of space: grids, strips, median trees, replicas at the borders."""

from __future__ import annotations

import uuid
from dataclasses import dataclass
from functools import lru_cache

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def strip(value: Column, splits: list[int]) -> Column:
    """Number of splits at or below the value; splits are few, the text stays
    in generated code."""
    out = F.lit(0)
    for s in splits:
        out = out + (value >= F.lit(s)).cast("int")
    return out


def _cross(parts: Column, more: Column, step: int) -> Column:
    return F.flatten(F.transform(parts, lambda p: F.transform(more, lambda q: p * step + q)))


@dataclass(frozen=True)
class GridMap:
    """Rectilinear partitions: sorted splits per axis (a bounded literal)."""

    splits: dict[str, tuple[int, ...]]

    @property
    def parts(self) -> int:
        n = 1
        for s in self.splits.values():
            n *= len(s) + 1
        return n

    def part(self, at: dict[str, Column] | None = None) -> Column:
        out = F.lit(0)
        for axis, s in self.splits.items():
            out = out * (len(s) + 1) + strip(F.col(axis) if at is None else at[axis], list(s))
        return out.cast("int")

    def covering(self, bound: dict[str, tuple[int, int]]) -> Column:
        """Parts with a place from which an agent here can be seen."""
        out = F.array(F.lit(0))
        for axis, s in self.splits.items():
            if axis in bound:
                lo, hi = bound[axis]
                some = F.sequence(strip(F.col(axis) - hi, list(s)), strip(F.col(axis) - lo, list(s)))
            else:
                some = F.sequence(F.lit(0), F.lit(len(s)))
            out = _cross(out, some, len(s) + 1)
        return out


def assign_partition(agents: DataFrame, pmap: GridMap) -> DataFrame:
    return agents.withColumn("part", pmap.part())


def replicate(agents: DataFrame, pmap: GridMap, bound: dict[str, tuple[int, int]]) -> DataFrame:
    """A row for each part from which the agent can be seen; ``is_owner`` marks
    its own part's row.  Only border agents make more than one row."""
    own = agents.withColumn("owner_part", pmap.part())
    return own.withColumn("part", F.explode(pmap.covering(bound))).withColumn("is_owner", F.col("part") == F.col("owner_part"))


def quantile_splits(agents: DataFrame, axis: str, parts: int, accuracy: int = 10_000) -> tuple[int, ...]:
    """Splits that balance the number of agents, from one sketch pass."""
    at = [i / parts for i in range(1, parts)]
    got = agents.agg(F.approx_percentile(axis, at, accuracy)).first()[0] if at else []
    return tuple(sorted(set(got or [])))


def initial_partition(agents: DataFrame, axes: list[str], parts_per_axis: int) -> GridMap:
    return GridMap({a: quantile_splits(agents, a, parts_per_axis) for a in axes})


def histogram(agents: DataFrame, axis: str, bins: int, low: int, width: int) -> DataFrame:
    """(bin, load): pre-aggregated counts of equal bins; the last is open."""
    b = F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((F.col(axis) - low) / F.lit(float(width)))))
    return agents.groupBy(b.cast("int").alias("bin")).agg(F.count("*").alias("load"))


def rebalance_1d(hist: DataFrame, parts: int) -> DataFrame:
    """(bin, load, strip): strips of about equal load by prefix sums.  Bins are
    a fixed number, so the one-task window is bounded."""
    run = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    total = F.sum("load").over(Window.partitionBy(F.lit(0)))
    before = F.sum("load").over(run) - F.col("load")
    return hist.withColumn("strip", F.least(F.lit(parts - 1), F.floor(before * parts / total)).cast("int"))


def should_repartition(load_now: list[int], load_new: list[int], moved: int, horizon: int, cost_per_row: float = 1.0, fixed: float = 0.0) -> bool:
    """Is the relief of the fullest part until the next review worth the move?"""
    return (max(load_now) - max(load_new)) * horizon > moved * cost_per_row + fixed


@dataclass(frozen=True)
class KdMap:
    """Partitions of a median tree: ``splits[l]`` holds the 2**l splits of level
    l, which cuts along ``axes[l % len(axes)]`` (bounded literals)."""

    axes: tuple[str, ...]
    splits: tuple[tuple[int, ...], ...]

    @property
    def parts(self) -> int:
        return 1 << len(self.splits)

    def _walk(self, make, level: int = 0, node: int = 0):
        if level == len(self.splits):
            return node
        left, right = (self._walk(make, level + 1, 2 * node + k) for k in (0, 1))
        return make(self.axes[level % len(self.axes)], self.splits[level][node], left, right)

    def part(self, at: dict[str, Column] | None = None) -> Column:
        lit = lambda x: F.lit(x) if isinstance(x, int) else x
        out = self._walk(lambda axis, s, a, b: F.when((F.col(axis) if at is None else at[axis]) >= F.lit(s), lit(b)).otherwise(lit(a)))
        return lit(out).cast("int")

    def covering(self, bound: dict[str, tuple[int, int]]) -> Column:
        """Parts with a place from which an agent here can be seen."""
        some = lambda x: F.array(F.lit(x)) if isinstance(x, int) else x
        none = F.array().cast("array<int>")

        def make(axis, s, a, b):
            a, b = some(a), some(b)
            if axis not in bound:
                return F.concat(a, b)
            lo, hi = bound[axis]
            return F.concat(F.when(F.col(axis) - hi < F.lit(s), a).otherwise(none), F.when(F.col(axis) - lo >= F.lit(s), b).otherwise(none))

        return some(self._walk(make))


def kd_map(agents: DataFrame, axes: list[str], depth: int, accuracy: int = 10_000) -> KdMap:
    """Approximate medians, all nodes of a level in one pre-aggregated pass; an
    empty node takes 0."""
    out = KdMap(tuple(axes), ())
    for level in range(depth):
        got = {r["p"]: r["m"] for r in agents.groupBy(out.part().alias("p")).agg(F.approx_percentile(axes[level % len(axes)], 0.5, accuracy).alias("m")).collect()}  # 2**level rows
        out = KdMap(out.axes, (*out.splits, tuple(got.get(p, 0) for p in range(1 << level))))
    return out


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder, removed when the driver ends."""
    from .runtime import checkpoint_dir

    path = f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"
    hpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    hpath.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hpath)
    return path


def ranked(rows: DataFrame, by: list[str], order: list[str]) -> DataFrame:
    """``rows`` with ``rank`` (from 1) and ``total`` within ``by``; the order must
    be without ties.  Rows are dealt by ranges of (by, order) and written, so no
    task ranks more than a partition; offsets come from the partitions' counts."""
    spark = rows.sparkSession
    path = scratch(spark, "ranked")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows.repartitionByRange(n, *by, *order).withColumn("_at", F.spark_partition_id()).write.parquet(path)
    held = spark.read.parquet(path)
    counts = held.groupBy("_at", *by).agg(F.count("*").alias("_n"))  # a row a partition and group
    w = Window.partitionBy(*(by or [F.lit(0)]))
    before = counts.select("_at", *by, (F.sum("_n").over(w.orderBy("_at").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n")).alias("_before"), F.sum("_n").over(w).alias("total"))
    here = Window.partitionBy("_at", *by).orderBy(*order)
    return held.withColumn("_r", F.row_number().over(here)).join(before, ["_at", *by]).withColumn("rank", F.col("_r") + F.col("_before")).drop("_at", "_r", "_before")


def kd_leaves(agents: DataFrame, axes: list[str], depth: int) -> DataFrame:
    """Leaf number by exact medians, ties by id (``kd_map``: approximate ones, and
    a map that places agents)."""
    out = agents.withColumn("leaf", F.lit(0))
    for level in range(depth):
        at = ranked(out, ["leaf"], [axes[level % len(axes)], "id"])
        out = at.withColumn("leaf", F.col("leaf") * 2 + (F.col("rank") * 2 > F.col("total")).cast("int")).drop("rank", "total")
    return out


# -- parts as Spark partitions -----------------------------------------------------

PART = "_part"


@lru_cache(maxsize=64)
def _labels(spark: SparkSession, parts: int) -> tuple[int, ...]:
    found: dict[int, int] = {}
    size = max(64, 16 * parts)
    while len(found) < parts:
        got = spark.range(size).select(F.col("id").cast("int").alias("v")).groupBy(F.expr(f"pmod(hash(v), {parts})").alias("slot")).agg(F.min("v").alias("v")).collect()
        found, size = {r["slot"]: r["v"] for r in got}, 4 * size
    return tuple(found[i] for i in range(parts))


def label(spark: SparkSession, pmap, part: Column) -> Column:
    """The number that stands for a part in column ``PART``: hash partitioning by
    it puts every part into a partition of its own."""
    return F.element_at(F.array(*map(F.lit, _labels(spark, pmap.parts))), part + 1)


def place(agents: DataFrame, pmap) -> DataFrame:
    """Agents in their parts' partitions; those with ``PART`` are there already."""
    if PART in agents.columns:
        return agents
    return agents.withColumn(PART, label(agents.sparkSession, pmap, pmap.part())).repartition(pmap.parts, PART)


def borders(agents: DataFrame, pmap, bound: dict[str, tuple[int, int]]) -> DataFrame:
    """Copies of placed agents for the other parts that can see them, with the
    owner's part in ``_owner``: the one exchange of a tick's query phase."""
    spark = agents.sparkSession
    copies = agents.withColumn("_owner", F.col(PART)).withColumn(PART, F.explode(F.transform(pmap.covering(bound), lambda p: label(spark, pmap, p))))
    return copies.where(F.col(PART) != F.col("_owner")).repartition(pmap.parts, PART)
