"""Lattice of strata counts: a base cuboid of additive cells, rolled up without its rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def measures(id_column: str, treatments, outcomes=()):
    """Additive measures of a cell: largest id, rows, and for each treatment its arm counts,
    largest id among its own rows, and arm sums of outcomes."""
    out = [F.max(id_column).alias("max_id"), F.count("*").alias("n")]
    for t in treatments:
        out.append(F.max(F.when(F.col(t).isNotNull(), F.col(id_column))).alias(f"max_{t}"))
        for a in (1, 0):
            own = F.col(t) == a
            out.append(F.count_if(own).alias(f"n{a}_{t}"))
            out += [F.sum(F.when(own, F.col(y))).alias(f"sum{a}_{t}_{y}") for y in outcomes]
    return out


def base_cuboid(df: DataFrame, dims, id_column: str, treatments, outcomes=()) -> DataFrame:
    """Cells of all dimensions: the only pass over rows."""
    return df.groupBy(*dims).agg(*measures(id_column, treatments, outcomes))


def roll_up(cells: DataFrame, dims, all_dims) -> DataFrame:
    """Cells of fewer dimensions from cells of more."""
    values = [c for c in cells.columns if c not in all_dims]
    return cells.groupBy(*dims).agg(*((F.max(c) if c.startswith("max_") else F.sum(c)).alias(c) for c in values))


def smallest_ancestor(wanted, sizes: dict[frozenset, int]) -> frozenset:
    """The materialized cuboid with the fewest cells that has all wanted dimensions."""
    able = [d for d in sizes if d >= set(wanted)]
    if not able:
        raise ValueError("no cuboid has these dimensions")
    return min(able, key=lambda d: (sizes[d], sorted(d)))


class Lattice:
    """Cuboids by their dimensions; each new one comes from its smallest ancestor."""

    def __init__(self, base: DataFrame, dims, store=lambda df: df):
        self.dims, self._store = tuple(dims), store
        self.cuboids = {frozenset(dims): store(base)}
        self.sizes: dict[frozenset, int] = {}

    def _size(self, key):
        if key not in self.sizes:
            self.sizes[key] = self.cuboids[key].count()
        return self.sizes[key]

    def cuboid(self, dims) -> DataFrame:
        key = frozenset(dims)
        if key not in self.cuboids:
            able = {k: self._size(k) for k in self.cuboids if k > key}
            source = smallest_ancestor(key, able)
            self.cuboids[key] = self._store(roll_up(self.cuboids[source], [d for d in self.dims if d in key], source))
        return self.cuboids[key]

    def build(self, cuboids) -> None:
        """Materialize the asked cuboids, largest first, so that ancestors come before."""
        for dims in sorted(cuboids, key=len, reverse=True):
            self.cuboid(dims)

    def cells(self) -> DataFrame:
        """All cuboids as one table; dims that are rolled up are null, ``grouping_id`` has their bits."""
        parts = []
        for key, cells in self.cuboids.items():
            gid = sum(1 << (len(self.dims) - 1 - i) for i, d in enumerate(self.dims) if d not in key)
            parts.append(cells.select(F.lit(gid).cast("long").alias("grouping_id"), *((F.col(d) if d in key else F.lit(None).cast(self.cuboids[frozenset(self.dims)].schema[d].dataType)).alias(d) for d in self.dims), *(c for c in cells.columns if c not in self.dims)))
        return reduce(DataFrame.unionByName, parts)


def strata_of(cells: DataFrame, treatment: str, dims, outcomes=()) -> DataFrame:
    """Strata of one treatment from cells of its covariates: as ``overlapping(summarize(...))``."""
    n1, n0 = F.col(f"n1_{treatment}"), F.col(f"n0_{treatment}")
    sums = [F.col(f"sum{a}_{treatment}_{y}").alias(f"sum{a}_{y}") for y in outcomes for a in (1, 0)]
    return cells.select(*dims, F.col(f"max_{treatment}").alias("subclass"), (n1 + n0).alias("n"), n1.alias("n1"), n0.alias("n0"), *sums).where("n1 > 0 and n0 > 0")


def cube_baseline(df: DataFrame, dims, id_column: str, treatments) -> DataFrame:
    """Baseline: Spark's own cube, which copies every row for each grouping set."""
    return df.cube(*dims).agg(F.grouping_id().alias("grouping_id"), *measures(id_column, treatments))
