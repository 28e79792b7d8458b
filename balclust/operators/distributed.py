"""One round between machines and a coordinator, with the bits it takes.

A machine's local summary is a partial aggregate over its rows; what it sends is counted before anything is merged. A machine
with more non-empty cells than allowed says so instead.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.functions import points as P
from balclust.operators import coreset, partition


def local_cells(points: DataFrame, grid: P.Grid, level: int) -> DataFrame:
    """machine, k0.., n of each machine's non-empty cells. points: machine, x0.., tag."""
    keyed = points.select("machine", *grid.leaf([f"x{m}" for m in range(grid.d)]))
    return keyed.groupBy("machine", *(k.alias(n) for k, n in zip(grid.keys(level), grid.key_names, strict=True))).agg(F.count("*").alias("n"))


def cell_bits(grid: P.Grid) -> int:
    return grid.d * (grid.levels + 1)


def messages(local: DataFrame, grid: P.Grid, alpha: int, beta: int) -> DataFrame:
    """machine, cells, small_points, failed, bits: cells and counts, and the points of cells of at most beta; a machine above alpha cells only says so."""
    per = local.groupBy("machine").agg(F.count("*").alias("cells"), F.coalesce(F.sum(F.when(F.col("n") <= beta, F.col("n"))), F.lit(0)).cast("long").alias("small_points"), F.sum("n").alias("held"))
    counter = F.length(F.bin(F.col("held"))).cast("long")
    bits = F.col("cells") * (cell_bits(grid) + counter) + F.col("small_points") * cell_bits(grid)
    return per.select("machine", "cells", "small_points", (F.col("cells") > alpha).alias("failed"), F.when(F.col("cells") > alpha, F.lit(1).cast("long")).otherwise(bits).alias("bits"))


def merged_cells(local: DataFrame, grid: P.Grid) -> DataFrame:
    """k0.., n over all machines."""
    return local.groupBy(*grid.key_names).agg(F.sum("n").alias("n"))


def small_cell_points(points: DataFrame, local: DataFrame, grid: P.Grid, level: int, beta: int, exact: bool = True) -> DataFrame:
    """Points of cells of at most beta points on their machine; exact: of those, cells that are also that small over all machines."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    keyed = points.select("*", *grid.leaf(coordinates))
    keyed = keyed.withColumns(dict(zip(grid.key_names, grid.keys(level), strict=True)))
    small = local.where(F.col("n") <= beta).select("machine", *grid.key_names)
    met = keyed.join(small, ["machine", *grid.key_names], "left_semi")
    if exact:
        met = met.join(merged_cells(local, grid).where(F.col("n") <= beta), grid.key_names, "left_semi")
    return met.select("machine", "tag", *coordinates)


def tree_merge(local: DataFrame, grid: P.Grid, fan: int = 4) -> DataFrame:
    """The same sums by merging groups of machines first, as a shared-nothing tree would."""
    middle = local.groupBy(F.floor(F.col("machine") / fan).alias("machine"), *grid.key_names).agg(F.sum("n").alias("n"))
    return merged_cells(middle, grid)


def leaves_of_machines(points: DataFrame, grid: P.Grid) -> DataFrame:
    """Leaf counts by machine first, then over machines: what the summary needs, with one message per machine."""
    return merged_cells(local_cells(points, grid, grid.levels), grid).select(*(F.col(k).alias(c) for k, c in zip(grid.key_names, grid.names, strict=True)), "n")


def cells_of_machines(points: DataFrame, grid: P.Grid) -> DataFrame:
    return partition.cell_counts(leaves_of_machines(points, grid), grid)


def summary(points: DataFrame, grid: P.Grid, params, h: P.Hash) -> tuple[coreset.Summary, DataFrame]:
    """(the summary that the coordinator makes, machine, n_leaves, n_points and bits of each machine). points: machine, x0.., tag.

    Each machine sends its leaves with their counts; the coordinator adds them up, and sends the heavy cells to all; each machine then sends those of its
    points that lie in important parts and that the shared hash samples. Which machine holds a point changes nothing.
    """
    local = local_cells(points, grid, grid.levels)
    merged = merged_cells(local, grid).select(*(F.col(k).alias(c) for k, c in zip(grid.key_names, grid.names, strict=True)), "n")
    made = coreset.from_cells(points.drop("machine"), partition.cell_counts(merged, grid), grid, params, h)
    names = [f"x{m}" for m in range(grid.d)]
    sent = points.select("machine", "tag", *names).join(made.coreset.select("tag", *names), ["tag", *names], "left_semi").groupBy("machine").agg(F.count("*").alias("n_points"))
    counter = F.length(F.bin(F.col("held"))).cast("long")
    up = local.groupBy("machine").agg(F.count("*").alias("n_leaves"), F.sum("n").alias("held")).join(sent, "machine", "left")
    n_heavy = made.heavy.count()
    bits = F.col("n_leaves") * (cell_bits(grid) + counter) + F.col("n_points") * (cell_bits(grid) + 64) + F.lit(n_heavy * cell_bits(grid))
    return made, up.withColumn("n_points", F.coalesce("n_points", F.lit(0)).cast("long")).select("machine", "n_leaves", "n_points", bits.cast("long").alias("bits"))
