"""Sizes of cells and parts from hashed samples, and whether estimates are good."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.functions import points as P
from balclust.operators import partition
from balclust.plans.params import Params


def estimate_cells(points: DataFrame, grid: P.Grid, params: Params, h: P.Hash, which: int = 0) -> DataFrame:
    """level, k0.., n (exact), estimate: sampled points over the realised rate, by one aggregation over (level, cell).

    which: 0 for the rates of cells, 1 for the higher ones of parts. Only points below the largest threshold are expanded by level.
    """
    coordinates = [f"x{m}" for m in range(grid.d)]
    cut = {i: P.threshold(params.size_rates(i)[which]) for i in range(-1, params.levels + 1)}
    keyed = points.select(*grid.leaf(coordinates), P.poly_hash(["tag", *coordinates], h).alias("h"))
    levels = F.explode(F.array(*(F.lit(i) for i in cut))).alias("level")
    each = keyed.select("*", levels)
    return each.select("level", *(k.alias(n) for k, n in zip(grid.keys(F.col("level")), grid.key_names, strict=True)), (F.col("h") < partition.by_level("level", cut)).alias("hit")).groupBy("level", *grid.key_names).agg(
        F.count("*").alias("n"), F.count_if("hit").alias("hits")
    ).withColumn("estimate", F.col("hits") * partition.by_level("level", {i: P.RANGE / t for i, t in cut.items()}))


def sampled_cells(points: DataFrame, grid: P.Grid, params: Params, h: P.Hash) -> DataFrame:
    """level, k0.., n: estimated sizes of the cells that a sampled point lies in. Only sampled points are expanded by level, and nothing else is counted."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    cut = {i: P.threshold(params.size_rates(i)[0]) for i in range(-1, params.levels + 1)}
    hit = points.withColumn("h", P.poly_hash(["tag", *coordinates], h)).where(F.col("h") < max(cut.values())).select(*grid.leaf(coordinates), "h")
    each = hit.select("*", F.explode(F.array(*(F.lit(i) for i in cut))).alias("level")).where(F.col("h") < partition.by_level("level", cut))
    counted = each.groupBy("level", *(k.alias(n) for k, n in zip(grid.keys(F.col("level")), grid.key_names, strict=True))).agg(F.count("*").alias("hits"))
    return counted.select("level", *grid.key_names, (F.col("hits") * partition.by_level("level", {i: P.RANGE / t for i, t in cut.items()})).alias("n"))


def sampled_parts(points: DataFrame, heavy: DataFrame, grid: P.Grid, params: Params, h: P.Hash, rows: list | None = None) -> DataFrame:
    """level, p0.., size: estimated sizes of the parts that a sampled point lies in."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    cut = {i: P.threshold(params.size_rates(i)[1]) for i in range(params.levels + 1)}
    hit = points.withColumn("h", P.poly_hash(["tag", *coordinates], h)).where(F.col("h") < max(cut.values()))
    each = partition.routed_points(hit, heavy, grid, rows).where(F.col("h") < partition.by_level("level", cut))
    counted = each.groupBy("level", *(f"p{m}" for m in range(grid.d))).agg(F.count("*").alias("hits"))
    return counted.select("level", *(f"p{m}" for m in range(grid.d)), (F.col("hits") * partition.by_level("level", {i: P.RANGE / t for i, t in cut.items()})).alias("size"))


def good_cells(cells: DataFrame, params: Params) -> DataFrame:
    """cells with good: within a tenth of the level's threshold, or within one per cent."""
    limit = {i: 0.1 * t for i, t in partition.thresholds(params).items()}
    off = F.abs(F.col("estimate") - F.col("n"))
    return cells.withColumn("good", (off <= partition.by_level("level", limit)) | (off <= 0.01 * F.col("n")))


def estimate_parts(points: DataFrame, routed: DataFrame, grid: P.Grid, params: Params, h: P.Hash) -> DataFrame:
    """level, p0.., size, estimate of parts at their own rates."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    cut = {i: P.threshold(params.size_rates(i)[1]) for i in range(params.levels + 1)}
    met = points.select(P.poly_hash(["tag", *coordinates], h).alias("h"), *grid.leaf(coordinates)).join(routed, grid.names)
    hit = F.col("h") < partition.by_level("level", cut)
    return met.groupBy("level", *(f"p{m}" for m in range(grid.d))).agg(F.count("*").alias("size"), F.count_if(hit).alias("hits")).withColumn("estimate", F.col("hits") * partition.by_level("level", {i: P.RANGE / t for i, t in cut.items()}))


def good_parts(parts: DataFrame, params: Params) -> DataFrame:
    limit = {i: 0.1 * params.gamma * params.cell_threshold(i) for i in range(params.levels + 1)}
    off = F.abs(F.col("estimate") - F.col("size"))
    return parts.withColumn("good", (off <= partition.by_level("level", limit)) | (off <= 0.1 * F.col("size")))


def good_levels(parts: DataFrame, params: Params) -> DataFrame:
    """level, mass, estimate, good of whole levels."""
    limit = {i: 0.1 * params.cell_threshold(i) for i in range(params.levels + 1)}
    sums = parts.groupBy("level").agg(F.sum("size").alias("mass"), F.sum("estimate").alias("estimate"))
    off = F.abs(F.col("estimate") - F.col("mass"))
    return sums.withColumn("good", (off <= partition.by_level("level", limit)) | (off <= 0.1 * F.col("mass")))
