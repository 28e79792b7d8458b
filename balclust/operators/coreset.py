"""The weighted summary: sampled points of the important parts, one weight per level.

The sample is drawn before any join: one hash decides for all levels, since a level's rate only asks for hash values
below its threshold. Points above the largest threshold of any level never move, and the others are routed by broadcast look-ups.
"""

from __future__ import annotations

import math
from typing import NamedTuple

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.functions import points as P
from balclust.operators import partition
from balclust.plans.params import Params


class Summary(NamedTuple):
    """Tables of a summary. fail: 0 or 1 row per reason."""

    params: Params
    grid: P.Grid
    heavy: DataFrame
    parts: DataFrame
    coreset: DataFrame


def rates(params: Params) -> dict[int, int]:
    return {i: P.threshold(params.rate(i)) for i in range(params.levels + 1)}


def important_parts(parts: DataFrame, params: Params) -> DataFrame:
    """Parts of at least the share gamma of their level's threshold."""
    limit = {i: params.gamma * params.cell_threshold(i) for i in range(params.levels + 1)}
    return parts.where(F.col("size") >= partition.by_level("level", limit))


def failures(heavy: DataFrame, parts: DataFrame, params: Params) -> DataFrame:
    """reason, value, cap, failed: too many heavy cells, or too much mass on a level."""
    cells = heavy.agg(F.count("*").cast("double").alias("value")).select(F.lit("heavy_cells").alias("reason"), "value", F.lit(float(params.cell_cap)).alias("cap"))
    caps = {i: params.mass_cap(i) for i in range(params.levels + 1)}
    mass = partition.level_masses(parts).select(F.concat(F.lit("mass_"), F.col("level").cast("string")).alias("reason"), F.col("mass").cast("double").alias("value"), partition.by_level("level", caps).alias("cap"))
    return cells.unionByName(mass).withColumn("failed", F.col("value") > F.col("cap"))


def sample(points: DataFrame, heavy: DataFrame, parts: DataFrame, grid: P.Grid, params: Params, h: P.Hash, rows: list | None = None) -> DataFrame:
    """Points of important parts whose hash is below their level's threshold, with part and weight. There are no more parts than heavy cells (rows: those, where at hand)."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    cut = rates(params)
    hashed = points.withColumn("h", P.poly_hash(["tag", *coordinates], h)).where(F.col("h") < max(cut.values()))
    some = important_parts(parts, params).select("level", *(f"p{m}" for m in range(grid.d)), "size")
    met = partition.routed_points(hashed, heavy, grid, rows).join(some if rows is None else F.broadcast(some), ["level", *(f"p{m}" for m in range(grid.d))])
    kept = met.where(F.col("h") < partition.by_level("level", cut))
    weight = partition.by_level("level", {i: P.RANGE / t for i, t in cut.items()})
    return kept.select("tag", *coordinates, "level", *(f"p{m}" for m in range(grid.d)), weight.alias("w"))


def from_cells(points: DataFrame, cells: DataFrame, grid: P.Grid, params: Params, h: P.Hash) -> Summary:
    """The summary from exact cell counts, wherever they were taken. The heavy cells are found by one job; with few of them nothing else is shuffled."""
    heavy = partition.heavy_cells(cells, params).select("level", *grid.key_names, "n")
    rows = partition.held(heavy, grid)
    if rows is not None:
        heavy = partition.frame(points.sparkSession, rows, grid)
    parts = partition.parts_of_cells(heavy, grid)
    return Summary(params, grid, heavy, parts, sample(points, heavy, parts, grid, params, h, rows))


def build(points: DataFrame, grid: P.Grid, params: Params, h: P.Hash) -> Summary:
    """The summary of one guess. points: tag, x0.., distinct."""
    return from_cells(points, partition.cell_counts(partition.leaf_counts(points, grid), grid), grid, params, h)


def from_estimates(points: DataFrame, cells: DataFrame, grid: P.Grid, params: Params, h: P.Hash, sized) -> Summary:
    """The summary from estimated sizes of cells (level, k0.., n); sized(heavy, rows) gives the parts with their estimated sizes.

    Heavy cells are marked from the top, level by level, since an estimate may pass its threshold where its parent's does not.
    """
    marked = partition.mark_cells(cells, grid, params)
    heavy = marked.where("kind = 'heavy'").select("level", *grid.key_names, "n")
    rows = partition.held(heavy, grid)
    if rows is not None:
        heavy = partition.frame(points.sparkSession, rows, grid)
    parts = sized(heavy, rows)
    return Summary(params, grid, heavy, parts, sample(points, heavy, parts, grid, params, h, rows))


def build_hashed(points: DataFrame, grid: P.Grid, params: Params, cell_hash: P.Hash, part_hash: P.Hash, h: P.Hash) -> Summary:
    """The summary of one guess with no exact count: cells' sizes from one hashed sample, parts' from a second, the summary's points from a third."""
    from balclust.operators import estimate

    cells = estimate.sampled_cells(points, grid, params, cell_hash)
    return from_estimates(points, cells, grid, params, h, lambda heavy, rows: estimate.sampled_parts(points, heavy, grid, params, part_hash, rows))


def surviving(rungs: DataFrame, params: Params) -> DataFrame:
    """Guesses of a ladder that fail no test: guess_log2, n_heavy. Only caps of the parameters enter, not their guess."""
    scale = {i: params._replace(guess=1.0).mass_cap(i) for i in range(params.levels + 1)}
    fits = F.when(F.col("level") >= 0, F.col("mass") <= partition.by_level("level", scale) * F.pow(F.lit(2.0), F.col("guess_log2"))).otherwise(F.lit(True))
    per = rungs.withColumn("fits", fits).groupBy("guess_log2").agg(F.sum("n_heavy").alias("n_heavy"), F.bool_and("fits").alias("fits"))
    return per.where(F.col("fits") & (F.col("n_heavy") <= params.cell_cap)).select("guess_log2", "n_heavy")


def top_guess(points: DataFrame, grid: P.Grid, r: float) -> int:
    """The exponent of a guess that no cost can pass: all points at the lattice's diameter."""
    return math.ceil(math.log2(max(1, points.count()) * (math.sqrt(grid.d) * 2.0**grid.levels) ** r)) + 1


def smallest_guess(points: DataFrame, grid: P.Grid, params: Params, exponents: int | None = None) -> float | None:
    """The smallest guess that fails no test, from one histogram; None if all fail. exponents: the ladder's end, by default the largest that can matter."""
    cells = partition.cell_counts(partition.leaf_counts(points, grid), grid)
    exponents = top_guess(points, grid, params.r) if exponents is None else exponents
    best = surviving(partition.ladder(cells, grid, params.r, params.d, exponents), params).agg(F.min("guess_log2")).first()[0]
    return None if best is None else float(2**best)


def build_auto(points: DataFrame, grid: P.Grid, params: Params, h: P.Hash) -> Summary:
    """The summary at the smallest guess that survives."""
    guess = smallest_guess(points, grid, params)
    if guess is None:
        raise ValueError("every guess fails")
    return build(points, grid, params._replace(guess=guess), h)
