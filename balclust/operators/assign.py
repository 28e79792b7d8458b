"""From a summary and centres to an assignment of every input row.

The summary is solved on the driver (fractional flow, splits removed, exchanged per level), its half-spaces and region tallies
go out as small tables, and the input is assigned by joins with them: rows of important parts by their
transferred region, the others to their nearest centre.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.operators import cost as C
from balclust.operators import coreset as S
from balclust.operators import flow, halfspace, partition


def assign_summary(summary: DataFrame, centres: C.Centres, capacity: float, r: float, d: int) -> tuple[DataFrame, dict]:
    """(x0.., tag, level, w, p0.., j of the summary's points, report). The summary's size is its parameters'; one too large for the driver is refused."""
    table = C.on_driver(summary).sort_values([*(f"x{m}" for m in range(d)), "tag"]).reset_index(drop=True)
    x, w = table[[f"x{m}" for m in range(d)]].to_numpy(np.int64), table["w"].to_numpy(float)
    z = np.asarray(centres, np.int64)
    distance = flow.costs(x, z, r)
    found = flow.transport(distance, w, np.full(len(z), float(capacity)))
    if found is None:
        raise ValueError("capacities are too small for the summary's weight")
    whole, splits = flow.remove_splits(distance, found[0])
    out = whole.copy()
    for level in np.unique(table["level"]):
        own = np.flatnonzero(table["level"] == level)
        sizes = np.bincount(whole[own], minlength=len(z))
        out[own] = flow.reassign(x[own], table["tag"].to_numpy()[own], w[own[0]], z, sizes, r)
    report = {"fractional": flow.value(distance, found[0]), "dual": flow.dual_value(distance, w, np.full(len(z), float(capacity)), found[1]), "splits": splits, "cost": float((w * distance[np.arange(len(x)), out]).sum()), "largest": float(np.bincount(out, w, len(z)).max())}
    spark = summary.sparkSession
    return spark.createDataFrame(table.assign(j=out.astype(np.int32))), report


def extend(points: DataFrame, built: S.Summary, assigned: DataFrame, centres: C.Centres, transfer: bool = True, routed: DataFrame | None = None) -> DataFrame:
    """points with level, j: every input row's centre. Heavy cells, parts and tallies, whose number the guess bounds, go to the points; no point moves.

    routed: what partition.routed_points gives for the points, where it is at hand. With many heavy levels the look-ups and the comparisons
    written into one step are more than the JVM compiles (8000 bytes), and each row is then interpreted: stage the routed points of large tables.
    """
    params, grid, k = built.params, built.grid, len(centres)
    part_key = ["level", *(f"p{m}" for m in range(grid.d))]
    ends = halfspace.derive(assigned, centres, params.r)
    tally = halfspace.tallies(halfspace.regions(assigned, ends, centres, params.r), k, part_key)
    sizes = S.important_parts(built.parts, params).select(*part_key, "size")
    rows = partition.held(built.heavy, grid)
    small = F.broadcast if rows is not None else (lambda df: df)  # no more parts than heavy cells
    keyed = partition.routed_points(points, built.heavy, grid, rows) if routed is None else routed
    placed = halfspace.regions(keyed, ends, centres, params.r).join(small(sizes), part_key, "left")
    if transfer:
        moved = halfspace.transfer(placed, small(tally), k, part_key, 2 * params.xi * F.col("size"))
    else:
        moved = placed.withColumn("j", F.when(F.col("region") > 0, F.col("region") - 1).cast("int"))
    near = C.nearest(moved.withColumnRenamed("j", "own"), centres, params.r).withColumnRenamed("j", "near")
    j = F.coalesce(F.when(F.col("size").isNotNull(), F.col("own")), F.col("near"))
    coordinates = [f"x{m}" for m in range(grid.d)]
    paid = F.lit(None).cast("long")
    for i, c in enumerate(C.distances(coordinates, centres, params.r)):
        paid = F.when(F.col("j") == i, c).otherwise(paid)
    return near.withColumn("j", j).drop("cost").withColumn("cost", paid).select(*points.columns, "level", "j", "cost")


def report(assigned: DataFrame, k: int, capacity: float) -> DataFrame:
    """cost, largest (cluster), violation (largest over capacity)."""
    sizes = C.size_vector(assigned, k).agg(F.max("size").alias("largest"))
    return assigned.agg(F.sum("cost").alias("cost")).crossJoin(F.broadcast(sizes)).withColumn("violation", F.col("largest") / F.lit(float(capacity)))


def frame(spark, centres: C.Centres) -> DataFrame:
    """Centres as rows (j, x0..)."""
    z = np.asarray(centres)
    return spark.createDataFrame(pd.DataFrame({"j": np.arange(len(z), dtype=np.int32), **{f"x{m}": z[:, m] for m in range(z.shape[1])}}))
