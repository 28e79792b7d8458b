"""Accuracy measures of summaries, samples, transfers and solutions."""

from __future__ import annotations

import math
import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.functions import points as P
from balclust.operators import coreset, flow
from balclust.operators import cost as C


def coreset_ratios(points: DataFrame, built: coreset.Summary, centres: C.Centres, capacities: list[int], eta: float, theorem: bool = False) -> DataFrame:
    """t, upper, lower for two centres.

    upper: the summary's cost at (1 + eta) t over the input's at t. lower: the input's cost over the summary's, at (1 + eta)^2 t and
    (1 + eta) t, or in the theorem's form at (1 + eta) t and t. Infeasible sides count as infinite.
    """
    r, d, spark = built.params.r, built.grid.d, points.sparkSession
    x, w = C.arrays(built.coreset, d, "w")
    scale = 1 if r == 2 else P.MICRO
    wide = [math.floor((1 + eta) ** (1 if theorem else 2) * t) for t in capacities]
    full = {row["t"]: row["cost"] for row in C.two_centre_cost(points, *centres, spark.createDataFrame([(t,) for t in sorted({*capacities, *wide})], "t long"), r).collect()}

    def mine(t: float) -> float:
        return flow.capacitated(x[:, :d], w, np.array(centres), t, r) * scale

    def ratio(a: float | None, b: float | None) -> float:
        a, b = (math.inf if v is None else float(v) for v in (a, b))
        return 1.0 if a == b else math.inf if b == 0 else a / b

    rows = [(t, ratio(mine((1 + eta) * t), full[t]), ratio(full[u], mine(t if theorem else (1 + eta) * t))) for t, u in zip(capacities, wide, strict=True)]
    return spark.createDataFrame(rows, "t long, upper double, lower double")


def solution_quality(assigned: DataFrame, k: int, capacity: float, best: float) -> DataFrame:
    """alpha (cost over the best known), beta (largest cluster over the capacity) of an assignment (j, cost)."""
    largest = C.size_vector(assigned, k).agg(F.max("size").alias("largest"))
    return assigned.agg(F.sum("cost").alias("cost")).join(F.broadcast(largest), F.lit(True)).select((F.col("cost") / F.lit(float(best))).alias("alpha"), (F.col("largest") / F.lit(float(capacity))).alias("beta"))


def sampling_error(assigned: DataFrame, sampled: DataFrame, k: int, xi: float, side: float, r: float, d: int) -> DataFrame:
    """cost_error, size_error, cost_bound, size_bound: a sample's weighted cost and cluster sizes against those of all points.

    assigned: j, cost; sampled: the same with w. Bounds: xi times (points times the cell's diameter^r plus the cost), xi times points.
    """
    full = assigned.groupBy("j").agg(F.sum("cost").alias("c"), F.count("*").alias("n"))
    part = sampled.groupBy("j").agg(F.sum(F.col("cost") * F.col("w")).alias("pc"), F.sum("w").alias("pn"))
    met = full.join(part, "j", "full").na.fill(0)
    sums = met.agg(F.abs(F.sum("c") - F.sum("pc")).alias("cost_error"), F.sum(F.abs(F.col("n") - F.col("pn"))).alias("size_error"), F.sum("c").alias("c"), F.sum("n").alias("n"))
    return sums.select("cost_error", "size_error", (xi * (F.col("n") * (math.sqrt(d) * side) ** r + F.col("c"))).alias("cost_bound"), (xi * F.col("n")).alias("size_bound"))


def transfer_overhead(before: DataFrame, after: DataFrame, key: list[str], k: int, xi: float) -> DataFrame:
    """moved (points that change centre), moved_bound (16 k xi of all), cost_factor: what a transfer costs. before, after: key.., j, cost."""
    met = before.select(*key, F.col("j").alias("j0"), F.col("cost").alias("c0")).join(after.select(*key, "j", "cost"), key)
    out = met.agg(F.count_if(~F.col("j").eqNullSafe(F.col("j0"))).alias("moved"), F.count("*").alias("n"), F.sum("c0").alias("c0"), F.sum("cost").alias("c1"))
    return out.select("moved", (16 * k * xi * F.col("n")).alias("moved_bound"), (F.col("c1") / F.col("c0")).alias("cost_factor"))


def purity(assigned: DataFrame, label: str) -> DataFrame:
    """j, size, most (rows of the commonest label), purity of each cluster."""
    counts = assigned.groupBy("j", label).agg(F.count("*").alias("n"))
    return counts.groupBy("j").agg(F.sum("n").alias("size"), F.max("n").alias("most")).withColumn("purity", F.col("most") / F.col("size"))


def timed_sweep(points: DataFrame, eighths: tuple[int, ...], run) -> DataFrame:
    """eighths, n, seconds: how long run(points) takes, all of its rows made, on growing shares of the points by their tags."""
    rows = []
    for f in eighths:
        part = points.where(F.col("tag") % 8 < f)
        n, began = part.count(), time.perf_counter()
        run(part).write.format("noop").mode("overwrite").save()
        rows.append((f, n, time.perf_counter() - began))
    return points.sparkSession.createDataFrame(rows, "eighths int, n long, seconds double")


def residue(points_in_parts: DataFrame, important: DataFrame, key: list[str]) -> DataFrame:
    """n_left, share_left: points outside important parts."""
    n = points_in_parts.agg(F.count("*").alias("n"))
    left = points_in_parts.join(important, key, "left_anti").agg(F.count("*").alias("n_left"))
    return left.join(F.broadcast(n), F.lit(True)).select("n_left", (F.col("n_left") / F.col("n")).alias("share_left"))


def stream_bits(shape_rows: int, sums: int, families: int, levels: int, independence: int) -> int:
    """Bits of all sketches of a stream and of its hash coefficients."""
    return shape_rows * sums * 64 * families * levels + families * independence * 31
