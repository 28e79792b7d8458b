"""What the summary is compared with: plain samples, snapped cells, rings, chunks and a sequential facility stream."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.functions import points as P
from balclust.operators import cost as C
from balclust.operators import partition, solvers
from balclust.plans.params import Params
from balclust.sources.store import staged


def uniform_sample(points: DataFrame, rate: float, h: P.Hash, d: int) -> DataFrame:
    """One rate everywhere."""
    cut = P.threshold(rate)
    kept = points.withColumn("h", P.poly_hash(["tag", *(f"x{m}" for m in range(d))], h)).where(F.col("h") < cut)
    return kept.drop("h").withColumn("w", F.lit(P.RANGE / cut))


def parts_of(points: DataFrame, grid: P.Grid, params: Params) -> DataFrame:
    """points with level, p0.., size of their part."""
    cells = partition.cell_counts(partition.leaf_counts(points, grid), grid)
    key = ["level", *(f"p{m}" for m in range(grid.d))]
    heavy = partition.heavy_cells(cells, params).select("level", *grid.key_names, "n")
    rows = partition.held(heavy, grid)
    if rows is not None:
        heavy = partition.frame(points.sparkSession, rows, grid)
    sizes = partition.parts_of_cells(heavy, grid)
    return partition.routed_points(points, heavy, grid, rows).join(sizes if rows is None else F.broadcast(sizes), key)


def plain_coreset(points: DataFrame, grid: P.Grid, params: Params, h: P.Hash, budget: int) -> DataFrame:
    """Every part sampled at budget over its size: right for costs without capacities."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    met = parts_of(points, grid, params)
    cut = F.floor(F.least(F.lit(float(P.RANGE)), F.lit(float(P.RANGE)) * budget / F.col("size")))
    kept = met.withColumn("cut", cut).where(P.poly_hash(["tag", *coordinates], h) < F.col("cut"))
    return kept.select("tag", *coordinates, "level", *(f"p{m}" for m in range(grid.d)), (F.lit(float(P.RANGE)) / F.col("cut")).alias("w"))


def snap_coreset(points: DataFrame, grid: P.Grid, params: Params) -> DataFrame:
    """Each part moved to its smallest point, weighted by its size."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    key = ["level", *(f"p{m}" for m in range(grid.d))]
    first = parts_of(points, grid, params).groupBy(*key).agg(F.min(F.struct(*coordinates, "tag")).alias("z"), F.count("*").alias("w"))
    return first.select(*(F.col(f"z.{c}").alias(c) for c in (*coordinates, "tag")), *key, "w")


def movement_bound(points: DataFrame, grid: P.Grid, params: Params) -> DataFrame:
    """moved: what moving parts to one of their points can cost, part size times squared diameter of its box (r = 2)."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    key = ["level", *(f"p{m}" for m in range(grid.d))]
    box = parts_of(points, grid, params).groupBy(*key).agg(F.count("*").alias("n"), *(F.max(x).alias(f"hi_{x}") for x in coordinates), *(F.min(x).alias(f"lo_{x}") for x in coordinates))
    diameter = sum((F.col(f"hi_{x}") - F.col(f"lo_{x}")) * (F.col(f"hi_{x}") - F.col(f"lo_{x}")) for x in coordinates)
    return box.agg(F.sum(F.col("n") * diameter).cast("long").alias("moved"))


def ring_coreset(points: DataFrame, centres: C.Centres, h: P.Hash, budget: int) -> DataFrame:
    """Rings of doubling radius around given centres, each sampled at budget over its size."""
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    near = C.nearest(points, centres, 2)
    ring = F.when(F.col("cost") == 0, F.lit(-1)).otherwise(F.length(F.bin("cost")) - 1)
    near = near.withColumn("ring", ring.cast("int")).drop("cost")
    met = near.join(F.broadcast(near.groupBy("j", "ring").agg(F.count("*").alias("size"))), ["j", "ring"])  # centres times at most 64 rings
    cut = F.floor(F.least(F.lit(float(P.RANGE)), F.lit(float(P.RANGE)) * budget / F.col("size")))
    kept = met.withColumn("cut", cut).where(P.poly_hash(["tag", *coordinates], h) < F.col("cut"))
    return kept.select("tag", *coordinates, "j", "ring", (F.lit(float(P.RANGE)) / F.col("cut")).alias("w"))


def ring_cells(points: DataFrame, centres: C.Centres, fine: int = 3) -> DataFrame:
    """Cells within rings, finer nearer the centre, one weighted point each: an exponential grid."""
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    near = C.nearest(points, centres, 2)
    ring = F.when(F.col("cost") == 0, F.lit(0)).otherwise(F.floor((F.length(F.bin("cost")) - 1) / 2)).cast("int")
    near = near.withColumn("ring", ring)
    drop = F.greatest(F.lit(0), F.col("ring") - fine)
    cells = [F.call_function("shiftright", F.col(x), drop.cast("int")).alias(f"g{m}") for m, x in enumerate(coordinates)]
    return near.groupBy("j", "ring", *cells).agg(F.min(F.struct(*coordinates, "tag")).alias("z"), F.count("*").alias("w")).select(*(F.col(f"z.{c}").alias(c) for c in (*coordinates, "tag")), "j", "ring", "w")


def three_pass(points: DataFrame, k: int, t: float, r: float, d: int) -> tuple[list, float, DataFrame]:
    """(centres, cost of the snapped solution, points with their snap): seeds, snap and count, solve the snapped set, lift."""
    seeds, _ = solvers.opt_estimate(points, 4 * k, r, d)
    snapped = C.nearest(points, seeds.tolist(), r)
    counts = C.size_vector(snapped, len(seeds)).toPandas().sort_values("j")["size"].to_numpy(float)
    held = counts > 0
    z, cost = solvers.alternate(seeds[held], counts[held], k, t, r)
    return z.tolist(), cost, snapped


def chunk_reduce(points: DataFrame, k: int, r: float, d: int, chunk_rows: int = 20_000) -> DataFrame:
    """x0.., w: each chunk of about chunk_rows rows reduced to weighted centres on executors; the number of chunks grows with the input. points may carry weights w."""
    coordinates = [f"x{m}" for m in range(d)]
    chunks = max(1, -(-points.count() // chunk_rows))
    points = points if "w" in points.columns else points.withColumn("w", F.lit(1).cast("long"))

    def reduce_(pdf: pd.DataFrame) -> pd.DataFrame:
        x = pdf[coordinates].to_numpy(np.int64)
        w = pdf["w"].to_numpy(float)
        z, _ = solvers.alternate(x, w, min(k, len(x)), float(len(x)), r, rounds=4)
        near = np.bincount(((x[:, None] - z[None]) ** 2).sum(axis=2).argmin(axis=1), w, len(z))
        return pd.DataFrame({**{c: z[:, m] for m, c in enumerate(coordinates)}, "w": near.astype(np.int64)})

    dealt = points.withColumn("chunk", F.pmod(F.xxhash64(*(c for c in ("tag", *coordinates, "w") if c in points.columns)), F.lit(chunks)))
    return dealt.groupBy("chunk").applyInPandas(reduce_, ", ".join(f"{c} long" for c in coordinates) + ", w long")


def hierarchy(points: DataFrame, k: int, t: float, r: float, d: int, per_chunk: int = 64, chunk_rows: int = 20_000) -> tuple[list, float, int]:
    """(centres, cost on the weighted rest, rounds): chunks reduced to weighted centres, and those again, until one chunk holds what is left, which is solved under the capacity t."""
    now, rounds = staged(chunk_reduce(points, per_chunk, r, d, chunk_rows)), 1
    while now.count() > chunk_rows:
        now, rounds = staged(chunk_reduce(now, per_chunk, r, d, chunk_rows)), rounds + 1
    x, w = C.arrays(now.withColumn("tag", F.xxhash64(*now.columns)), d, "w")
    z, cost = solvers.alternate(x[:, :d], w, k, t, r)
    return z.tolist(), cost, rounds


def merged_facilities(points: DataFrame, k: int, t: float, r: float, d: int, fee: float) -> tuple[list, float]:
    """(centres, cost on the weighted facilities): the facilities of all partitions together, solved under the capacity t."""
    found = facility_stream(points, r, d, fee)
    x, w = C.arrays(found.withColumn("tag", F.xxhash64(*found.columns)), d, "w")
    z, cost = solvers.alternate(x[:, :d], w, k, t, r)
    return z.tolist(), cost


def facility_stream(points: DataFrame, r: float, d: int, fee: float) -> DataFrame:
    """x0.., w: facilities that each partition opens in one pass, with chance in proportion to a point's distance over the fee."""
    coordinates = [f"x{m}" for m in range(d)]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        z, w = np.zeros((0, d), np.int64), []
        for pdf in batches:
            for x, u in zip(pdf[coordinates].to_numpy(np.int64), pdf["u"].to_numpy(), strict=True):
                dist = ((z - x) ** 2).sum(axis=1) if len(z) else np.array([np.inf])
                j = int(dist.argmin())
                if not len(z) or u < dist[j] ** (r / 2) / fee:
                    z = np.concatenate([z, x[None]])
                    w.append(1)
                else:
                    w[j] += 1
        if len(z):
            yield pd.DataFrame({**{c: z[:, m] for m, c in enumerate(coordinates)}, "w": np.array(w, np.int64)})

    chance = F.pmod(F.xxhash64("tag", *coordinates), F.lit(1 << 30)) / F.lit(float(1 << 30))
    return points.select(*coordinates, chance.alias("u")).mapInPandas(run, ", ".join(f"{c} long" for c in coordinates) + ", w long")


def library_kmeans(points: DataFrame, k: int, d: int, seed: int = 1) -> tuple[list, float]:
    """The engine library's own k-means, without capacities."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    table = VectorAssembler(inputCols=[f"x{m}" for m in range(d)], outputCol="features").transform(points)
    model = KMeans(k=k, seed=seed, maxIter=10).fit(table)
    centres = [[int(round(v)) for v in c] for c in model.clusterCenters()]
    return centres, float(model.summary.trainingCost)
