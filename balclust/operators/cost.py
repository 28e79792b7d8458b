"""Clustering costs: nearest centre, exact two centres under a capacity, certified bounds for more.

Costs are sums of whole numbers (squares, or millionths for other powers), so they do not depend on order.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from balclust.functions import points as P

Centres = Sequence[Sequence[int]]


def distances(coordinates: Sequence[str], centres: Centres, r: float) -> list[Column]:
    return [P.dist_r(P.sqdist(coordinates, z), r) for z in centres]


def nearest(df: DataFrame, centres: Centres, r: float = 2) -> DataFrame:
    """df with j (the nearest centre, the first of ties, from 0) and cost."""
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    each = [F.struct(c.alias("cost"), F.lit(k).alias("j")) for k, c in enumerate(distances(coordinates, centres, r))]
    best = df.withColumn("_near", F.least(*each) if len(each) > 1 else each[0])
    return best.select(*(c for c in df.columns if c not in ("j", "cost")), F.col("_near.j").alias("j"), F.col("_near.cost").alias("cost"))


def plain_cost(df: DataFrame, centres: Centres, r: float = 2, weight: str | None = None, wide: bool = False) -> DataFrame:
    """cost: without capacities, everything goes to its nearest centre. wide: sums of 38 digits, for inputs whose cost may pass 2^63."""
    each = nearest(df, centres, r)
    paid = F.col("cost").cast("decimal(20,0)") if wide else F.col("cost")
    return each.agg(F.coalesce(F.sum(paid * F.col(weight)) if weight else F.sum(paid), F.lit(0)).alias("cost"))


def size_vector(assigned: DataFrame, k: int, weight: str | None = None) -> DataFrame:
    """j, size of each centre, empty ones too."""
    sizes = assigned.groupBy("j").agg((F.sum(weight) if weight else F.count("*")).alias("size"))
    return assigned.sparkSession.range(k).select(F.col("id").cast("int").alias("j")).join(F.broadcast(sizes), "j", "left").select("j", F.coalesce("size", F.lit(0)).alias("size"))


def order_key(coordinates: Sequence[str], a: Sequence[int], b: Sequence[int], r: float) -> list[Column]:
    """What orders points between two centres: difference of the distances, then the point, then the tag."""
    return [(P.dist_r(P.sqdist(coordinates, a), r) - P.dist_r(P.sqdist(coordinates, b), r)).alias("diff"), *(F.col(x) for x in coordinates), F.col("tag")]


def two_centre_sweep(df: DataFrame, a: Sequence[int], b: Sequence[int], r: float = 2, buckets: int = 64) -> DataFrame:
    """m, cost: the cost of sending the first m points of the order to a and the others to b, for every m at which the difference changes.

    Points of one difference count alike, so differences are counted first; running sums are taken within buckets of about equally many
    differences, by their quantiles, and then over the buckets, never over all rows in one task.
    """
    coordinates = [f"x{m}" for m in range(len(a))]
    diff = (P.dist_r(P.sqdist(coordinates, a), r) - P.dist_r(P.sqdist(coordinates, b), r)).alias("diff")
    to_b = P.dist_r(P.sqdist(coordinates, b), r).alias("to_b")
    counted = df.select(diff, to_b).groupBy("diff").agg(F.count("*").alias("n"), F.sum("to_b").alias("to_b"))
    edges = counted.agg(F.percentile_approx("diff", [k / buckets for k in range(1, buckets)], 10 * buckets)).first()[0] or []
    split = counted.withColumn("bucket", F.size(F.filter(F.lit(sorted(set(edges))), lambda e: e < F.col("diff"))) if edges else F.lit(0))
    inner = W.partitionBy("bucket").orderBy("diff")
    part = split.withColumns({"m": F.sum("n").over(inner), "moved": F.sum(F.col("n") * F.col("diff")).over(inner)})
    totals = split.groupBy("bucket").agg(F.sum("n").alias("bn"), F.sum(F.col("n") * F.col("diff")).alias("bd"), F.sum("to_b").alias("bb"))
    before = W.orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    everything = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    based = totals.select("bucket", F.coalesce(F.sum("bn").over(before), F.lit(0)).alias("m0"), F.coalesce(F.sum("bd").over(before), F.lit(0)).alias("d0"), F.sum("bb").over(everything).alias("all_b"))
    return part.join(based, "bucket").select("diff", "n", (F.col("m") + F.col("m0")).alias("m"), (F.col("all_b") + F.col("moved") + F.col("d0")).alias("cost"))


def two_centre_cost(df: DataFrame, a: Sequence[int], b: Sequence[int], capacities: DataFrame, r: float = 2) -> DataFrame:
    """t, cost of each capacity t: exact; null if 2 t points are too few.

    The cost is convex in m, so between n - t and t the best m is the clamped one where differences turn positive.
    capacities: t (long).
    """
    coordinates = [f"x{m}" for m in range(len(a))]
    diff = P.dist_r(P.sqdist(coordinates, a), r) - P.dist_r(P.sqdist(coordinates, b), r)
    counted = df.select(diff.alias("diff"), P.dist_r(P.sqdist(coordinates, b), r).alias("to_b")).groupBy("diff").agg(F.count("*").alias("n"), F.sum("to_b").alias("to_b"))
    total = counted.agg(F.sum("n").alias("all_n"), F.sum("to_b").alias("all_b"), F.coalesce(F.sum(F.when(F.col("diff") < 0, F.col("n"))), F.lit(0)).alias("free"))
    wanted = capacities.crossJoin(F.broadcast(total)).withColumn("m", F.greatest(F.col("all_n") - F.col("t"), F.least("t", "free")))
    sweep = two_centre_sweep(df, a, b, r).select("diff", "n", F.col("m").alias("upto"), "cost")
    # The step that the m-th point falls into: part of it goes. The sweep stays in place; the few capacities go to it.
    met = sweep.join(F.broadcast(wanted.select("t", "m")), (F.col("m") <= F.col("upto")) & (F.col("m") > F.col("upto") - F.col("n")))
    part = met.select("t", (F.col("cost") - (F.col("upto") - F.col("m")) * F.col("diff")).alias("part"))
    cost = F.when(2 * F.col("t") < F.col("all_n"), None).when(F.col("m") == 0, F.col("all_b")).otherwise(F.col("part"))
    return wanted.join(part, "t", "left").select("t", cost.cast("long").alias("cost"))


def dual_bound(df: DataFrame, centres: Centres, prices: Sequence[int], t: float, r: float = 2, weight: str | None = None) -> DataFrame:
    """bound: any prices on centres give a lower bound of the cost under capacity t, in one pass."""
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    priced = [d + F.lit(int(p)) for d, p in zip(distances(coordinates, centres, r), prices, strict=True)]
    low = F.least(*priced) if len(priced) > 1 else priced[0]
    return df.agg((F.sum(low * F.col(weight)) if weight else F.sum(low)).alias("s")).select((F.col("s") - F.lit(float(t) * sum(prices))).alias("bound"))


def set_distance(df: DataFrame, centres: Centres) -> DataFrame:
    """sqdist: the least squared distance between the points and a set of centres."""
    return nearest(df, centres, 2).agg(F.min("cost").alias("sqdist"))


def bottleneck(df: DataFrame, centres: Centres, radius: int) -> DataFrame:
    """n_far: points without a centre within a squared radius (the measure for r without bound)."""
    each = nearest(df, centres, 2)
    return each.agg(F.count(F.when(F.col("cost") > radius, 1)).alias("n_far"))


def _after(counted: DataFrame, column: str, skip: int) -> int:
    """The value of the (skip + 1)-th largest entry of a histogram (column, n); 0 if there are no more."""
    down = W.orderBy(F.col(column).desc())  # values of a lattice's squared distances: as many as its sides allow, not as there are points
    found = counted.withColumn("upto", F.sum("n").over(down)).where(F.col("upto") > skip).agg(F.max(column)).first()[0]
    return 0 if found is None else int(found)


def two_centre_bottleneck(df: DataFrame, a: Sequence[int], b: Sequence[int], capacities: Sequence[int]) -> DataFrame:
    """t, radius: the least squared radius within which all points can be assigned under each capacity t (r without bound); null if 2 t points are too few.

    Points out of b's reach are a's, and the other way round; both must fit, and every point must be in reach of one.
    """
    coordinates = [f"x{m}" for m in range(len(a))]
    both = df.select(P.sqdist(coordinates, a).cast("long").alias("da"), P.sqdist(coordinates, b).cast("long").alias("db"))
    n, least = both.agg(F.count("*"), F.max(F.least("da", "db"))).first()
    hist = {c: both.groupBy(c).agg(F.count("*").alias("n")) for c in ("da", "db")}
    rows = [(int(t), max(least, _after(hist["da"], "da", t), _after(hist["db"], "db", t)) if 2 * t >= n and n else None) for t in capacities]
    return df.sparkSession.createDataFrame(rows, "t long, radius long")


#: Rows of a summary that the driver takes; more than that is an error, not a cut.
MOST = 2_000_000


def on_driver(df: DataFrame, most: int = MOST):
    """df as a pandas frame, if it has at most so many rows."""
    table = df.limit(most + 1).toPandas()
    if len(table) > most:
        raise ValueError(f"more than {most} rows are not for the driver: choose a larger guess or a smaller m")
    return table


def arrays(df: DataFrame, d: int, weight: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Coordinates (with the tag last) and weights of a summary, in a fixed order, on the driver."""
    table = on_driver(df.select(*(f"x{m}" for m in range(d)), "tag", (F.col(weight) if weight else F.lit(1.0)).alias("w")))
    raw = table[[*(f"x{m}" for m in range(d)), "tag"]].to_numpy(np.int64)
    order = np.lexsort(raw.T[::-1])
    return raw[order], table["w"].to_numpy(float)[order]
