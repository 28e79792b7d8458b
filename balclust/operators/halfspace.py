"""Half-spaces between centres, the regions they cut, and the transfer of sparse regions.

A half-space is a prefix of the order of points between two centres; its end is a struct (difference, point, tag). All
comparisons are columns, so that regions of every input row come from one map over the points.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from balclust.functions import points as P
from balclust.operators.cost import Centres


def pair_key(coordinates: Sequence[str], a: Sequence[int], b: Sequence[int], r: float) -> Column:
    diff = P.dist_r(P.sqdist(coordinates, a), r) - P.dist_r(P.sqdist(coordinates, b), r)
    return F.struct(diff.alias("diff"), *(F.col(x).cast("long").alias(x) for x in coordinates), F.col("tag").cast("long").alias("tag"))


def pairs(k: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(k) for j in range(i + 1, k)]


def derive(assigned: DataFrame, centres: Centres, r: float, by: Sequence[str] = ("level",)) -> DataFrame:
    """by.., and h_i_j for each pair: the last point that goes to i; null where none does. assigned: x0.., tag, j."""
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    ends = [F.max(F.when(F.col("j") == i, pair_key(coordinates, centres[i], centres[j], r))).alias(f"h_{i}_{j}") for i, j in pairs(len(centres))]
    return assigned.groupBy(*by).agg(*ends) if ends else assigned.select(*by).distinct()


def separable(assigned: DataFrame, centres: Centres, r: float, by: Sequence[str] = ("level",)) -> DataFrame:
    """by.., i, j, ok: whether all points at i come before all points at j."""
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    out = None
    for i, j in pairs(len(centres)):
        key = pair_key(coordinates, centres[i], centres[j], r)
        one = assigned.groupBy(*by).agg(F.max(F.when(F.col("j") == i, key)).alias("last"), F.min(F.when(F.col("j") == j, key)).alias("first"))
        one = one.select(*by, F.lit(i).alias("i"), F.lit(j).alias("j"), F.coalesce(F.col("last") < F.col("first"), F.lit(True)).alias("ok"))
        out = one if out is None else out.unionByName(one)
    return out


def regions(df: DataFrame, ends: DataFrame, centres: Centres, r: float, by: Sequence[str] = ("level",)) -> DataFrame:
    """df with region: 1..k, or 0 where no centre wins all its comparisons. ends: as derive gives, a few rows that are broadcast (one per level)."""
    k = len(centres)
    if k == 1:
        return df.withColumn("region", F.lit(1))
    coordinates = [f"x{m}" for m in range(len(centres[0]))]
    met = df.join(F.broadcast(ends), list(by), "left")
    # Distances and comparisons are columns of their own: written out, each distance would be worked out again in each of k (k - 1) comparisons.
    met = met.withColumns({f"_d{i}": P.dist_r(P.sqdist(coordinates, z), r) for i, z in enumerate(centres)})
    point = [F.col(x).cast("long").alias(x) for x in coordinates] + [F.col("tag").cast("long").alias("tag")]
    met = met.withColumns({f"_b_{i}_{j}": F.coalesce(F.struct((F.col(f"_d{i}") - F.col(f"_d{j}")).alias("diff"), *point) <= F.col(f"h_{i}_{j}"), F.lit(False)) for i, j in pairs(k)})

    def wins(i: int) -> Column:
        return reduce(lambda a, b: a & b, [F.col(f"_b_{i}_{j}") if i < j else ~F.col(f"_b_{j}_{i}") for j in range(k) if j != i])

    region = reduce(lambda rest, i: F.when(wins(i), F.lit(i + 1)).otherwise(rest), reversed(range(k)), F.lit(0))
    return met.withColumn("region", region).drop(*(f"_d{i}" for i in range(k)), *(f"{name}_{i}_{j}" for i, j in pairs(k) for name in ("h", "_b")))


def tallies(df: DataFrame, k: int, by: Sequence[str], weight: str = "w") -> DataFrame:
    """by.., b0..bk: weight in each region of each part."""
    return df.groupBy(*by).agg(*(F.coalesce(F.sum(F.when(F.col("region") == i, F.col(weight))), F.lit(0.0)).alias(f"b{i}") for i in range(k + 1)))


def transfer(df: DataFrame, tally: DataFrame, k: int, by: Sequence[str], least: Column) -> DataFrame:
    """df with j: a point stays with its region's centre if the region holds at least least (twice xi times the part's bound); else it goes to the fullest region's.

    tally: by.., b0..bk; rows with no tally get null.
    """
    met = df.join(tally, list(by), "left")
    full = F.greatest(*(F.col(f"b{i}") for i in range(1, k + 1))) if k > 1 else F.col("b1")
    fullest = reduce(lambda rest, i: F.when(F.col(f"b{i}") == full, F.lit(i)).otherwise(rest), reversed(range(1, k + 1)), F.lit(None).cast("int"))
    own = reduce(lambda rest, i: F.when(F.col("region") == i, F.col(f"b{i}")).otherwise(rest), range(1, k + 1), F.lit(None).cast("double"))
    stays = (F.col("region") > 0) & (own >= least)
    return met.withColumn("j", F.when(F.col("b0").isNull(), None).when(stays, F.col("region") - 1).otherwise(fullest - 1).cast("int")).drop(*(f"b{i}" for i in range(k + 1)))


def exchange_ties(assigned: DataFrame, a: Sequence[int], b: Sequence[int], r: float, by: Sequence[str] = ("level",)) -> DataFrame:
    """assigned (x0.., tag, j of 0 or 1) with points of one difference exchanged until the lexicographically smaller ones are with the first centre; costs and sizes stay.

    Points of one difference lie on one curve of the lattice; their places are ranks within it.
    """
    coordinates = [f"x{m}" for m in range(len(a))]
    diff = P.dist_r(P.sqdist(coordinates, a), r) - P.dist_r(P.sqdist(coordinates, b), r)
    tie = W.partitionBy(*by, "_diff")
    ranked = assigned.withColumn("_diff", diff).withColumn("_first", F.sum((F.col("j") == 0).cast("long")).over(tie)).withColumn("_rank", F.row_number().over(tie.orderBy(*coordinates, "tag")))
    return ranked.withColumn("j", F.when(F.col("_rank") <= F.col("_first"), 0).otherwise(1).cast("int")).drop("_diff", "_first", "_rank")
