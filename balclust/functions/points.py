"""Points of a lattice: discretisation, tags, distances, shifted grids and limited-independence hashes as columns."""

from __future__ import annotations

import random
from collections.abc import Sequence
from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

#: The hash field: a prime below 2^31, so that products fit into 64 bits. A hash is a pair of its elements, a number below RANGE.
FIELD = (1 << 31) - 1
RANGE = FIELD * FIELD


class Dimension(NamedTuple):
    """expression: Spark SQL of the real value; sql: the same for DuckDB, if it differs."""

    expression: str
    low: float
    high: float
    sql: str = ""


class PointSpec(NamedTuple):
    """How a table becomes points of {1..2^levels}^d. key: columns that tell rows apart; none: rows with equal points are numbered by order."""

    name: str
    table: str
    dimensions: tuple[Dimension, ...]
    levels: int
    key: str = ""
    order: tuple[str, ...] = ()

    @property
    def d(self) -> int:
        return len(self.dimensions)

    @property
    def side(self) -> int:
        return 1 << self.levels

    @property
    def coordinates(self) -> list[str]:
        return [f"x{m}" for m in range(self.d)]


def lattice(value: Column, low: float, high: float, levels: int) -> Column:
    """The lattice value of a real one; what lies outside the declared bounds is clamped."""
    side = 1 << levels
    raw = F.floor((value.cast("double") - low) / (high - low) * (side - 1)) + 1
    return F.least(F.lit(side), F.greatest(F.lit(1), raw)).cast("long")


def discretize(df: DataFrame, spec: PointSpec, keep: Sequence[str] = ()) -> DataFrame:
    """x0.. of each row of a table, with the columns to keep."""
    return df.select(*keep, *(lattice(F.expr(m.expression), m.low, m.high, spec.levels).alias(x) for x, m in zip(spec.coordinates, spec.dimensions, strict=True)))


def clamped(df: DataFrame, spec: PointSpec) -> DataFrame:
    """How many rows lie outside the declared bounds of each dimension."""
    return df.agg(*(F.count(F.when((F.expr(m.expression) < m.low) | (F.expr(m.expression) > m.high), 1)).alias(f"clamped_{x}") for x, m in zip(spec.coordinates, spec.dimensions, strict=True)))


def points(df: DataFrame, spec: PointSpec, keep: Sequence[str] = ()) -> DataFrame:
    """pid, x0.., tag: distinct tagged points. The key column is the tag; without one, equal points are numbered in the given order."""
    if spec.key:
        return discretize(df, spec, [F.col(spec.key).cast("long").alias("tag"), *keep])
    placed = discretize(df, spec, [*spec.order, *(c for c in keep if c not in spec.order)])
    tag = F.row_number().over(W.partitionBy(*spec.coordinates).orderBy(*spec.order)).cast("long")
    return placed.select(tag.alias("tag"), *keep, *spec.coordinates)


def tag_by_hash(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """df with a tag that needs no shuffle: a 62-bit hash of the columns that tell rows apart."""
    return df.withColumn("tag", F.shiftrightunsigned(F.xxhash64(*columns), 2))


def sqdist(coordinates: Sequence[str], centre: Sequence[int]) -> Column:
    return reduce(lambda a, b: a + b, ((F.col(x) - F.lit(int(z))) * (F.col(x) - F.lit(int(z))) for x, z in zip(coordinates, centre, strict=True)))


#: Distances to other powers than squares are counted in millionths, rounded row by row, so that sums do not depend on order.
MICRO = 1_000_000


def dist_r(squared: Column, r: float) -> Column:
    """Euclidean distance to the power r as a whole number: exact for r = 2, in millionths otherwise.

    Powers that are multiples of a half are products of square roots, which every engine rounds alike.
    """
    if r == 2:
        return squared.cast("long")
    square = squared.cast("double")
    factors = [square] * int(r // 2)
    if (2 * r) % 1:
        factors = [F.pow(F.sqrt(square), F.lit(float(r)))]
    else:
        factors += [F.sqrt(square)] * (int(2 * r) % 4 // 2) + [F.sqrt(F.sqrt(square))] * (int(2 * r) % 2)
    return F.round(reduce(lambda a, b: a * b, factors) * MICRO).cast("long")


class Grid(NamedTuple):
    """Randomly shifted nested grids: a point's key at level i is its leaf key without its last levels - i bits."""

    d: int
    levels: int
    shift: tuple[int, ...]

    def leaf(self, coordinates: Sequence[str]) -> list[Column]:
        return [(F.col(x) - F.lit(u) + F.lit(1 << self.levels)).alias(f"c{m}") for m, (x, u) in enumerate(zip(coordinates, self.shift, strict=True))]

    def keys(self, level: Column | int) -> list[Column]:
        drop = F.lit(self.levels) - level
        return [F.expr(f"shiftright(c{m}, {self.levels} - {level})") if isinstance(level, int) else F.call_function("shiftright", F.col(f"c{m}"), drop.cast("int")) for m in range(self.d)]

    @property
    def names(self) -> list[str]:
        return [f"c{m}" for m in range(self.d)]

    @property
    def key_names(self) -> list[str]:
        return [f"k{m}" for m in range(self.d)]


def grid(d: int, levels: int, seed: int) -> Grid:
    rng = random.Random(f"grid {seed}")
    return Grid(d, levels, tuple(rng.randint(1, 1 << levels) for _ in range(d)))


class Poly(NamedTuple):
    """A polynomial over the field, of a point folded into one element; fold: the evaluation point that merges tag and coordinates."""

    fold: int
    coefficients: tuple[int, ...]


class Hash(NamedTuple):
    """Two polynomials of degree below the independence, each with a fold of its own: points collide only if they do in both, with a chance of about 2^-62."""

    first: Poly
    second: Poly


def hash_family(seed: int, family: str, independence: int) -> Hash:
    """The hash of a family; families share neither folds nor coefficients."""

    def one(part: str) -> Poly:
        rng = random.Random(f"{family} {part} {seed}")
        return Poly(rng.randrange(1 << 20, FIELD), tuple(rng.randrange(1, FIELD) for _ in range(independence)))

    return Hash(one("high"), one("low"))


def folded(columns: Sequence[str], fold: int) -> Column:
    """The tagged point as one element of the field."""
    acc = F.pmod(F.col(columns[0]).cast("long"), F.lit(FIELD))
    for c in columns[1:]:
        acc = (acc * F.lit(fold) + F.col(c)) % F.lit(FIELD)
    return acc


def evaluated(columns: Sequence[str], p: Poly) -> Column:
    point = folded(columns, p.fold)
    acc = F.lit(p.coefficients[0]).cast("long")
    for c in p.coefficients[1:]:
        acc = (acc * point + F.lit(c)) % F.lit(FIELD)
    return acc


def poly_hash(columns: Sequence[str], h: Hash) -> Column:
    return evaluated(columns, h.first) * F.lit(FIELD) + evaluated(columns, h.second)


def threshold(rate: float) -> int:
    """The hash values below it are sampled; threshold / RANGE is the rate that weights use."""
    return RANGE if rate >= 1 else max(1, int(rate * RANGE))
