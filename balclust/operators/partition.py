"""Cells of nested grids, heavy and crucial, and the parts they make.

Counting touches the points once: distinct leaves are counted first and only those are rolled up to the other
levels. With exact counts a cell's ancestors hold at least what it holds while their thresholds are lower, so
"heavy with heavy ancestors" is one filter, and a point's part follows from its deepest heavy cell.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from balclust.functions.points import Grid
from balclust.plans.params import Params


def leaf_counts(df: DataFrame, grid: Grid, weight: str | None = None) -> DataFrame:
    """c0.., n of each non-empty leaf. df: x0..; weight: a signed count column."""
    leaf = df.select(*grid.leaf([f"x{m}" for m in range(grid.d)]), *([F.col(weight)] if weight else []))
    return leaf.groupBy(*grid.names).agg((F.sum(weight) if weight else F.count("*")).cast("long").alias("n"))


def cell_counts(leaves: DataFrame, grid: Grid) -> DataFrame:
    """level, k0.., n of each non-empty cell of levels -1 to the leaves."""
    levels = F.explode(F.array(*(F.lit(i) for i in range(-1, grid.levels + 1)))).alias("level")
    each = leaves.select("*", levels)
    keyed = each.select("level", *(k.alias(name) for k, name in zip(grid.keys(F.col("level")), grid.key_names, strict=True)), "n")
    return keyed.groupBy("level", *grid.key_names).agg(F.sum("n").alias("n"))


def by_level(level_column: str, values: dict[int, float]) -> F.Column:
    """A column that takes a value for each level; whole numbers stay exact. One look-up: a level written out for each value would be worked out as often."""
    kind = "long" if all(isinstance(v, int) for v in values.values()) else "double"
    least = min(values)
    held = F.array(*(F.lit(values.get(level)).cast(kind) for level in range(least, max(values) + 1)))
    return F.get(held, F.col(level_column).cast("int") - F.lit(least))


def thresholds(params: Params) -> dict[int, float]:
    return {i: params.cell_threshold(i) for i in range(-1, params.levels + 1)}


def heavy_cells(cells: DataFrame, params: Params) -> DataFrame:
    """The heavy cells of exact counts."""
    return cells.where((F.col("level") < params.levels) & (F.col("n") >= by_level("level", thresholds(params))))


def mark_cells(cells: DataFrame, grid: Grid, params: Params, size: str = "n") -> DataFrame:
    """level, k0.., n, kind (heavy, crucial or inside) for sizes that may be estimates: level by level, each looking at its marked parents."""
    limit = thresholds(params)
    out = None
    parents = None
    for level in range(-1, params.levels + 1):
        own = cells.where(F.col("level") == level)
        if parents is None:
            own = own.withColumn("open", F.lit(True))
        else:
            up = parents.where(F.col("kind") == "heavy").select(*(F.col(k).alias(f"p{k}") for k in grid.key_names), F.lit(True).alias("open"))
            own = own.join(up, [F.expr(f"shiftright({k}, 1)") == F.col(f"p{k}") for k in grid.key_names], "left").drop(*(f"p{k}" for k in grid.key_names))
        heavy = (F.col(size) >= limit[level]) if level < params.levels else F.lit(False)
        parents = own.withColumn("kind", F.when(F.col("open").isNull(), "inside").when(heavy, "heavy").otherwise("crucial")).drop("open")
        out = parents if out is None else out.unionByName(parents)
    return out


def mark_exact(cells: DataFrame, grid: Grid, params: Params) -> DataFrame:
    """The same marks from exact counts by one self-join on the parent's key: a cell is open if its parent is heavy."""
    heavy = F.when(F.col("level") < params.levels, F.col("n") >= by_level("level", thresholds(params))).otherwise(F.lit(False))
    own = cells.withColumn("heavy", heavy)
    up = own.where("heavy").select((F.col("level") + 1).alias("level"), *(F.col(k).alias(f"p{k}") for k in grid.key_names), F.lit(True).alias("open"))
    keyed = own.withColumns({f"p{k}": F.expr(f"shiftright({k}, 1)") for k in grid.key_names})
    met = keyed.join(up, ["level", *(f"p{k}" for k in grid.key_names)], "left")
    kind = F.when(F.col("heavy"), "heavy").when((F.col("level") == -1) | F.col("open"), "crucial").otherwise("inside")
    return met.select("level", *grid.key_names, "n", kind.alias("kind"))


def part_sizes(marked: DataFrame, grid: Grid) -> DataFrame:
    """level, p0.., size: parts are the crucial cells below one heavy cell; sizes come from cell counts alone."""
    parent = [F.expr(f"shiftright({k}, 1)").alias(f"p{m}") for m, k in enumerate(grid.key_names)]
    return marked.where((F.col("kind") == "crucial") & (F.col("level") >= 0)).select("level", *parent, "n").groupBy("level", *(f"p{m}" for m in range(grid.d))).agg(F.sum("n").alias("size"))


def leaf_levels(leaves: DataFrame, cells: DataFrame, grid: Grid, params: Params) -> DataFrame:
    """c0.., level, p0..: the part of each leaf, one level below its deepest heavy cell; leaves without one are left out."""
    return deepest(leaves, heavy_cells(cells, params), grid)


def deepest(leaves: DataFrame, heavy: DataFrame, grid: Grid) -> DataFrame:
    """The same for heavy cells however found."""
    levels = F.explode(F.array(*(F.lit(i) for i in range(-1, grid.levels)))).alias("level")
    each = leaves.select(*grid.names, levels).withColumns(dict(zip(grid.key_names, grid.keys(F.col("level")), strict=True)))
    found = each.join(heavy.select("level", *grid.key_names), ["level", *grid.key_names], "left_semi").groupBy(*grid.names).agg((F.max("level") + 1).alias("level"))
    return found.withColumns({f"p{m}": F.call_function("shiftright", F.col(f"c{m}"), (F.lit(grid.levels) - F.col("level") + 1).cast("int")) for m in range(grid.d)})


#: Heavy cells that routing broadcasts; of more, points are joined with their leaves instead.
BROADCAST_CELLS = 100_000


def held(heavy: DataFrame, grid: Grid, most: int = BROADCAST_CELLS) -> list | None:
    """The heavy cells (level, k0.., n) as rows on the driver, or None where there are more than so many."""
    rows = heavy.select("level", *grid.key_names, "n").limit(most + 1).collect()
    return None if len(rows) > most else rows


def frame(spark, rows: list, grid: Grid) -> DataFrame:
    """level, k0.., n of cells at hand."""
    return spark.createDataFrame([tuple(r) for r in rows], f"level int, {', '.join(f'{k} long' for k in grid.key_names)}, n {'double' if any(isinstance(r['n'], float) for r in rows) else 'long'}")


def route(points: DataFrame, rows: list, grid: Grid) -> DataFrame:
    """points (x0..) with level and p0..: the part one level below the deepest heavy cell; points without one are left out.

    rows: the heavy cells, each with its parent, so that a point's depth is the number of heavy cells it lies in: one small broadcast
    look-up for each level that has any, and no shuffle of the points, however many share a leaf.
    """
    spark, by = points.sparkSession, {}
    for r in rows:
        by.setdefault(r["level"], []).append(tuple(r[k] for k in grid.key_names))
    out, depth = points.select("*", *grid.leaf([f"x{m}" for m in range(grid.d)])), F.lit(0)
    for level in sorted(by):
        cells = spark.createDataFrame([(*k, 1) for k in by[level]], ", ".join(f"_h{m} long" for m in range(grid.d)) + f", _in{level + 1} int")
        on = [F.expr(f"shiftright(c{m}, {grid.levels - level})") == F.col(f"_h{m}") for m in range(grid.d)]
        out = out.join(F.broadcast(cells), on, "left").drop(*(f"_h{m}" for m in range(grid.d)))
        depth = depth + F.coalesce(F.col(f"_in{level + 1}"), F.lit(0))
    out = out.withColumn("level", (depth - 1).cast("int")).drop(*(f"_in{level + 1}" for level in by)).where("level >= 0")
    parent = {f"p{m}": F.call_function("shiftright", F.col(f"c{m}"), (F.lit(grid.levels + 1) - F.col("level")).cast("int")) for m in range(grid.d)}
    return out.withColumns(parent).drop(*grid.names)


def routed_points(points: DataFrame, heavy: DataFrame, grid: Grid, rows: list | None = None) -> DataFrame:
    """points with level and p0.. as route gives, by broadcast where the heavy cells are few, else by a join over their leaves."""
    rows = held(heavy, grid) if rows is None else rows
    if rows is not None:
        return route(points, rows, grid)
    keyed = points.select("*", *grid.leaf([f"x{m}" for m in range(grid.d)]))
    leaves = keyed.select(*grid.names).distinct()
    return keyed.join(deepest(leaves, heavy, grid), grid.names).drop(*grid.names)


def parts_of_cells(heavy: DataFrame, grid: Grid) -> DataFrame:
    """level, p0.., size of all parts from the heavy cells alone: what a heavy cell holds less what its heavy children hold."""
    up = heavy.select((F.col("level") + 1).alias("level"), *(F.col(k).alias(f"p{m}") for m, k in enumerate(grid.key_names)), F.col("n").alias("size"))
    down = heavy.where("level >= 0").select("level", *(F.expr(f"shiftright({k}, 1)").alias(f"p{m}") for m, k in enumerate(grid.key_names)), (-F.col("n")).alias("size"))
    return up.unionByName(down).groupBy("level", *(f"p{m}" for m in range(grid.d))).agg(F.sum("size").alias("size")).where("size > 0")


def level_masses(parts: DataFrame) -> DataFrame:
    return parts.groupBy("level").agg(F.sum("size").alias("mass"), F.count("*").alias("n_parts"))


def ladder(cells: DataFrame, grid: Grid, r: float, d: int, exponents: int) -> DataFrame:
    """guess_log2, level, n_heavy, mass for all guesses 2^0..2^exponents in one pass.

    A cell is heavy for all guesses up to a limit of its own and crucial for those above it up to its parent's limit, so
    that counts and masses are running sums over a histogram of limits.
    """
    powers = F.array(*(F.lit(float(2**e)) for e in range(exponents + 1)))
    diameter = {i: (d**0.5 * 2.0 ** (grid.levels - i)) ** r for i in range(-1, grid.levels + 1)}
    limit = F.when(F.col("level") < grid.levels, 100.0 * F.col("n") * by_level("level", diameter)).otherwise(F.lit(0.0))
    top = F.size(F.filter(powers, lambda p: p <= F.col("limit"))) - 1  # -1: heavy for no guess
    own = cells.withColumn("limit", limit).withColumn("top", F.least(top, F.lit(exponents))).drop("limit")
    up = own.select((F.col("level") + 1).alias("level"), *(F.col(k).alias(f"p{k}") for k in grid.key_names), F.col("top").alias("up"))
    met = own.withColumns({f"p{k}": F.expr(f"shiftright({k}, 1)") for k in grid.key_names}).join(up, ["level", *(f"p{k}" for k in grid.key_names)])
    # Mass at a level: in from the parent's limit down, out from the own limit down. Heavy cells: from the own limit down.
    changes = met.select("level", F.col("up").alias("e"), F.col("n").alias("mass"), F.lit(0).alias("heavy")).unionByName(
        met.select("level", F.col("top").alias("e"), (-F.col("n")).alias("mass"), F.lit(0).alias("heavy"))
    ).unionByName(own.select("level", F.col("top").alias("e"), F.lit(0).cast("long").alias("mass"), F.lit(1).alias("heavy")))
    histogram = changes.where("e >= 0").groupBy("level", "e").agg(F.sum("mass").alias("mass"), F.sum("heavy").alias("heavy"))
    frame = cells.sparkSession.range(-1, grid.levels + 1).select(F.col("id").cast("int").alias("level"), F.explode(F.sequence(F.lit(0), F.lit(exponents))).alias("e"))
    filled = frame.join(histogram, ["level", "e"], "left")
    down = W.partitionBy("level").orderBy(F.col("e").desc())
    return filled.select(F.col("e").alias("guess_log2"), "level", F.coalesce(F.sum("heavy").over(down), F.lit(0)).cast("long").alias("n_heavy"), F.coalesce(F.sum("mass").over(down), F.lit(0)).cast("long").alias("mass"))
