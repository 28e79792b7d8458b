"""Queries of the summary's methods, costs, assignments and measures."""

from __future__ import annotations

import decimal
import math

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from balclust import workloads as WL
from balclust.functions import points as P
from balclust.operators import assign, baselines, cellstore, coreset, distributed, estimate, flow, halfspace, measures, partition, solvers
from balclust.operators import cost as C
from balclust.plans import oracle as O
from balclust.plans import params as PR
from balclust.register import query, table
from balclust.sources import store


def pts(s, sf, i, keep=()):
    return WL.load(s, sf, i.spec, keep)


def verdict(s, flags, schema):
    """One row of truths."""
    return s.createDataFrame([tuple(bool(f) for f in flags)], schema)


def _cells(s, sf, i):
    return partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)


# --- lattice, tags, grids, hashes


def _lattice_query(key, i):
    spec = i.spec
    xs = ", ".join(spec.coordinates)

    @query(f"discretize_{spec.name}", f"WITH {O.points(spec)} SELECT {xs}, count(*) AS n FROM pts GROUP BY {xs}")
    def run(s, sf):
        return P.discretize(table(s, sf, spec.table), spec).groupBy(*spec.coordinates).agg(F.count("*").alias("n"))


for _k, _i in WL.ALL.items():
    if _k not in ("w02", "w20"):
        _lattice_query(_k, _i)


@query("m02_tags", f"WITH {O.points(WL.LI2)} SELECT tag, count(*) AS n, sum(x0)::BIGINT AS s0, sum(x1)::BIGINT AS s1 FROM pts GROUP BY tag")
def tags(s, sf):
    return pts(s, sf, WL.W01).groupBy("tag").agg(F.count("*").alias("n"), F.sum("x0").alias("s0"), F.sum("x1").alias("s1"))


@query("m02_clamped_rows", "SELECT count(CASE WHEN l_quantity < 5 OR l_quantity > 45 THEN 1 END) AS clamped_x0 FROM lineitem")
def clamped(s, sf):
    return P.clamped(table(s, sf, "lineitem"), P.PointSpec("t", "lineitem", (P.Dimension("l_quantity", 5, 45),), 4))


@query("m03_cell_keys", O.chain(WL.W01, "points", "leaves") + "SELECT lvl::INTEGER AS level, sum(c0 >> (10 - lvl))::BIGINT AS s0, sum(c1 >> (10 - lvl))::BIGINT AS s1, count(DISTINCT (c0 >> (10 - lvl)) * 4096 + (c1 >> (10 - lvl))) AS n_cells FROM leaf, (SELECT CAST(unnest(range(-1, 11)) AS INTEGER) AS lvl) GROUP BY lvl")
def cell_keys(s, sf):
    cells = _cells(s, sf, WL.W01)
    return cells.groupBy("level").agg(F.sum(F.col("k0") * F.col("n")).alias("s0"), F.sum(F.col("k1") * F.col("n")).alias("s1"), F.count("*").alias("n_cells"))


@query("m04_common_cell", O.chain(WL.W01, "points", "leaves") + "SELECT max(CASE WHEN a = b THEN lvl END)::INTEGER AS level FROM (SELECT lvl, min((c0 >> (10 - lvl)) * 4096 + (c1 >> (10 - lvl))) AS a, max((c0 >> (10 - lvl)) * 4096 + (c1 >> (10 - lvl))) AS b FROM leaf, (SELECT CAST(unnest(range(-1, 11)) AS INTEGER) AS lvl) WHERE x0 <= 300 AND x1 <= 200 GROUP BY lvl)")
def common_cell(s, sf):
    """The deepest cell that holds a whole set."""
    near = pts(s, sf, WL.W01).where("x0 <= 300 AND x1 <= 200")
    cells = partition.cell_counts(partition.leaf_counts(near, WL.W01.grid), WL.W01.grid)
    return cells.groupBy("level").agg(F.count("*").alias("c")).where("c = 1").agg(F.max("level").alias("level"))


@query("m05_ancestors", O.chain(WL.W01, "points", "leaves", "cells") + "SELECT a.level, count(*) AS n FROM cells a JOIN cells b ON b.level = 6 AND a.level <= 6 AND a.k0 = b.k0 >> (6 - a.level) AND a.k1 = b.k1 >> (6 - a.level) GROUP BY a.level")
def ancestors(s, sf):
    cells = _cells(s, sf, WL.W01)
    below = cells.where("level = 6").select(F.explode(F.sequence(F.lit(-1), F.lit(6))).alias("level"), "k0", "k1")
    up = below.select("level", *(F.call_function("shiftright", F.col(k), 6 - F.col("level")).alias(k) for k in ("k0", "k1")))
    return up.join(cells, ["level", "k0", "k1"]).groupBy("level").agg(F.count("*").alias("n"))


def _cell_query(key, i):
    names = ", ".join(i.grid.key_names)

    @query(f"m06_cell_counts_{key}", O.chain(i, "points", "leaves", "cells") + f"SELECT level, {names}, n FROM cells")
    def run(s, sf):
        return _cells(s, sf, i)


for _k in ("w01", "w04", "w05", "w06", "w11", "w14", "w15", "w15c", "w16"):
    _cell_query(_k, WL.ALL[_k])


@query("leaf_counts", O.chain(WL.W01, "points", "leaves") + "SELECT c0, c1, count(*) AS n FROM leaf GROUP BY c0, c1")
def leaf_counts(s, sf):
    return partition.leaf_counts(pts(s, sf, WL.W01), WL.W01.grid)


@query("m07_thresholds", O.chain(WL.W01, "points", "leaves", "cells")[:-1] + ", t(level, threshold) AS (VALUES " + ", ".join(f"({i}::INTEGER, {WL.W01.params.cell_threshold(i)!r}::DOUBLE)" for i in range(-1, 11)) + ") SELECT level, threshold, count(*) AS n_cells, count(CASE WHEN n >= threshold THEN 1 END) AS n_reached FROM cells JOIN t USING (level) GROUP BY level, threshold")
def thresholds(s, sf):
    """Each level's threshold, and how many cells of lineitem's lattice there are and reach it."""
    met = _cells(s, sf, WL.W01).withColumn("threshold", partition.by_level("level", partition.thresholds(WL.W01.params)))
    return met.groupBy("level", "threshold").agg(F.count("*").alias("n_cells"), F.count_if(F.col("n") >= F.col("threshold")).alias("n_reached"))


def _marks_sql(i):
    """The parents' keys are columns of their own, so that the join is one of equal columns."""
    ks = [f"k{m}" for m in range(i.spec.d)]
    ps = ", ".join(f"p{m}" for m in range(i.spec.d))
    return O.chain(i, "points", "leaves", "cells", "heavy")[:-1] + f""", up AS (SELECT CAST(level + 1 AS INTEGER) AS level, {', '.join(f'{k} AS p{m}' for m, k in enumerate(ks))}, true AS open FROM heavy),
own AS (SELECT *, {', '.join(f'{k} >> 1 AS p{m}' for m, k in enumerate(ks))} FROM cells)
SELECT level, {', '.join(ks)}, n, CASE WHEN level < {i.spec.levels} AND n >= {O.limits(i.params)} THEN 'heavy' WHEN level = -1 OR open THEN 'crucial' ELSE 'inside' END AS kind FROM own LEFT JOIN up USING (level, {ps})"""


def _mark_query(key, i):
    @query(f"m08_marks_{key}", _marks_sql(i))
    def run(s, sf):
        return partition.mark_exact(_cells(s, sf, i), i.grid, i.params)

    @query(f"m09_parts_{key}", O.chain(i, *O.UP_TO_PARTS) + f"SELECT {O.part_key(i)}, size FROM parts")
    def run_parts(s, sf):
        return partition.part_sizes(partition.mark_exact(_cells(s, sf, i), i.grid, i.params), i.grid)


for _k in ("w01", "w02", "w04", "w06"):
    _mark_query(_k, WL.ALL[_k])


@query("m08_marks_by_level", _marks_sql(WL.W04))
def marks_by_level(s, sf):
    """The chain over levels that estimated sizes need, on exact ones."""
    return partition.mark_cells(_cells(s, sf, WL.W04), WL.W04.grid, WL.W04.params)


_THEORY, _LEAST5 = PR.derive(8, 2, 2, 10, 16.0, profile="theory"), (math.sqrt(2) * 2.0**5) ** 2


@query("m10_parameters", "WITH t AS (SELECT count(*) AS n, (1::BIGINT << (length(bin(count(*) * 16)) - 1))::DOUBLE AS guess FROM lineitem), p AS (SELECT 'calibrated' AS profile, 0.05::DOUBLE AS gamma, (1.0 / 1600)::DOUBLE AS xi, 8::BIGINT AS independence UNION ALL SELECT 'theory', "
       f"{_THEORY.gamma!r}::DOUBLE, {_THEORY.xi!r}::DOUBLE, (1000000::BIGINT * 2 * 512 * 2 * 10 * 8)::BIGINT) SELECT p.*, n, guess, 0.01::DOUBLE * guess / {O.number(_LEAST5)} AS threshold FROM p, t")
def parameters(s, sf):
    """Both profiles' parameters for lineitem: the guess from its number of rows, and the least size of a heavy cell of level 5."""
    n = table(s, sf, "lineitem").count()
    each = [PR.derive(8, 2, 2, 10, PR.guess_for(n, 16), profile=x) for x in ("calibrated", "theory")]
    rows = [(p.profile, p.gamma, p.xi, p.independence, n, p.guess, p.cell_threshold(5)) for p in each]
    return s.createDataFrame(rows, "profile string, gamma double, xi double, independence long, n long, guess double, threshold double")


def _hash_sql(i, h):
    return f"WITH {O.points(i.spec)}, {O.hashed(i, h, 'pts', 'hashed')} SELECT tag, {', '.join(i.spec.coordinates)}, h FROM hashed"


@query("m11_poly_hash", _hash_sql(WL.W01, WL.W01.core_hash))
def poly_hash(s, sf):
    i = WL.W01
    return pts(s, sf, i).withColumn("h", P.poly_hash(["tag", *i.spec.coordinates], i.core_hash))


@query("m11_sample_by_hash", f"WITH {O.points(WL.LI2)}, {O.hashed(WL.W01, WL.W01.cell_hash, 'pts', 'hashed')} SELECT count(*) AS n, sum(x0)::BIGINT AS s FROM hashed WHERE h < {P.threshold(0.125)}")
def sample_by_hash(s, sf):
    i = WL.W01
    return pts(s, sf, i).where(P.poly_hash(["tag", *i.spec.coordinates], i.cell_hash) < P.threshold(0.125)).agg(F.count("*").alias("n"), F.sum("x0").alias("s"))


@query("m12_independent_sample")
def independent_sample(s, sf):
    """The fully independent alternative: a seeded row hash, replayable on every attempt."""
    return pts(s, sf, WL.W01).where(F.pmod(F.xxhash64("tag", "x0", "x1", F.lit(5)), F.lit(8)) == 0)


_CAPS = {i: WL.W01.params.mass_cap(i) for i in range(11)}


@query("m13_failures", O.chain(WL.W01, *O.UP_TO_PARTS) + f"SELECT 'heavy_cells' AS reason, count(*)::DOUBLE AS value, {WL.W01.params.cell_cap!r}::DOUBLE AS cap, count(*) > {WL.W01.params.cell_cap!r} AS failed FROM heavy UNION ALL SELECT 'mass_' || level, sum(size)::DOUBLE, {O.case('level', _CAPS)}::DOUBLE, sum(size) > {O.case('level', _CAPS)} FROM parts GROUP BY level")
def failures(s, sf):
    i = WL.W01
    marked = partition.mark_exact(_cells(s, sf, i), i.grid, i.params)
    return coreset.failures(marked.where("kind = 'heavy'"), partition.part_sizes(marked, i.grid), i.params)


@query("m14_important_parts", O.chain(WL.W01, *O.UP_TO_PARTS, "important") + "SELECT level, p0, p1, size FROM important")
def important(s, sf):
    i = WL.W01
    return coreset.important_parts(partition.part_sizes(partition.mark_exact(_cells(s, sf, i), i.grid, i.params), i.grid), i.params)


def built(s, sf, i):
    return coreset.build(pts(s, sf, i), i.grid, i.params, i.core_hash)


def _core_query(name, i):
    key = O.part_key(i)

    @query(name, O.chain(i, *O.UP_TO_CORESET) + f"SELECT tag, {', '.join(i.spec.coordinates)}, {key}, w FROM core")
    def run(s, sf):
        return built(s, sf, i).coreset


for _n, _k in (("m15_coreset_lineitem", "w01"), ("w02_coreset_median", "w02"), ("w03_coreset_four_columns", "w03"), ("w04_coreset_orders", "w04"), ("w05_coreset_one_column", "w05"), ("w06_coreset_events", "w06"),
               ("w11_coreset_projected", "w11"), ("w13_coreset_suppliers", "w13"), ("w14_coreset_documents", "w14"), ("w15_coreset_pages", "w15"), ("w15_coreset_conversations", "w15c"), ("w16_coreset_customers", "w16"), ("w20_coreset_theory", "w20")):
    _core_query(_n, WL.ALL[_k])


def _ladder_sql(i, exponents):
    p, d, levels = i.params, i.spec.d, i.spec.levels
    diameter = {j: (d**0.5 * 2.0 ** (levels - j)) ** p.r for j in range(-1, levels + 1)}
    on = " AND ".join(f"u.k{m} = c.k{m} >> 1" for m in range(d))
    return O.chain(i, "points", "leaves", "cells") + f"""SELECT g.e::INTEGER AS guess_log2, l.level, count(CASE WHEN x.lim >= pow(2.0, g.e) AND x.level < {levels} THEN 1 END) AS n_heavy,
coalesce(sum(CASE WHEN x.level >= 0 AND x.up >= pow(2.0, g.e) AND x.lim < pow(2.0, g.e) THEN x.n END), 0)::BIGINT AS mass
FROM (SELECT unnest(range(0, {exponents + 1})) AS e) g CROSS JOIN (SELECT CAST(unnest(range(-1, {levels + 1})) AS INTEGER) AS level) l
JOIN (SELECT c.level, c.n, CASE WHEN c.level < {levels} THEN 100.0 * c.n * {O.case('c.level', diameter)} ELSE 0 END AS lim, 100.0 * u.n * {O.case('u.level', diameter)} AS up FROM cells c LEFT JOIN cells u ON u.level = c.level - 1 AND {on}) x ON x.level = l.level
GROUP BY g.e, l.level"""


@query("m16_guess_ladder", _ladder_sql(WL.W04, 40))
def guess_ladder(s, sf):
    i = WL.W04
    return partition.ladder(_cells(s, sf, i), i.grid, i.params.r, i.spec.d, 40)


_SURVIVE = {j: WL.W04.params._replace(guess=1.0).mass_cap(j) for j in range(11)}


@query("m16_smallest_guess", "WITH rungs AS (" + _ladder_sql(WL.W04, 40) + f") SELECT min(e)::INTEGER AS guess_log2 FROM (SELECT guess_log2 AS e, sum(n_heavy) AS h, bool_and(level < 0 OR mass <= coalesce({O.case('level', _SURVIVE)}, 0) * pow(2.0, guess_log2)) AS fits FROM rungs GROUP BY guess_log2) WHERE fits AND h <= {WL.W04.params.cell_cap!r}")
def smallest_guess(s, sf):
    i = WL.W04
    rungs = partition.ladder(_cells(s, sf, i), i.grid, i.params.r, i.spec.d, 40)
    return coreset.surviving(rungs, i.params).agg(F.min("guess_log2").alias("guess_log2"))


@query("m17_guess_by_estimate", "SELECT true AS below_estimate, true AS within_two")
def guess_by_estimate(s, sf):
    """The largest power of two up to half an upper bound of the best cost."""
    i = WL.W01
    _, bound = solvers.opt_estimate(pts(s, sf, i), 8, 2, 2, sample=2000)
    guess = PR.guess_for(bound // 2 or 1, 1)
    return verdict(s, (guess <= bound / 2, guess > bound / 4), "below_estimate boolean, within_two boolean")


# --- estimates


def _estimate_sql(i, which):
    h = i.cell_hash if which == 0 else i.part_hash
    cut = {j: P.threshold(i.params.size_rates(j)[which]) for j in range(-1, i.spec.levels + 1)}
    names = ", ".join(f"k{m}" for m in range(i.spec.d))
    keys = ", ".join(f"c{m} >> ({i.spec.levels} - lvl) AS k{m}" for m in range(i.spec.d))
    return O.chain(i, "points", "leaves")[:-1] + f""", {O.hashed(i, h, 'leaf', 'hashed')}
SELECT level, {names}, count(*) AS n, count(CASE WHEN h < {O.case('level', cut)} THEN 1 END) AS hits, count(CASE WHEN h < {O.case('level', cut)} THEN 1 END) * {O.case('level', {j: P.RANGE / t for j, t in cut.items()})} AS estimate
FROM (SELECT lvl AS level, {keys}, h FROM hashed, (SELECT CAST(unnest(range(-1, {i.spec.levels + 1})) AS INTEGER) AS lvl)) GROUP BY level, {names}"""


@query("m18_estimates", _estimate_sql(WL.W04, 0))
def estimates(s, sf):
    i = WL.W04
    return estimate.estimate_cells(pts(s, sf, i), i.grid, i.params, i.cell_hash)


_OFF = {j: 0.1 * WL.W04.params.cell_threshold(j) for j in range(-1, 11)}


@query("m19_good_cells", f"SELECT level, count(*) AS n_cells, count(CASE WHEN abs(estimate - n) <= {O.case('level', _OFF)} OR abs(estimate - n) <= 0.01 * n THEN 1 END) AS n_good FROM ({_estimate_sql(WL.W04, 0)}) GROUP BY level")
def good_cells(s, sf):
    i = WL.W04
    return estimate.good_cells(estimates(s, sf), i.params).groupBy("level").agg(F.count("*").alias("n_cells"), F.count_if("good").alias("n_good"))


_OFF_PARTS = {j: 0.1 * WL.W04.params.gamma * WL.W04.params.cell_threshold(j) for j in range(11)}
_PART_CUT = {j: P.threshold(WL.W04.params.size_rates(j)[1]) for j in range(11)}


@query("m19_good_parts", O.chain(WL.W04, *O.UP_TO_PARTS)[:-1] + f", {O.hashed(WL.W04, WL.W04.part_hash, 'routed', 'hashed')}, e AS (SELECT level, p0, p1, count(*) AS size, count(CASE WHEN h < {O.case('level', _PART_CUT)} THEN 1 END) * {O.case('level', {j: P.RANGE / t for j, t in _PART_CUT.items()})} AS estimate FROM hashed GROUP BY level, p0, p1) SELECT level, count(*) AS n_parts, count(CASE WHEN abs(estimate - size) <= {O.case('level', _OFF_PARTS)} OR abs(estimate - size) <= 0.1 * size THEN 1 END) AS n_good FROM e GROUP BY level")
def good_parts(s, sf):
    i = WL.W04
    p = pts(s, sf, i)
    leaves = partition.leaf_counts(p, i.grid)
    routed = partition.leaf_levels(leaves, partition.cell_counts(leaves, i.grid), i.grid, i.params)
    parts = estimate.good_parts(estimate.estimate_parts(p, routed, i.grid, i.params, i.part_hash), i.params)
    return parts.groupBy("level").agg(F.count("*").alias("n_parts"), F.count_if("good").alias("n_good"))


# --- costs and assignments


def _near_sql(i, r):
    d = [O.dist(i.spec.coordinates, z, r) for z in i.centres]
    least = f"least({', '.join(d)})" if len(d) > 1 else d[0]
    place = "CASE " + " ".join(f"WHEN {c} = {least} THEN {k}" for k, c in enumerate(d)) + " END"
    return least, place


def _cost_query(key, i, r):
    least, place = _near_sql(i, r)

    @query(f"m22_cost_{key}_r{r:g}".replace(".", "_"), f"WITH {O.points(i.spec)} SELECT coalesce(sum({least}), 0)::BIGINT AS cost FROM pts")
    def run(s, sf):
        # The sum has 38 digits; it is given as BIGINT where it fits, and as it is beyond 2^63, where SQL's own cast ends with an error.
        cost = C.plain_cost(pts(s, sf, i), i.centres, r, wide=True)
        total = int(cost.first()["cost"])
        return s.createDataFrame([(total,)], "cost long") if total < 1 << 63 else s.createDataFrame([(decimal.Decimal(total),)], "cost decimal(38,0)")

    @query(f"m23_sizes_{key}_r{r:g}".replace(".", "_"), f"WITH {O.points(i.spec)} SELECT z.j::INTEGER AS j, count(p.j) AS size FROM (SELECT unnest(range(0, {len(i.centres)})) AS j) z LEFT JOIN (SELECT {place} AS j FROM pts) p USING (j) GROUP BY z.j")
    def sizes(s, sf):
        return C.size_vector(C.nearest(pts(s, sf, i), i.centres, r), len(i.centres))


for _k, _r in (("w01", 2), ("w01", 1), ("w01", 3), ("w03", 2), ("w06", 1.5), ("w11", 2), ("w13", 2)):
    _cost_query(_k, WL.ALL[_k], _r)


def _sweep_sql(i, r):
    a, b = i.centres[:2]
    da, db = O.dist(i.spec.coordinates, a, r), O.dist(i.spec.coordinates, b, r)
    return f"""WITH {O.points(i.spec)}, d AS (SELECT ({da}) - ({db}) AS diff, {db} AS to_b, row_number() OVER (ORDER BY ({da}) - ({db}), {', '.join(i.spec.coordinates)}, tag) AS m FROM pts),
run AS (SELECT m, (sum(diff) OVER (ORDER BY m) + sum(to_b) OVER ())::BIGINT AS cost FROM d UNION ALL SELECT 0, sum(to_b)::BIGINT FROM d),
caps AS (SELECT ((n * f + 99) // 100)::BIGINT AS t FROM (SELECT count(*) AS n FROM pts), (SELECT unnest([40, 50, 55, 75, 100]) AS f))
SELECT t, min(cost) AS cost FROM caps LEFT JOIN run ON m >= (SELECT count(*) FROM pts) - t AND m <= t GROUP BY t"""


def _capacities(s, p):
    n = p.count()
    return s.createDataFrame([((n * f + 99) // 100,) for f in (40, 50, 55, 75, 100)], "t long")


def _two_query(key, i, r):
    @query(f"m20_two_centres_{key}_r{r}", _sweep_sql(i, r))
    def run(s, sf):
        p = pts(s, sf, i)
        return C.two_centre_cost(p, *i.centres[:2], _capacities(s, p), r)


for _k, _r in (("w04", 2), ("w04", 1), ("w05", 2), ("w13", 2)):
    _two_query(_k, WL.ALL[_k], _r)


@query("v04_bottleneck", f"WITH {O.points(WL.SUP)} SELECT count(CASE WHEN {_near_sql(WL.W13, 2)[0]} > 400 THEN 1 END) AS n_far FROM pts")
def bottleneck(s, sf):
    return C.bottleneck(pts(s, sf, WL.W13), WL.W13.centres, 400)


@query("m24_half_space_order", f"WITH {O.points(WL.ORD)}, d AS (SELECT tag, ({O.dist(WL.ORD.coordinates, WL.W04.centres[0], 2)}) - ({O.dist(WL.ORD.coordinates, WL.W04.centres[1], 2)}) AS diff, x0, x1 FROM pts) SELECT tag, diff FROM d ORDER BY diff, x0, x1, tag LIMIT 50")
def half_space_order(s, sf):
    i = WL.W04
    return pts(s, sf, i).select("tag", *C.order_key(i.spec.coordinates, *i.centres, 2)[:1], "x0", "x1").orderBy("diff", "x0", "x1", "tag").limit(50).select("tag", "diff")


@query("m24_half_space_ranks", f"WITH {O.points(WL.ORD)}, d AS (SELECT tag, ({O.dist(WL.ORD.coordinates, WL.W04.centres[0], 2)}) - ({O.dist(WL.ORD.coordinates, WL.W04.centres[1], 2)}) AS diff, x0, x1 FROM pts) SELECT tag, diff, row_number() OVER (ORDER BY diff, x0, x1, tag) AS place FROM d")
def half_space_ranks(s, sf):
    """The place of every row in the order: within runs of differences, and the runs' sizes before."""
    i = WL.W04
    p = pts(s, sf, i).select("tag", *C.order_key(i.spec.coordinates, *i.centres, 2)[:1], "x0", "x1").withColumn("run", F.floor(F.col("diff") / 4096))
    runs = p.groupBy("run").agg(F.count("*").alias("n"))  # at most 1,024 by the lattice's bounds
    before = runs.select("run", F.coalesce(F.sum("n").over(W.orderBy("run").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = F.row_number().over(W.partitionBy("run").orderBy("diff", "x0", "x1", "tag"))
    return p.withColumn("inside", inside).join(F.broadcast(before), "run").select("tag", "diff", (F.col("inside") + F.col("before")).alias("place"))


def _assigned(s, sf, i):
    """A deterministic assignment of the summary: to the nearest centre."""
    return C.nearest(built(s, sf, i).coreset, i.centres, i.params.r)


def _ends_sql(i):
    xs = i.spec.coordinates
    least, place = _near_sql(i, 2)
    z = i.centres
    key = {(a, b): f"struct_pack(diff := ({O.dist(xs, z[a], 2)}) - ({O.dist(xs, z[b], 2)}), {', '.join(f'{x} := {x}' for x in xs)}, tag := tag)" for a, b in halfspace.pairs(len(z))}
    return key, place


_KEY4, _PLACE4 = _ends_sql(WL.W04)


@query("m25_half_spaces", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT *, {_PLACE4} AS j FROM core) SELECT level, max(CASE WHEN j = 0 THEN {_KEY4[0, 1]} END).diff AS diff, max(CASE WHEN j = 0 THEN {_KEY4[0, 1]} END).tag AS tag FROM a GROUP BY level")
def half_spaces(s, sf):
    return halfspace.derive(_assigned(s, sf, WL.W04), WL.W04.centres, 2).select("level", "h_0_1.diff", "h_0_1.tag")


def _separable_sql(i):
    key, place = _ends_sql(i)
    one = [f"SELECT level, {a} AS i, {b} AS j, coalesce(max(CASE WHEN c = {a} THEN {key[a, b]} END) < min(CASE WHEN c = {b} THEN {key[a, b]} END), true) AS ok FROM a GROUP BY level" for a, b in halfspace.pairs(len(i.centres))]
    return O.chain(i, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT *, {place} AS c FROM core) " + " UNION ALL ".join(one)


@query("m26_separable", _separable_sql(WL.W14))
def separable(s, sf):
    return halfspace.separable(_assigned(s, sf, WL.W14), WL.W14.centres, 2)


_DIFF13 = f"({O.dist(WL.SUP.coordinates, WL.W13.centres[0], 2)}) - ({O.dist(WL.SUP.coordinates, WL.W13.centres[1], 2)})"


@query("m27_tie_exchange", f"WITH {O.points(WL.SUP)}, a AS (SELECT tag, row_number() OVER (ORDER BY {_DIFF13}, x0, x1, tag) AS place, sum(1 - tag % 2) OVER () AS firsts FROM pts) SELECT tag, (CASE WHEN place <= firsts THEN 0 ELSE 1 END)::INTEGER AS j FROM a")
def tie_exchange(s, sf):
    """Suppliers dealt to two centres by their keys exchange them until the earlier ones of the order, ties by the point, are with the first; sizes stay."""
    x, _ = C.arrays(pts(s, sf, WL.W13), 2)
    out = flow.canonical(x[:, :2], x[:, 2], x[:, 2] % 2, np.array(WL.W13.centres), 2)
    return s.createDataFrame([(int(t), int(j)) for t, j in zip(x[:, 2], out, strict=True)], "tag long, j int")


@query("tied_swap_pairs", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT level, tag, x0, x1, ({O.dist(WL.ORD.coordinates, WL.W04.centres[0], 2)}) - ({O.dist(WL.ORD.coordinates, WL.W04.centres[1], 2)}) AS diff, tag % 2 AS j FROM core) SELECT p.level, count(*) AS n FROM a p JOIN a q ON p.level = q.level AND p.diff = q.diff AND p.j = 0 AND q.j = 1 AND struct_pack(x0 := q.x0, x1 := q.x1, tag := q.tag) < struct_pack(x0 := p.x0, x1 := p.x1, tag := p.tag) GROUP BY p.level")
def tied_swap_pairs(s, sf):
    """Pairs that the tie exchange would swap, of an assignment that ignores the order: equal differences, later point at the earlier centre."""
    diff = P.sqdist(["x0", "x1"], WL.W04.centres[0]) - P.sqdist(["x0", "x1"], WL.W04.centres[1])
    a = built(s, sf, WL.W04).coreset.select("level", diff.alias("diff"), "x0", "x1", "tag", (F.col("tag") % 2).alias("j"))
    before = W.partitionBy("level", "diff").orderBy("x0", "x1", "tag").rowsBetween(W.unboundedPreceding, -1)
    return a.withColumn("earlier", F.coalesce(F.sum("j").over(before), F.lit(0))).where("j = 0 AND earlier > 0").groupBy("level").agg(F.sum("earlier").alias("n"))


@query("theta_separator_violations", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT level, {_PLACE4} AS j, ({O.dist(WL.ORD.coordinates, WL.W04.centres[0], 2)}) - ({O.dist(WL.ORD.coordinates, WL.W04.centres[1], 2)}) AS diff FROM core), e AS (SELECT level, max(CASE WHEN j = 0 THEN diff END) AS last FROM a GROUP BY level) SELECT level, count(*) AS n FROM a JOIN e USING (level) WHERE j = 1 AND diff < last GROUP BY level")
def separator_violations(s, sf):
    """Points at the later centre before the end of the earlier one's half-space; none for an optimal assignment."""
    diff = P.sqdist(["x0", "x1"], WL.W04.centres[0]) - P.sqdist(["x0", "x1"], WL.W04.centres[1])
    a = _assigned(s, sf, WL.W04).select("level", "j", diff.alias("diff"))
    ends = a.groupBy("level").agg(F.max(F.when(F.col("j") == 0, F.col("diff"))).alias("last"))
    return a.join(F.broadcast(ends), "level").where("j = 1 AND diff < last").groupBy("level").agg(F.count("*").alias("n"))


@query("m28_regions", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT *, {_PLACE4} AS j FROM core), e AS (SELECT level, max(CASE WHEN j = 0 THEN {_KEY4[0, 1]} END) AS last FROM a GROUP BY level), r AS (SELECT level, CASE WHEN coalesce({_KEY4[0, 1]} <= last, false) THEN 1 ELSE 2 END AS region FROM routed JOIN e USING (level)) SELECT level, region, count(*) AS n FROM r GROUP BY level, region")
def regions(s, sf):
    i = WL.W04
    p = pts(s, sf, i)
    leaves = partition.leaf_counts(p, i.grid)
    routed = partition.leaf_levels(leaves, partition.cell_counts(leaves, i.grid), i.grid, i.params)
    ends = halfspace.derive(_assigned(s, sf, i), i.centres, 2)
    keyed = p.select("*", *i.grid.leaf(i.spec.coordinates)).join(routed, i.grid.names)
    return halfspace.regions(keyed.join(F.broadcast(ends.select("level")), "level"), ends, i.centres, 2).groupBy("level", "region").agg(F.count("*").alias("n"))


@query("m29_region_tallies", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT *, {_PLACE4} AS j FROM core), e AS (SELECT level, max(CASE WHEN j = 0 THEN {_KEY4[0, 1]} END) AS last FROM a GROUP BY level), r AS (SELECT a.*, CASE WHEN coalesce({_KEY4[0, 1]} <= last, false) THEN 1 ELSE 2 END AS region FROM a JOIN e USING (level)) SELECT level, p0, p1, count(CASE WHEN region = 0 THEN 1 END) AS n0, count(CASE WHEN region = 1 THEN 1 END) AS n1, count(CASE WHEN region = 2 THEN 1 END) AS n2 FROM r GROUP BY level, p0, p1")
def region_tallies(s, sf):
    i = WL.W04
    a = _assigned(s, sf, i)
    placed = halfspace.regions(a, halfspace.derive(a, i.centres, 2), i.centres, 2).withColumn("w", F.lit(1.0))
    t = halfspace.tallies(placed, 2, ["level", "p0", "p1"])
    return t.select("level", "p0", "p1", *(F.col(f"b{k}").cast("long").alias(f"n{k}") for k in range(3)))


@query("m30_transfer", "WITH c AS (SELECT c_custkey AS pid, c_nationkey AS part, ascii(c_mktsegment) % 4 AS region FROM customer), t AS (SELECT part, count(*) AS n, " + ", ".join(f"count(CASE WHEN region = {k} THEN 1 END) AS b{k}" for k in range(4)) + " FROM c GROUP BY part) "
       "SELECT pid, (CASE WHEN region > 0 AND CASE region WHEN 1 THEN b1 WHEN 2 THEN b2 ELSE b3 END >= n * 0.4e0 THEN region ELSE CASE greatest(b1, b2, b3) WHEN b1 THEN 1 WHEN b2 THEN 2 ELSE 3 END END - 1)::INTEGER AS j FROM c JOIN t USING (part)")
def transfer(s, sf):
    """Customers in parts by nation and regions by market segment: regions with little of their part's mass, and undecided points, go to the fullest region's centre."""
    df = table(s, sf, "customer").select(F.col("c_custkey").alias("pid"), F.col("c_nationkey").alias("part"), (F.ascii("c_mktsegment") % 4).alias("region"))
    tally = halfspace.tallies(df.withColumn("w", F.lit(1.0)), 3, ["part"])
    mass = F.col("b0") + F.col("b1") + F.col("b2") + F.col("b3")
    return halfspace.transfer(df, F.broadcast(tally), 3, ["part"], mass * 0.4).select("pid", "j")


@query("m31_flow_certificate", "SELECT true AS tight, true AS feasible")
def flow_certificate(s, sf):
    i = WL.W06
    x, w = C.arrays(built(s, sf, i).coreset, 2, "w")
    cost, cap = flow.costs(x[:, :2], np.array(i.centres), 2), np.full(4, 0.3 * w.sum())
    share, price = flow.transport(cost, w, cap)
    v, bound = flow.value(cost, share), flow.dual_value(cost, w, cap, price)
    return verdict(s, (bool(abs(v - bound) <= 1e-7 * v), bool((share.sum(axis=0) <= cap * (1 + 1e-9)).all())), "tight boolean, feasible boolean")


@query("m32_split_removal", "SELECT true AS few_splits, true AS cost_kept, true AS sizes_kept")
def split_removal(s, sf):
    i = WL.W06
    x, w = C.arrays(built(s, sf, i).coreset, 2, "w")
    cost, cap = flow.costs(x[:, :2], np.array(i.centres), 2), 0.3 * w.sum()
    share, _ = flow.transport(cost, w, np.full(4, cap))
    whole, splits = flow.remove_splits(cost, share)
    after = float((w * cost[np.arange(len(x)), whole]).sum())
    return verdict(s, (splits <= 3, after <= flow.value(cost, share) * (1 + 1e-9), float(np.bincount(whole, w, 4).max()) <= cap + 3 * w.max()), "few_splits boolean, cost_kept boolean, sizes_kept boolean")


def _extended(s, sf, i, factor, transfer=True):
    b = built(s, sf, i)
    p = pts(s, sf, i)
    n, weight = p.count(), b.coreset.agg(F.sum("w")).first()[0]
    cap = factor * max(n, weight) / len(i.centres)
    assigned, report = assign.assign_summary(b.coreset, i.centres, cap, i.params.r, i.spec.d)
    return assign.extend(p, b, assigned, i.centres, transfer), report, cap, n


@query("m33_m34_extension", "SELECT true AS all_assigned, true AS near_capacity, true AS near_cost")
def extension(s, sf):
    """Every row of the input gets a centre from the summary's half-spaces; loads and cost stay near those of the summary."""
    full, report, cap, n = _extended(s, sf, WL.W04, 1.2)
    row = full.agg(F.count("j").alias("n"), F.sum("cost").alias("cost")).first()
    largest = C.size_vector(full, 2).agg(F.max("size")).first()[0]
    return verdict(s, (row["n"] == n, largest <= 1.3 * cap, row["cost"] <= 1.3 * report["cost"]), "all_assigned boolean, near_capacity boolean, near_cost boolean")


@query("b12_no_transfer", "SELECT true AS all_assigned")
def no_transfer(s, sf):
    full, _, _, n = _extended(s, sf, WL.W04, 1.2, transfer=False)
    return full.agg((F.count("j") == n).alias("all_assigned"))


@query("m35_stored_model", O.chain(WL.W04, *O.UP_TO_CORESET) + "SELECT level, count(*) AS n, sum(x0)::BIGINT AS s0, sum(tag)::BIGINT AS st FROM core GROUP BY level")
def stored_model(s, sf):
    path = store.fresh(s, "model")
    store.save(built(s, sf, WL.W04), path)
    return store.load(s, path).coreset.groupBy("level").agg(F.count("*").alias("n"), F.sum("x0").alias("s0"), F.sum("tag").alias("st"))


@query("m36_cell_store", O.chain(WL.W07, "points", "leaves", "cells") + "SELECT k0, k1, n FROM cells WHERE level = 4")
def cell_store(s, sf):
    """The sketch of one level's cells, decoded."""
    i = WL.W07
    keyed = pts(s, sf, i).select(*i.grid.leaf(i.spec.coordinates))
    updates = keyed.select(cellstore.pack(i.grid.keys(4), 11).alias("key"), F.lit(1).cast("long").alias("sign"))
    shape = cellstore.Shape(1200)
    return cellstore.decoded(s, cellstore.sketch(updates, shape).collect(), shape, 2, 11)


@query("m36_overfull_store_fails", "SELECT true AS failed")
def overfull(s, sf):
    i = WL.W07
    keyed = pts(s, sf, i).select(*i.grid.leaf(i.spec.coordinates))
    updates = keyed.select(cellstore.pack(i.grid.keys(9), 11).alias("key"), F.lit(1).cast("long").alias("sign"))
    shape = cellstore.Shape(16)
    return verdict(s, (cellstore.decode(cellstore.sketch(updates, shape).collect(), shape) is None,), "failed boolean")


def _machines(s, sf, machines=8):
    return pts(s, sf, WL.W01, ("l_orderkey",)).withColumn("machine", F.pmod("l_orderkey", F.lit(machines)).cast("int"))


_MACHINES = f"WITH {O.points(WL.LI2, ('l_orderkey',))}, {O.leaves(WL.W01)}, loc AS (SELECT (l_orderkey % 8)::INTEGER AS machine, c0 >> 5 AS k0, c1 >> 5 AS k1, count(*) AS n FROM leaf GROUP BY 1, 2, 3)"


@query("m39_local_cells", _MACHINES + " SELECT machine, k0, k1, n FROM loc")
def local_cells(s, sf):
    return distributed.local_cells(_machines(s, sf), WL.W01.grid, 5)


@query("m39_messages", _MACHINES + " SELECT machine, count(*) AS cells, coalesce(sum(CASE WHEN n <= 3 THEN n END), 0)::BIGINT AS small_points, count(*) > 5000 AS failed, (CASE WHEN count(*) > 5000 THEN 1 ELSE count(*) * (22 + length(bin(sum(n)::BIGINT))) + coalesce(sum(CASE WHEN n <= 3 THEN n END), 0) * 22 END)::BIGINT AS bits FROM loc GROUP BY machine")
def messages(s, sf):
    return distributed.messages(distributed.local_cells(_machines(s, sf), WL.W01.grid, 5), WL.W01.grid, 5000, 3)


@query("m39_small_cells", _MACHINES + ", pl AS (SELECT (l_orderkey % 8)::INTEGER AS machine, tag, x0, x1, c0 >> 5 AS k0, c1 >> 5 AS k1 FROM leaf) SELECT machine, tag, x0, x1 FROM pl SEMI JOIN (SELECT k0, k1 FROM loc GROUP BY k0, k1 HAVING sum(n) <= 3) USING (k0, k1)")
def small_cells(s, sf):
    m = _machines(s, sf)
    return distributed.small_cell_points(m, distributed.local_cells(m, WL.W01.grid, 5), WL.W01.grid, 5, 3)


@query("m40_distributed_cells", O.chain(WL.W01, "points", "leaves", "cells") + "SELECT level, k0, k1, n FROM cells")
def distributed_cells(s, sf):
    return distributed.cells_of_machines(_machines(s, sf), WL.W01.grid)


@query("v12_tree_merge", _MACHINES + " SELECT k0, k1, sum(n)::BIGINT AS n FROM loc GROUP BY k0, k1")
def tree_merge(s, sf):
    return distributed.tree_merge(distributed.local_cells(_machines(s, sf), WL.W01.grid, 5), WL.W01.grid)


def _bits_query(name, i, key, by, machines):
    """by: the number that deals the rows to machines, alike in both engines."""
    sizes = f"SELECT n.n AS machines, ({by}) % n.n AS machine, c0 >> 5 AS k0, c1 >> 5 AS k1, count(*) AS c FROM leaf, (SELECT unnest({list(machines)})::INTEGER AS n) n GROUP BY ALL"

    @query(name, f"WITH {O.points(i.spec, (key,) if key != i.spec.key else ())}, {O.leaves(i)}, loc AS ({sizes}), per AS (SELECT machines, machine, count(*) * (22 + length(bin(sum(c)::BIGINT))) + coalesce(sum(CASE WHEN c <= 3 THEN c END), 0) * 22 AS bits FROM loc GROUP BY machines, machine) SELECT machines, sum(bits)::BIGINT AS bits FROM per GROUP BY machines")
    def run(s, sf):
        out = None
        for n in machines:
            m = WL.load(s, sf, i.spec, (key,) if key != i.spec.key else ()).withColumn("machine", F.pmod(F.expr(by), F.lit(n)).cast("int"))
            one = distributed.messages(distributed.local_cells(m, i.grid, 5), i.grid, 10**6, 3).agg(F.lit(n).alias("machines"), F.sum("bits").alias("bits"))
            out = one if out is None else out.unionByName(one)
        return out


_bits_query("w09_bits_by_machines", WL.W01, "l_orderkey", "l_orderkey", (1, 2, 4, 8, 16))
_bits_query("w10_bits_skewed_machines", WL.W04, "o_orderpriority", "ascii(o_orderpriority)", (1, 5))


@query("m41_solve_and_lift", "SELECT true AS finite, true AS beats_random, true AS near_capacity")
def solve_and_lift(s, sf):
    """Centres from the summary alone, applied to the input."""
    i = WL.W06
    b, p = built(s, sf, i), pts(s, sf, i)
    n, weight = p.count(), b.coreset.agg(F.sum("w")).first()[0]
    z, value = solvers.solve(b.coreset, 4, max(n, weight) / 4, 2, 2)
    full = assign.extend(p, b, assign.assign_summary(b.coreset, z.tolist(), 1.2 * max(n, weight) / 4, 2, 2)[0], z.tolist())
    mine = full.agg(F.sum("cost")).first()[0]
    other = C.plain_cost(p, i.centres, 2).first()[0]
    largest = C.size_vector(full, 4).agg(F.max("size")).first()[0]
    return verdict(s, (math.isfinite(value), mine <= other, largest <= 1.35 * n / 4), "finite boolean, beats_random boolean, near_capacity boolean")


@query("m43_centre_cells", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT level, count(*) AS n FROM cells WHERE " + " OR ".join("(" + " + ".join(f"pow(greatest(0, greatest((k{m} << greatest(0, 10 - level)) - {z[m] - WL.W04.grid.shift[m] + 1024}, {z[m] - WL.W04.grid.shift[m] + 1024} - (((k{m} + 1) << greatest(0, 10 - level)) - 1))), 2)" for m in range(2)) + ") * 4 <= pow(2.0, 2 * (10 - level))" for z in WL.W04.centres) + " GROUP BY level")
def centre_cells(s, sf):
    """Cells within their side over d of a centre."""
    i = WL.W04
    cells = _cells(s, sf, i)
    width = F.call_function("shiftleft", F.lit(1).cast("long"), F.lit(10) - F.col("level"))
    hit = F.lit(False)
    for z in i.centres:
        off = F.lit(0).cast("long")
        for m in range(2):
            at = z[m] - i.grid.shift[m] + 1024
            gap = F.greatest(F.lit(0), F.col(f"k{m}") * width - at, at - ((F.col(f"k{m}") + 1) * width - 1))
            off = off + gap * gap
        hit = hit | (off * 4 <= width * width)
    return cells.where(hit).groupBy("level").agg(F.count("*").alias("n"))


@query("m44_small_parts", O.chain(WL.W01, *O.UP_TO_PARTS) + f"SELECT level, count(*) AS n_parts, sum(size)::BIGINT AS mass FROM parts WHERE size <= {O.case('level', {j: 2 * WL.W01.params.gamma * WL.W01.params.cell_threshold(j) for j in range(11)})} GROUP BY level")
def small_parts(s, sf):
    i = WL.W01
    parts = partition.part_sizes(partition.mark_exact(_cells(s, sf, i), i.grid, i.params), i.grid)
    small = parts.where(F.col("size") <= partition.by_level("level", {j: 2 * i.params.gamma * i.params.cell_threshold(j) for j in range(11)}))
    return small.groupBy("level").agg(F.count("*").alias("n_parts"), F.sum("size").alias("mass"))


@query("m45_set_distance", f"WITH {O.points(WL.SUP)} SELECT min({_near_sql(WL.W13, 2)[0]})::BIGINT AS sqdist FROM pts")
def set_distance(s, sf):
    return C.set_distance(pts(s, sf, WL.W13), WL.W13.centres)


@query("m46_movement_bound", O.chain(WL.W04, *O.UP_TO_PARTS) + "SELECT sum(n * (a * a + b * b))::BIGINT AS moved FROM (SELECT count(*) AS n, max(x0) - min(x0) AS a, max(x1) - min(x1) AS b FROM routed GROUP BY level, p0, p1)")
def movement_bound(s, sf):
    return baselines.movement_bound(pts(s, sf, WL.W04), WL.W04.grid, WL.W04.params)


# --- baselines


@query("b02_plain_coreset", O.chain(WL.W04, *O.UP_TO_PARTS)[:-1] + f", {O.hashed(WL.W04, WL.W04.core_hash, 'routed', 'hashed')} SELECT tag, x0, x1, level, p0, p1, {float(P.RANGE)!r}::DOUBLE / floor(least({float(P.RANGE)!r}::DOUBLE, {float(P.RANGE)!r}::DOUBLE * 40 / size))::BIGINT AS w FROM hashed JOIN parts USING (level, p0, p1) WHERE h < floor(least({float(P.RANGE)!r}::DOUBLE, {float(P.RANGE)!r}::DOUBLE * 40 / size))::BIGINT")
def plain_coreset(s, sf):
    i = WL.W04
    return baselines.plain_coreset(pts(s, sf, i), i.grid, i.params, i.core_hash, 40)


@query("b03_uniform_sample", f"WITH {O.points(WL.ORD)}, {O.hashed(WL.W04, WL.W04.core_hash, 'pts', 'hashed')} SELECT tag, x0, x1, {P.RANGE / P.threshold(0.02)!r}::DOUBLE AS w FROM hashed WHERE h < {P.threshold(0.02)}")
def uniform_sample(s, sf):
    return baselines.uniform_sample(pts(s, sf, WL.W04), 0.02, WL.W04.core_hash, 2)


@query("b04_snapped_cells", O.chain(WL.W04, *O.UP_TO_PARTS) + "SELECT z.x0, z.x1, z.tag, level, p0, p1, w FROM (SELECT min(struct_pack(x0 := x0, x1 := x1, tag := tag)) AS z, level, p0, p1, count(*) AS w FROM routed GROUP BY level, p0, p1)")
def snapped(s, sf):
    return baselines.snap_coreset(pts(s, sf, WL.W04), WL.W04.grid, WL.W04.params)


_NEAR4, _PLACE4B = _near_sql(WL.W04, 2)
_RINGS = f"WITH {O.points(WL.ORD)}, near AS (SELECT *, {_PLACE4B} AS j, {_NEAR4} AS cost FROM pts), ring AS (SELECT *, (CASE WHEN cost = 0 THEN -1 ELSE length(bin(cost)) - 1 END)::INTEGER AS ring FROM near)"


@query("b06_ring_sample", _RINGS + f", sizes AS (SELECT j, ring, count(*) AS size FROM ring GROUP BY j, ring), {O.hashed(WL.W04, WL.W04.core_hash, 'ring', 'hashed')} SELECT tag, x0, x1, j::INTEGER AS j, ring, {float(P.RANGE)!r}::DOUBLE / floor(least({float(P.RANGE)!r}::DOUBLE, {float(P.RANGE)!r}::DOUBLE * 60 / size))::BIGINT AS w FROM hashed JOIN sizes USING (j, ring) WHERE h < floor(least({float(P.RANGE)!r}::DOUBLE, {float(P.RANGE)!r}::DOUBLE * 60 / size))::BIGINT")
def ring_sample(s, sf):
    return baselines.ring_coreset(pts(s, sf, WL.W04), WL.W04.centres, WL.W04.core_hash, 60)


@query("b05_ring_cells", f"WITH {O.points(WL.ORD)}, near AS (SELECT *, {_PLACE4B} AS j, {_NEAR4} AS cost FROM pts), ring AS (SELECT *, (CASE WHEN cost = 0 THEN 0 ELSE floor((length(bin(cost)) - 1) / 2) END)::INTEGER AS ring FROM near) SELECT z.x0, z.x1, z.tag, j::INTEGER AS j, ring, w FROM (SELECT j, ring, x0 >> greatest(0, ring - 3), x1 >> greatest(0, ring - 3), min(struct_pack(x0 := x0, x1 := x1, tag := tag)) AS z, count(*) AS w FROM ring GROUP BY ALL)")
def ring_cells(s, sf):
    return baselines.ring_cells(pts(s, sf, WL.W04), WL.W04.centres)


@query("b01_three_pass", "SELECT true AS finite, true AS all_snapped")
def three_pass(s, sf):
    p = pts(s, sf, WL.W05)
    n = p.count()
    _, cost, snapped_ = baselines.three_pass(p, 3, 1.2 * n / 3, 2, 1)
    return verdict(s, (math.isfinite(cost), snapped_.count() == n), "finite boolean, all_snapped boolean")


@query("b07_chunk_centres", "SELECT (SELECT count(*) FROM customer)::BIGINT AS mass")
def chunk_centres(s, sf):
    return baselines.chunk_reduce(pts(s, sf, WL.W05), 4, 2, 1).agg(F.sum("w").alias("mass"))


@query("b08_facilities", "SELECT (SELECT count(*) FROM customer)::BIGINT AS mass")
def facilities(s, sf):
    return baselines.facility_stream(pts(s, sf, WL.W05), 2, 1, 40_000.0).agg(F.sum("w").alias("mass"))


@query("b10_all_assignments", "SELECT (count(*) * ln(8))::DOUBLE > count(*) AS worse_than_input FROM lineitem")
def all_assignments(s, sf):
    n = table(s, sf, "lineitem").count()
    return verdict(s, (PR.all_assignments_bound(n, 8) > n,), "worse_than_input boolean")


_SCOPES = {"one": (), "all": (2, 10)}


@query("b11_rates_by_scope", f"WITH {O.points(WL.ORD)}, a AS (SELECT {_PLACE4}::INTEGER AS j, count(*) AS size FROM pts GROUP BY 1) SELECT j, size, "
       + ", ".join(f"{(n := PR.fixed_instance_rate(0.01, 1.0, 2, 2, 0.01, *scope)[0])}::BIGINT AS independence_{name}, least(1e0, {O.number(1000 * 2.0**4 * n)} / ({O.number(0.01**3)} * size)) AS rate_{name}" for name, scope in _SCOPES.items()) + " FROM a")
def rates_by_scope(s, sf):
    """By cluster of orders: the independence and rate that its size asks for if one set of centres is to be served, and if all are."""
    sizes = C.size_vector(C.nearest(pts(s, sf, WL.W04), WL.W04.centres, 2), 2).where("size > 0").collect()  # two rows
    rows = [(r["j"], r["size"], *(v for scope in _SCOPES.values() for v in PR.fixed_instance_rate(0.01, r["size"], 2, 2, 0.01, *scope))) for r in sizes]
    return s.createDataFrame(rows, "j int, size long, independence_one long, rate_one double, independence_all long, rate_all double")


@query("b13_nearest_centres", f"WITH {O.points(WL.ORD)} SELECT tag, x0, x1, {_PLACE4B}::INTEGER AS j, {_NEAR4} AS cost FROM pts")
def nearest_centres(s, sf):
    return C.nearest(pts(s, sf, WL.W04), WL.W04.centres, 2)


@query("b14_library_kmeans", "SELECT true AS positive")
def library_kmeans(s, sf):
    _, cost = baselines.library_kmeans(pts(s, sf, WL.W16), 5, 2)
    return verdict(s, (cost > 0,), "positive boolean")


# --- measures and workloads


def summary_report(s, sf, i, percents=(55, 75, 100), eta=0.1, theorem=False):
    p = pts(s, sf, i)
    n = p.count()
    return measures.coreset_ratios(p, built(s, sf, i), i.centres[:2], [(n * f + 99) // 100 for f in percents], eta, theorem)


@query("a12_transfer_overhead", "SELECT true AS few_moved, true AS little_dearer")
def transfer_overhead(s, sf):
    with_, _, _, _ = _extended(s, sf, WL.W04, 1.2)
    without, _, _, _ = _extended(s, sf, WL.W04, 1.2, transfer=False)
    row = measures.transfer_overhead(without, with_, ["tag"], 2, WL.W04.params.xi)
    return row.select((F.col("moved") <= F.greatest(F.lit(50), F.col("moved_bound"))).alias("few_moved"), (F.col("cost_factor") <= 1.1).alias("little_dearer"))


@query("a13_residue", O.chain(WL.W01, *O.UP_TO_PARTS, "important") + "SELECT count(*) AS n_left, count(*)::DOUBLE / (SELECT count(*) FROM routed) AS share_left FROM routed ANTI JOIN important USING (level, p0, p1)")
def residue(s, sf):
    i = WL.W01
    p = baselines.parts_of(pts(s, sf, i), i.grid, i.params)
    sizes = p.groupBy("level", "p0", "p1").agg(F.count("*").alias("size"))
    return measures.residue(p, coreset.important_parts(sizes, i.params), ["level", "p0", "p1"])


@query("a06_a21_summary_size", O.chain(WL.W01, *O.UP_TO_CORESET) + "SELECT count(*) AS n_summary, (SELECT count(*) FROM pts) AS n_input FROM core")
def summary_size(s, sf):
    return built(s, sf, WL.W01).coreset.agg(F.count("*").alias("n_summary")).join(F.broadcast(pts(s, sf, WL.W01).agg(F.count("*").alias("n_input"))), F.lit(True))


@query("a07_heavy_counts", O.chain(WL.W01, "points", "leaves", "cells", "heavy") + f"SELECT count(*) AS n_heavy, count(*) <= {WL.W01.params.cell_cap!r} AS within FROM heavy")
def heavy_counts(s, sf):
    return partition.heavy_cells(_cells(s, sf, WL.W01), WL.W01.params).agg(F.count("*").alias("n_heavy"), (F.count("*") <= WL.W01.params.cell_cap).alias("within"))


@query("a09_level_mass", O.chain(WL.W01, *O.UP_TO_PARTS) + "SELECT level, sum(size)::BIGINT AS mass, count(*) AS n_parts FROM parts GROUP BY level")
def level_mass(s, sf):
    return partition.level_masses(partition.part_sizes(partition.mark_exact(_cells(s, sf, WL.W01), WL.W01.grid, WL.W01.params), WL.W01.grid))


@query("a15_tail_bound", "SELECT true AS holds")
def tail_bound(s, sf):
    """The frequency with which a hashed sample is off by a quarter, over 16 families, against the bound."""
    p = pts(s, sf, WL.W05)
    families = [P.hash_family(f"tail {k}", "f", 4) for k in range(16)]
    counts = p.agg(*(F.count_if(P.poly_hash(["tag", "x0"], h) < P.threshold(0.5)).alias(f"f{k}") for k, h in enumerate(families)), F.count("*").alias("n")).first()
    n = counts["n"]
    off = sum(abs(counts[f"f{k}"] - n / 2) > n / 8 for k in range(16)) / 16
    return verdict(s, (off <= PR.tail_bound(n / 2, 1, 4, n / 8) + 0.05,), "holds boolean")


_SHAPE17 = cellstore.Shape(1200)


def _bucket_sql(shape, rep):
    acc, *rest = shape.numbers(f"bucket {rep}", 4)
    for c in rest:
        acc = f"(({acc}::BIGINT * low + {c}) % {P.FIELD})"
    return f"SELECT {rep} AS rep, {acc} % {shape.buckets} AS bucket FROM u"


@query("a17_sketch_bits", O.chain(WL.W01, "points", "leaves")[:-1] + f", u AS (SELECT DISTINCT ((c0 >> 5) * 2048 + (c1 >> 5)) % {P.FIELD} AS low FROM leaf), b AS (" + " UNION ".join(_bucket_sql(_SHAPE17, rep) for rep in range(_SHAPE17.repetitions)) + f") SELECT count(*) AS used_rows, {_SHAPE17.rows}::BIGINT AS max_rows, {_SHAPE17.bits}::BIGINT AS bits FROM b")
def sketch_bits(s, sf):
    """The rows that a sketch of lineitem's cells of level 5 fills, of those that its shape allows, and the bits of all."""
    i, shape = WL.W01, _SHAPE17
    updates = pts(s, sf, i).select(*i.grid.leaf(i.spec.coordinates)).select(cellstore.pack(i.grid.keys(5), i.grid.levels + 1).alias("key"), F.lit(1).cast("long").alias("sign"))
    return cellstore.sketch(updates, shape).agg(F.count("*").alias("used_rows")).select("used_rows", F.lit(shape.rows).cast("long").alias("max_rows"), F.lit(shape.bits).cast("long").alias("bits"))


@query("w12_label_purity", "WITH s AS (SELECT label, count(*) AS n FROM embeddings GROUP BY label) SELECT label, n, n::DOUBLE / (SELECT sum(n) FROM s) AS share FROM s")
def label_purity(s, sf):
    """Labels as a naturally balanced instance: each one's share."""
    counts = table(s, sf, "embeddings").groupBy("label").agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)))


@query("w13_brute_force", "SELECT true AS equal")
def brute_force(s, sf):
    """Flow and sweep against every assignment of ten points."""
    i = WL.W13
    first = pts(s, sf, i).orderBy("tag").limit(10)
    x, w = C.arrays(first, 2)
    z = np.array(i.centres)
    ok = all(abs(solvers.brute_force(x[:, :2], z, t, 2) - flow.capacitated(x[:, :2], w, z, t, 2)) < 1e-6 for t in (5, 6, 8, 10))
    return verdict(s, (ok,), "equal boolean")


@query("w16_territories", "WITH t AS (SELECT n_regionkey AS region, avg(c_acctbal) AS m FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1) SELECT region, count(*) AS customers FROM t JOIN nation ON n_regionkey = region JOIN customer ON c_nationkey = n_nationkey GROUP BY region")
def territories(s, sf):
    n = F.broadcast(table(s, sf, "nation"))  # 25 rows
    return table(s, sf, "customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy(F.col("n_regionkey").alias("region")).agg(F.count("*").alias("customers"))


@query("w17_supply_points", "WITH p AS (SELECT least(256, greatest(1, CAST(floor((p_retailprice - 900.0) / 100.0 * 255) AS BIGINT) + 1)) AS x0, least(256, greatest(1, CAST(floor((s_acctbal + 1000.0) / 11000.0 * 255) AS BIGINT) + 1)) AS x1 FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey) SELECT x0, x1, count(*) AS n FROM p GROUP BY x0, x1")
def supply_points(s, sf):
    met = table(s, sf, "lineitem").select("l_partkey", "l_suppkey").join(table(s, sf, "part").select("p_partkey", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey")).join(table(s, sf, "supplier").select("s_suppkey", "s_acctbal"), F.col("l_suppkey") == F.col("s_suppkey"))
    spec = P.PointSpec("supply", "", (P.Dimension("p_retailprice", 900, 1000), P.Dimension("s_acctbal", -1000, 10000)), 8)
    return P.discretize(met, spec).groupBy("x0", "x1").agg(F.count("*").alias("n"))


@query("w19_rate_sweep", "SELECT true AS grows_with_m, true AS shrinks_with_guess")
def rate_sweep(s, sf):
    """Summaries grow with m and shrink as the guess grows."""
    i = WL.W06
    p = pts(s, sf, i)

    def size(**change):
        return coreset.build(p, i.grid, i.params._replace(**change), i.core_hash).coreset.count()

    by_m = [size(m=m) for m in (8.0, 32.0, 128.0)]
    by_guess = [size(guess=i.params.guess * f) for f in (1.0, 8.0)]
    return verdict(s, (by_m == sorted(by_m) and by_m[0] < by_m[2], by_guess[0] >= by_guess[1]), "grows_with_m boolean, shrinks_with_guess boolean")


@query("w20_theory_is_exact", O.chain(WL.W20, *O.UP_TO_CORESET) + "SELECT count(*) AS n, min(w) AS least, max(w) AS most FROM core")
def theory_is_exact(s, sf):
    return built(s, sf, WL.W20).coreset.agg(F.count("*").alias("n"), F.min("w").alias("least"), F.max("w").alias("most"))


@query("w21_crowded_cells", O.chain(WL.W14, "points", "leaves") + "SELECT c0, c1, count(*) AS n, max(tag) AS last FROM leaf GROUP BY c0, c1 HAVING count(*) > 2")
def crowded_cells(s, sf):
    i = WL.W14
    return pts(s, sf, i).select("tag", *i.grid.leaf(i.spec.coordinates)).groupBy("c0", "c1").agg(F.count("*").alias("n"), F.max("tag").alias("last")).where("n > 2")
