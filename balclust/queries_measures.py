"""Measures and whole methods against SQL that recomputes them: ratios, bounds, regions of many centres, estimated sizes, machines, stored models, ablations."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from balclust import workloads as WL
from balclust.functions import points as P
from balclust.operators import assign, baselines, coreset, distributed, flow, halfspace, measures, partition, solvers
from balclust.operators import cost as C
from balclust.plans import oracle as O
from balclust.plans import params as PR
from balclust.queries_methods import _machines, _near_sql, built, pts, summary_report
from balclust.register import query, table
from balclust.sources import store

# --- two centres under a capacity, on weighted rows


def two_cost(source, name, i, caps):
    """name (t, cost): SQL of the cheapest fractional assignment of weighted rows (x0.., tag, w) to an instance's first two centres; null where 2 t is too little."""
    xs = i.spec.coordinates
    da, db = (O.dist(xs, z, 2) for z in i.centres[:2])
    return f"""{name}_d AS (SELECT {da} - {db} AS diff, {db} AS db, w, sum(w) OVER (ORDER BY {da} - {db}, {', '.join(xs)}, tag ROWS UNBOUNDED PRECEDING) - w AS before FROM {source}),
{name}_t AS (SELECT sum(w) AS w, sum(w * db) AS b, coalesce(sum(CASE WHEN diff < 0 THEN w END), 0) AS free FROM {name}_d),
{name}_m AS (SELECT t, b, w > 2 * t AS short, greatest(w - t, least(t, free)) AS m FROM ({caps}) c, {name}_t),
{name} AS (SELECT t, CASE WHEN any_value(short) THEN NULL ELSE any_value(b) + sum(diff * greatest(0, least(d.w, m - before))) END AS cost FROM {name}_m, {name}_d d GROUP BY t)"""


def _full_cost(i):
    """full (m, cost): the input's cost of sending its first m points of the order to the first centre."""
    xs = i.spec.coordinates
    da, db = (O.dist(xs, z, 2) for z in i.centres[:2])
    return f"""fd AS (SELECT {da} - {db} AS diff, {db} AS db, row_number() OVER (ORDER BY {da} - {db}, {', '.join(xs)}, tag) AS m FROM pts),
sweep AS (SELECT m, (sum(diff) OVER (ORDER BY m) + sum(db) OVER ())::BIGINT AS cost FROM fd UNION ALL SELECT 0, sum(db)::BIGINT FROM fd)"""


_CAP = "SELECT unnest([((n * 55 + 99) // 100)::BIGINT, ((n * 75 + 99) // 100)::BIGINT, n::BIGINT]) AS c FROM (SELECT count(*) AS n FROM pts)"


def _ratios_sql(i, theorem):
    """t, upper, lower as measures.coreset_ratios defines them, for eta 0.1."""
    eta = 1 + 0.1
    wide, mine = (eta**1 if theorem else eta**2), (1.0 if theorem else eta)
    full = lambda t: f"(SELECT min(cost) FROM sweep WHERE m >= (SELECT count(*) FROM pts) - {t} AND m <= {t})"
    return (
        O.chain(i, *O.UP_TO_CORESET)[:-1] + f", caps AS ({_CAP}), {_full_cost(i)}, {two_cost('core', 'up', i, f'SELECT c * {eta!r}e0 AS t FROM caps')}, {two_cost('core', 'low', i, f'SELECT c * {mine!r}e0 AS t FROM caps')} "
        f"SELECT c AS t, round(coalesce(up.cost, 'inf'::DOUBLE) / {full('c')}, 4) AS upper, round({full(f'floor(c * {wide!r}e0)')} / coalesce(low.cost, 'inf'::DOUBLE), 4) AS lower FROM caps JOIN up ON up.t = c * {eta!r}e0 JOIN low ON low.t = c * {mine!r}e0"
    )


def _ratio_query(name, i, theorem):
    @query(name, _ratios_sql(i, theorem))
    def run(s, sf):
        return summary_report(s, sf, i, theorem=theorem).select("t", F.round("upper", 4).alias("upper"), F.round("lower", 4).alias("lower"))


_ratio_query("a02_a03_ratios", WL.W04, False)
_ratio_query("v14_theorem_form", WL.W04, True)


def _caps(n):
    return [(n * f + 99) // 100 for f in (55, 75, 100)]


@query("w19_ablation", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", caps AS ({_CAP}), {O.hashed(WL.W04, WL.W04.core_hash, 'pts', 'uni_h')}, uni AS (SELECT *, {P.RANGE / P.threshold(0.02)!r}::DOUBLE AS w FROM uni_h WHERE h < {P.threshold(0.02)}), "
       f"plain AS (SELECT hashed.*, {float(P.RANGE)!r}::DOUBLE / floor(least({float(P.RANGE)!r}::DOUBLE, {float(P.RANGE)!r}::DOUBLE * 40 / size))::BIGINT AS w FROM hashed JOIN parts USING (level, p0, p1) WHERE h < floor(least({float(P.RANGE)!r}::DOUBLE, {float(P.RANGE)!r}::DOUBLE * 40 / size))::BIGINT), "
       f"{_full_cost(WL.W04)}, " + ", ".join(two_cost(source, f"c_{source}", WL.W04, f"SELECT c * {1 + 0.1!r}e0 AS t FROM caps") for source in ("core", "uni", "plain")) + " "
       + " UNION ALL ".join(f"SELECT '{label}' AS method, c AS t, (SELECT count(*) FROM {source}) AS n_rows, round(coalesce(x.cost, 'inf'::DOUBLE) / (SELECT min(cost) FROM sweep WHERE m >= (SELECT count(*) FROM pts) - c AND m <= c), 4) AS upper FROM caps JOIN c_{source} x ON x.t = c * {1 + 0.1!r}e0" for label, source in (("summary", "core"), ("uniform", "uni"), ("plain parts", "plain"))))
def ablation(s, sf):
    """How far the cost of the summary, of a uniform sample and of plain samples of all parts is from the input's, at the same capacities."""
    i = WL.W04
    p = pts(s, sf, i)
    whole = built(s, sf, i)
    caps = _caps(p.count())
    out = None
    for name, rows in (("summary", whole.coreset), ("uniform", baselines.uniform_sample(p, 0.02, i.core_hash, 2)), ("plain parts", baselines.plain_coreset(p, i.grid, i.params, i.core_hash, 40))):
        one = measures.coreset_ratios(p, whole._replace(coreset=rows), i.centres[:2], caps, 0.1).select(F.lit(name).alias("method"), "t", F.lit(rows.count()).cast("long").alias("n_rows"), F.round("upper", 4).alias("upper"))
        out = one if out is None else out.unionByName(one)
    return out


@query("m20_dual_certificate", f"WITH {O.points(WL.ORD)}, {_full_cost(WL.W04)}, c AS (SELECT ((count(*) * 60 + 99) // 100)::BIGINT AS t, count(*) AS n FROM pts) SELECT t, (SELECT min(cost) FROM sweep WHERE m >= n - t AND m <= t) AS cost, true AS bound_below, true AS near FROM c")
def dual_certificate(s, sf):
    """The exact cost under a capacity of 60 in 100; prices from the summary's flow bound it from below in one pass over all points, and come near it."""
    i = WL.W04
    p = pts(s, sf, i)
    x, w = C.arrays(built(s, sf, i).coreset, 2, "w")
    n, z = p.count(), np.array(i.centres)
    t = (n * 60 + 99) // 100
    _, price = flow.transport(flow.costs(x[:, :2], z, 2), w, np.full(2, 0.6 * w.sum()))
    exact = C.two_centre_cost(p, *i.centres, s.createDataFrame([(t,)], "t long")).first()["cost"]
    bound = float(C.dual_bound(p, i.centres, np.rint(price).astype(int).tolist(), t).first()[0])
    return s.createDataFrame([(t, exact, bound <= exact, bound >= 0.9 * exact)], "t long, cost long, bound_below boolean, near boolean")


@query("m21_weighted_bracket", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", {two_cost('core', 'bracket', WL.W04, 'SELECT 0.6e0 * sum(w) AS t FROM core')} SELECT round(cost / (SELECT sum(w) FROM core), 4) AS fractional, true AS few_splits, true AS within FROM bracket")
def weighted_bracket(s, sf):
    """The summary's fractional cost by its flow, and whether removing its one split changes it by no more than that point's weight can."""
    i = WL.W04
    x, w = C.arrays(built(s, sf, i).coreset, 2, "w")
    cost = flow.costs(x[:, :2], np.array(i.centres), 2)
    share, _ = flow.transport(cost, w, np.full(2, 0.6 * w.sum()))
    split = np.flatnonzero((share > 1e-9 * w.sum()).sum(axis=1) > 1)
    whole, splits = flow.remove_splits(cost, share)
    low, high = flow.value(cost, share), float((w * cost[np.arange(len(x)), whole]).sum())
    room = float((w[split] * np.abs(cost[split, 0] - cost[split, 1])).sum()) + 1e-6 * low
    return s.createDataFrame([(round(float(low / w.sum()), 4), splits <= 1, abs(high - low) <= room)], "fractional double, few_splits boolean, within boolean")


@query("m35_serve", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + ", caps AS (" + _CAP + "), " + ", ".join(two_cost("core", f"z{n}", WL.W04._replace(centres=tuple((z[0] // (n + 1) + 1, z[1] // (n + 1) + 1) for z in WL.W04.centres)), f"SELECT c * {1 + 0.1!r}e0 AS t FROM caps") for n in range(3))
       + " " + " UNION ALL ".join(f"SELECT {n} AS z, c AS t, round(x.cost / (SELECT sum(w) FROM core), 3) AS mean_cost FROM caps JOIN z{n} x ON x.t = c * {1 + 0.1!r}e0" for n in range(3)))
def serve(s, sf):
    """A stored model, loaded again, answers for centres and capacities that were not known when it was built."""
    i = WL.W04
    path = store.fresh(s, "model")
    store.save(built(s, sf, i), path)
    x, w = C.arrays(store.load(s, path).coreset, 2, "w")
    rows = []
    for n in range(3):
        z = [(c[0] // (n + 1) + 1, c[1] // (n + 1) + 1) for c in i.centres]
        for t in _caps(pts(s, sf, i).count()):
            value = flow.capacitated(x[:, :2], w, z, (1 + 0.1) * t, 2)
            rows.append((n, t, None if math.isinf(value) else round(float(value / w.sum()), 3)))
    return s.createDataFrame(rows, "z int, t long, mean_cost double")


# --- solutions


_N4, _P4 = _near_sql(WL.W04, 2)


@query("a04_solution_quality", f"WITH {O.points(WL.ORD)}, {_full_cost(WL.W04)}, a AS (SELECT {_P4} AS j, {_N4} AS cost FROM pts), c AS (SELECT ((count(*) * 55 + 99) // 100)::BIGINT AS t, count(*) AS n FROM pts) SELECT t, (SELECT sum(cost)::DOUBLE FROM a) / (SELECT min(cost) FROM sweep WHERE m >= n - t AND m <= t) AS alpha, (SELECT max(n) FROM (SELECT count(*) AS n FROM a GROUP BY j))::DOUBLE / t AS beta FROM c")
def solution_quality(s, sf):
    """Nearest centres against the best assignment under a capacity of 55 in 100: cheaper, and over the capacity."""
    i = WL.W04
    p = pts(s, sf, i)
    t = _caps(p.count())[0]
    best = C.two_centre_cost(p, *i.centres, s.createDataFrame([(t,)], "t long")).first()["cost"]
    return measures.solution_quality(C.nearest(p, i.centres, 2), 2, float(t), float(best)).select(F.lit(t).alias("t"), "alpha", "beta")


@query("a05_assignment_report", f"WITH {O.points(WL.DOC)}, a AS (SELECT {_near_sql(WL.W14, 2)[1]} AS j, {_near_sql(WL.W14, 2)[0]} AS cost FROM pts) SELECT sum(cost)::BIGINT AS cost, (SELECT max(n) FROM (SELECT count(*) AS n FROM a GROUP BY j)) AS largest, (SELECT max(n) FROM (SELECT count(*) AS n FROM a GROUP BY j))::DOUBLE / 100 AS violation FROM a")
def assignment_report(s, sf):
    return assign.report(C.nearest(pts(s, sf, WL.W14), WL.W14.centres, 2), 4, 100.0)


@query("v04_capacitated_bottleneck", f"WITH {O.points(WL.ORD)}, d AS (SELECT {O.dist(WL.ORD.coordinates, WL.W04.centres[0], 2)} AS da, {O.dist(WL.ORD.coordinates, WL.W04.centres[1], 2)} AS db FROM pts), caps AS ({_CAP}), ra AS (SELECT da, row_number() OVER (ORDER BY da DESC) AS k FROM d), rb AS (SELECT db, row_number() OVER (ORDER BY db DESC) AS k FROM d) SELECT c AS t, greatest((SELECT max(least(da, db)) FROM d), coalesce((SELECT da FROM ra WHERE k = c + 1), 0), coalesce((SELECT db FROM rb WHERE k = c + 1), 0))::BIGINT AS radius FROM caps")
def capacitated_bottleneck(s, sf):
    p = pts(s, sf, WL.W04)
    return C.two_centre_bottleneck(p, *WL.W04.centres, _caps(p.count()))


_COARSE = P.PointSpec("coarse", "supplier", (P.Dimension("s_acctbal", -1000, 10000), P.Dimension("s_nationkey", 0, 24)), 2, key="s_suppkey")


@query("v13_exhaustive_pairs", f"WITH {O.points(_COARSE)}, c AS (SELECT x0, x1, count(*) AS w FROM pts GROUP BY x0, x1), v AS (SELECT a.x0 AS a0, a.x1 AS a1, b.x0 AS b0, b.x1 AS b1, sum(p.w * least((p.x0 - a.x0) ** 2 + (p.x1 - a.x1) ** 2, (p.x0 - b.x0) ** 2 + (p.x1 - b.x1) ** 2)) AS cost FROM c a, c b, c p GROUP BY ALL) SELECT min(cost)::DOUBLE AS cost FROM v")
def exhaustive_pairs(s, sf):
    """The best two of the coarse lattice's points as centres, by trying all."""
    counted = pts(s, sf, WL.W13._replace(spec=_COARSE)).groupBy("x0", "x1").agg(F.count("*").alias("w"), F.min("tag").alias("tag"))  # at most 16 rows
    x, w = C.arrays(counted, 2, "w")
    return s.createDataFrame([(float(solvers.exhaustive(x[:, :2], w, 2, w.sum(), 2)[1]),)], "cost double")


_TINY = P.PointSpec("tiny", "supplier", _COARSE.dimensions, 3, key="s_suppkey")


@query("a20_assignments_counted", f"WITH {O.points(_TINY)}, q AS (SELECT *, row_number() OVER (ORDER BY x0, x1, tag) - 1 AS id FROM (SELECT * FROM pts WHERE tag <= 10)), z AS (SELECT unnest(range(1, 9)) AS z), d AS (SELECT a.z AS a0, b.z AS a1, c.z AS b0, e.z AS b1, id, x0, x1, tag, (x0 - a.z) ** 2 + (x1 - b.z) ** 2 - (x0 - c.z) ** 2 - (x1 - e.z) ** 2 AS diff FROM q, z a, z b, z c, z e), m AS (SELECT sum(1 << id) OVER (PARTITION BY a0, a1, b0, b1 ORDER BY diff, x0, x1, tag) AS mask FROM d) SELECT (count(DISTINCT mask) + 1)::BIGINT AS n_assignments, {2.0 ** PR.assignments_bound(8, 2, 2)!r}::DOUBLE AS half_spaces, 1024::BIGINT AS all_assignments FROM m")
def assignments_counted(s, sf):
    """Assignments of ten points that are best for some two centres and sizes, of all that there are: sets that a half-space of the order cuts off."""
    q = pts(s, sf, WL.W13._replace(spec=_TINY)).where("tag <= 10").withColumn("id", F.row_number().over(W.orderBy("x0", "x1", "tag")) - 1)
    z = s.range(1, 9)
    pairs = z.select(F.col("id").alias("a0")).crossJoin(z.select(F.col("id").alias("a1"))).crossJoin(z.select(F.col("id").alias("b0"))).crossJoin(z.select(F.col("id").alias("b1")))  # 4,096 rows of a fixed lattice
    diff = (F.col("x0") - F.col("a0")) * (F.col("x0") - F.col("a0")) + (F.col("x1") - F.col("a1")) * (F.col("x1") - F.col("a1")) - (F.col("x0") - F.col("b0")) * (F.col("x0") - F.col("b0")) - (F.col("x1") - F.col("b1")) * (F.col("x1") - F.col("b1"))
    each = pairs.crossJoin(F.broadcast(q)).withColumn("diff", diff)  # ten rows are broadcast
    mask = F.sum(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("id"))).over(W.partitionBy("a0", "a1", "b0", "b1").orderBy("diff", "x0", "x1", "tag"))
    return each.select(mask.alias("mask")).agg((F.count_distinct("mask") + 1).alias("n_assignments"), F.lit(2.0 ** PR.assignments_bound(8, 2, 2)).alias("half_spaces"), F.lit(1 << 10).cast("long").alias("all_assignments"))


# --- proved bounds beside what is measured


def _opt(i):
    return f"(SELECT sum({_near_sql(i, i.params.r)[0]})::DOUBLE FROM pts)"


@query("a07_heavy_bound", O.chain(WL.W01, "points", "leaves", "cells", "heavy") + f"SELECT count(*) AS n_heavy, {WL.W01.params.heavy_bound(1.0)!r}::DOUBLE * {_opt(WL.W01)} AS bound, count(*) <= {WL.W01.params.heavy_bound(1.0)!r}::DOUBLE * {_opt(WL.W01)} AS within FROM heavy")
def heavy_bound(s, sf):
    """The number of heavy cells against the proved bound, with the cost of fixed centres for the best cost."""
    i = WL.W01
    n = partition.heavy_cells(partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid), i.params).count()
    bound = i.params.heavy_bound(1.0) * float(C.plain_cost(pts(s, sf, i), i.centres, 2).first()[0])
    return s.createDataFrame([(n, bound, n <= bound)], "n_heavy long, bound double, within boolean")


def _centre_gap(z, i):
    gaps = [f"pow(greatest(0, greatest((k{m} << greatest(0, {i.spec.levels} - level)) - {z[m] - i.grid.shift[m] + i.spec.side}, {z[m] - i.grid.shift[m] + i.spec.side} - (((k{m} + 1) << greatest(0, {i.spec.levels} - level)) - 1))), 2)" for m in range(i.spec.d)]
    return f"({' + '.join(gaps)}) * {i.spec.d ** 2} <= pow(2.0, 2 * ({i.spec.levels} - level))"


@query("a08_centre_cells_bound", O.chain(WL.W04, "points", "leaves", "cells") + f"SELECT count(*) AS n_cells, {WL.W04.params.centre_cell_bound}::BIGINT AS bound, count(*) <= {WL.W04.params.centre_cell_bound} AS within FROM cells WHERE level >= 0 AND ({' OR '.join(_centre_gap(z, WL.W04) for z in WL.W04.centres)})")
def centre_cells_bound(s, sf):
    """Non-empty cells near a centre, over all levels, against the bound 2000 k L."""
    from balclust.register import QUERIES

    bound = WL.W04.params.centre_cell_bound
    return QUERIES["m43_centre_cells"](s, sf).where("level >= 0").agg(F.sum("n").alias("n_cells")).select("n_cells", F.lit(bound).cast("long").alias("bound"), (F.col("n_cells") <= bound).alias("within"))


_MASS = {j: 4000 * (WL.W01.params.k * 10 + 2**3.0) * WL.W01.params.cell_threshold(j) for j in range(11)}


@query("a09_level_mass_bound", O.chain(WL.W01, *O.UP_TO_PARTS) + f"SELECT level, sum(size)::BIGINT AS mass, {O.case('level', _MASS)} AS bound, sum(size) <= {O.case('level', _MASS)} AS within FROM parts GROUP BY level")
def level_mass_bound(s, sf):
    i = WL.W01
    mass = partition.level_masses(built(s, sf, i).parts)
    bound = partition.by_level("level", _MASS)
    return mass.select("level", "mass", bound.alias("bound"), (F.col("mass") <= bound).alias("within"))


_SIDE = {j: (math.sqrt(2) * 2.0 ** (10 - j)) ** 2 for j in range(11)}


@query("a11_sampling_error", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", f AS (SELECT level, count(*) AS n, sum({_N4})::BIGINT AS cost FROM routed JOIN important USING (level, p0, p1) GROUP BY level), g AS (SELECT level, count(*) AS n_sampled, sum({_N4})::BIGINT AS sampled, any_value(w) AS w FROM core GROUP BY level) SELECT level, n, n_sampled, round(abs(n - n_sampled * w) / n, 6) AS size_error, round(abs(cost - sampled * w) / (n * {O.case('level', _SIDE)} + cost), 6) AS cost_error FROM f JOIN g USING (level)")
def sampling_error(s, sf):
    """By level: the summary's number and cost of points against those of the important parts, as shares of what the bounds scale with (points, and points times the cell's diameter plus the cost)."""
    i = WL.W04
    b = built(s, sf, i)
    whole = partition.routed_points(pts(s, sf, i), b.heavy, i.grid).join(F.broadcast(coreset.important_parts(b.parts, i.params).select("level", "p0", "p1")), ["level", "p0", "p1"])
    full = C.nearest(whole, i.centres, 2).groupBy("level").agg(F.count("*").alias("n"), F.sum("cost").alias("cost"))
    part = C.nearest(b.coreset, i.centres, 2).groupBy("level").agg(F.count("*").alias("n_sampled"), F.sum("cost").alias("sampled"), F.max("w").alias("w"))
    scale = F.col("n") * partition.by_level("level", _SIDE) + F.col("cost")
    return full.join(part, "level").select("level", "n", "n_sampled", F.round(F.abs(F.col("n") - F.col("n_sampled") * F.col("w")) / F.col("n"), 6).alias("size_error"), F.round(F.abs(F.col("cost") - F.col("sampled") * F.col("w")) / scale, 6).alias("cost_error"))


def _seeded(k):
    return WL.W05._replace(core_hash=P.hash_family(f"seed {k}", "core", 8))


def _seed_sql(k):
    i = _seeded(k)
    near = _near_sql(i, 2)[0]
    return f"SELECT * FROM ({O.chain(i, *O.UP_TO_CORESET)} SELECT {k}::INTEGER AS seed, (SELECT count(*) FROM core) AS n_summary, round((SELECT sum(w * {near}) FROM core) / (SELECT sum({near})::DOUBLE FROM pts) - 1, 6) AS off)"


@query("a19_failures_over_seeds", " UNION ALL ".join(_seed_sql(k) for k in range(10)))
def failures_over_seeds(s, sf):
    """Of ten hash families, the size of the summary and how far off its cost of fixed centres is."""
    i = WL.W05
    p = pts(s, sf, i)
    full = float(C.plain_cost(p, i.centres, 2).first()[0])
    out = None
    for k in range(10):
        core = C.nearest(coreset.build(p, i.grid, i.params, _seeded(k).core_hash).coreset, i.centres, 2)
        one = core.agg(F.lit(k).alias("seed"), F.count("*").alias("n_summary"), F.round(F.sum(F.col("w") * F.col("cost")) / full - 1, 6).alias("off"))
        out = one if out is None else out.unionByName(one)
    return out


def _share(f):
    return O.chain(WL.W04, *O.UP_TO_CORESET).replace("pts AS (", "every AS (", 1).replace(", \nleaf", ", leaf").replace("leaf AS (SELECT *", f"pts AS (SELECT * FROM every WHERE tag % 8 < {f}), leaf AS (SELECT *", 1)


@query("w18_scale_sweep", " UNION ALL ".join(f"SELECT * FROM ({_share(f)} SELECT {f}::INTEGER AS eighths, (SELECT count(*) FROM pts) AS n, (SELECT count(*) FROM heavy) AS n_heavy, count(*) AS n_summary FROM core)" for f in (1, 2, 4, 8)))
def scale_sweep(s, sf):
    """The summary's size as the input grows at a fixed guess."""
    i, out = WL.W04, None
    for f in (1, 2, 4, 8):
        p = pts(s, sf, i).where(F.col("tag") % 8 < f)
        b = coreset.build(p, i.grid, i.params, i.core_hash)
        counts = [d.agg(F.count("*").alias(c)) for d, c in ((p, "n"), (b.heavy, "n_heavy"), (b.coreset, "n_summary"))]
        one = counts[0].join(F.broadcast(counts[1]), F.lit(True)).join(F.broadcast(counts[2]), F.lit(True)).select(F.lit(f).alias("eighths"), "n", "n_heavy", "n_summary")  # one row each
        out = one if out is None else out.unionByName(one)
    return out


@query("a16_time_by_rows")
def time_by_rows(s, sf):
    """Seconds that the summary takes as the input grows; no SQL, since times differ."""
    return measures.timed_sweep(pts(s, sf, WL.W04), (1, 2, 4, 8), lambda p: coreset.build(p, WL.W04.grid, WL.W04.params, WL.W04.core_hash).coreset)


# --- half-spaces and regions of four centres, and for r = 1


def _regions_sql(i, r):
    """a (the summary, nearest centres), e (ends by level), placed (all points with region)."""
    xs, z, k = i.spec.coordinates, i.centres, len(i.centres)
    key = {(a, b): f"struct_pack(diff := ({O.dist(xs, z[a], r)}) - ({O.dist(xs, z[b], r)}), {', '.join(f'{x} := {x}' for x in xs)}, tag := tag)" for a, b in halfspace.pairs(k)}
    place = _near_sql(i, r)[1]
    ends = ", ".join(f"max(CASE WHEN j = {a} THEN {key[a, b]} END) AS h_{a}_{b}" for a, b in halfspace.pairs(k))
    before = {(a, b): f"coalesce({key[a, b]} <= h_{a}_{b}, false)" for a, b in halfspace.pairs(k)}
    wins = [" AND ".join(before[a, b] if a < b else f"NOT {before[b, a]}" for b in range(k) if b != a) for a in range(k)]
    region = "CASE " + " ".join(f"WHEN {w} THEN {a + 1}" for a, w in enumerate(wins)) + " ELSE 0 END"
    return O.chain(i, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT *, {place} AS j FROM core), e AS (SELECT level, {ends} FROM a GROUP BY level), placed AS (SELECT r.level, p0, p1, {', '.join(f'r.{x}' for x in xs)}, tag, {region} AS region FROM routed r JOIN e USING (level)), inside AS (SELECT a.level, p0, p1, {region} AS region FROM a JOIN e USING (level))"


def _placed(s, sf, i, r):
    b = built(s, sf, i)
    a = C.nearest(b.coreset, i.centres, r)
    ends = halfspace.derive(a, i.centres, r)
    every = partition.routed_points(pts(s, sf, i), b.heavy, i.grid).join(F.broadcast(ends.select("level")), "level")
    return a, halfspace.regions(every, ends, i.centres, r), halfspace.regions(a, ends, i.centres, r)


def _region_queries(tag, i, r):
    k = len(i.centres)
    xs = i.spec.coordinates
    base = _regions_sql(i, r)
    flat = " UNION ALL ".join(f"SELECT level, {a} AS i, {b} AS j, h_{a}_{b}.diff AS diff, h_{a}_{b}.tag AS tag FROM e" for a, b in halfspace.pairs(k))

    @query(f"m25_half_spaces_{tag}", f"{base} {flat}")
    def half_spaces(s, sf):
        ends, out = halfspace.derive(C.nearest(built(s, sf, i).coreset, i.centres, r), i.centres, r), None
        for a, b in halfspace.pairs(k):
            one = ends.select("level", F.lit(a).alias("i"), F.lit(b).alias("j"), f"h_{a}_{b}.diff", f"h_{a}_{b}.tag")
            out = one if out is None else out.unionByName(one)
        return out

    @query(f"m28_regions_{tag}", f"{base} SELECT level, region, count(*) AS n FROM placed GROUP BY level, region")
    def regions(s, sf):
        return _placed(s, sf, i, r)[1].groupBy("level", "region").agg(F.count("*").alias("n"))

    tally = ", ".join(f"count(CASE WHEN region = {a} THEN 1 END) AS b{a}" for a in range(k + 1))

    @query(f"m29_region_tallies_{tag}", f"{base} SELECT level, p0, p1, {tally} FROM inside GROUP BY level, p0, p1")
    def tallies(s, sf):
        t = halfspace.tallies(_placed(s, sf, i, r)[2].withColumn("w", F.lit(1.0)), k, ["level", "p0", "p1"])
        return t.select("level", "p0", "p1", *(F.col(f"b{a}").cast("long").alias(f"b{a}") for a in range(k + 1)))

    most = f"greatest({', '.join(f'b{a}' for a in range(1, k + 1))})"
    fullest = "CASE " + " ".join(f"WHEN b{a} = {most} THEN {a}" for a in range(1, k + 1)) + " END"
    own = "CASE region " + " ".join(f"WHEN {a} THEN b{a}" for a in range(1, k + 1)) + " END"

    @query(f"m30_transfer_{tag}", f"{base}, t AS (SELECT level, p0, p1, {tally} FROM inside GROUP BY level, p0, p1) SELECT tag, (CASE WHEN t.b0 IS NULL THEN NULL WHEN region > 0 AND {own} >= 2 THEN region - 1 ELSE {fullest} - 1 END)::INTEGER AS j FROM placed LEFT JOIN t USING (level, p0, p1)")
    def transfer(s, sf):
        """Every point of the input after the transfer of sparse regions and undecided points."""
        _, every, inside = _placed(s, sf, i, r)
        t = halfspace.tallies(inside.withColumn("w", F.lit(1.0)), k, ["level", "p0", "p1"])
        return halfspace.transfer(every, F.broadcast(t), k, ["level", "p0", "p1"], F.lit(2.0)).select("tag", "j")


_region_queries("four", WL.W14, 2)
_region_queries("orders_r1", WL.W04, 1)
_region_queries("events", WL.W06, 2)


@query("m27_tie_exchange_orders", O.chain(WL.W04, *O.UP_TO_CORESET)[:-1] + f", a AS (SELECT level, tag, x0, x1, tag % 2 AS j, ({O.dist(WL.ORD.coordinates, WL.W04.centres[0], 2)}) - ({O.dist(WL.ORD.coordinates, WL.W04.centres[1], 2)}) AS diff FROM core), b AS (SELECT *, sum(1 - j) OVER (PARTITION BY level, diff) AS firsts, row_number() OVER (PARTITION BY level, diff ORDER BY x0, x1, tag) AS k FROM a) SELECT level, tag, (CASE WHEN k <= firsts THEN 0 ELSE 1 END)::INTEGER AS j FROM b")
def tie_exchange_orders(s, sf):
    i = WL.W04
    a = built(s, sf, i).coreset.withColumn("j", (F.col("tag") % 2).cast("int"))
    return halfspace.exchange_ties(a, *i.centres, 2).select("level", "tag", "j")


# --- estimated sizes all the way, machines


def _hashed_chain(i):
    """SQL of the summary from hashed sizes: est, marked level by level, routed, parts, core."""
    levels, ks, cs = i.spec.levels, [f"k{m}" for m in range(i.spec.d)], [f"c{m}" for m in range(i.spec.d)]
    cut = [{j: P.threshold(i.params.size_rates(j)[w]) for j in range(-1 if w == 0 else 0, levels + 1)} for w in (0, 1)]
    scale = [{j: P.RANGE / t for j, t in c.items()} for c in cut]
    limit = partition.thresholds(i.params)
    keys = ", ".join(f"{c} >> ({levels} - lvl) AS {k}" for c, k in zip(cs, ks, strict=True))
    steps = [O.points(i.spec), O.leaves(i), O.hashed(i, i.cell_hash, "leaf", "h1")]
    steps.append(f"est AS (SELECT level, {', '.join(ks)}, count(*) * {O.case('level', scale[0])} AS n FROM (SELECT lvl AS level, {keys}, h FROM h1, (SELECT CAST(unnest(range(-1, {levels + 1})) AS INTEGER) AS lvl)) WHERE h < {O.case('level', cut[0])} GROUP BY level, {', '.join(ks)})")
    for j in range(-1, levels):
        up = "" if j < 0 else f" SEMI JOIN hv{j} p ON " + " AND ".join(f"e.{k} >> 1 = p.{k}" for k in ks)
        steps.append(f"hv{j + 1} AS (SELECT e.* FROM est e{up} WHERE e.level = {j} AND e.n >= {O.number(limit[j])})")
    steps.append("heavy AS (" + " UNION ALL ".join(f"SELECT * FROM hv{j + 1}" for j in range(-1, levels)) + ")")
    steps.append(O.route(i))
    steps.append(O.hashed(i, i.part_hash, "routed", "h2"))
    steps.append(f"parts AS (SELECT {O.part_key(i)}, count(*) * {O.case('level', scale[1])} AS size FROM h2 WHERE h < {O.case('level', cut[1])} GROUP BY {O.part_key(i)})")
    steps += [O.important(i), O.coreset(i)]
    return "WITH " + ",\n".join(steps) + "\n"


def _hashed_query(name, i):
    xs = ", ".join(i.spec.coordinates)

    @query(name, _hashed_chain(i) + f"SELECT tag, {xs}, {O.part_key(i)}, w FROM core")
    def run(s, sf):
        """The summary with no exact count of anything."""
        return coreset.build_hashed(pts(s, sf, i), i.grid, i.params, i.cell_hash, i.part_hash, i.core_hash).coreset


_hashed_query("m18_coreset_hashed", WL.W04)
_hashed_query("v08_coreset_hashed_lineitem", WL.W01)
_hashed_query("v08_coreset_hashed_events", WL.W07)


def _machine_query(name, i, count, key, by):
    @query(name, O.chain(i, *O.UP_TO_CORESET) + f"SELECT tag, x0, x1, {O.part_key(i)}, w FROM core")
    def run(s, sf):
        """Machines send leaf counts, get the heavy cells and important parts back, and send the points that they sample: the same summary, however rows are dealt."""
        m = WL.load(s, sf, i.spec, (key,) if key != i.spec.key else ()).withColumn("machine", F.pmod(F.expr(by), F.lit(count)).cast("int"))
        return distributed.summary(m, i.grid, i.params, i.core_hash)[0].coreset


for _n in (2, 4, 8, 16):
    _machine_query(f"m40_distributed_coreset_{_n}", WL.W01, _n, "l_orderkey", "l_orderkey")
_machine_query("w10_skewed_coreset", WL.W04, 5, "o_orderpriority", "ascii(o_orderpriority)")


@query("m40_total_bits", f"WITH {O.points(WL.LI2, ('l_orderkey',))}, {O.leaves(WL.W01)}, {O.cells(WL.W01)}, {O.heavy(WL.W01)}, {O.route(WL.W01)}, {O.parts(WL.W01)}, {O.important(WL.W01)}, {O.coreset(WL.W01)}, up AS (SELECT (l_orderkey % 8)::INTEGER AS machine, count(DISTINCT (c0, c1)) AS n_leaves, length(bin(count(*)))::BIGINT AS counter FROM leaf GROUP BY 1), own AS (SELECT (l_orderkey % 8)::INTEGER AS machine, count(*) AS n_points FROM core GROUP BY 1) "
       "SELECT machine, n_leaves, coalesce(n_points, 0)::BIGINT AS n_points, (n_leaves * (22 + counter) + coalesce(n_points, 0) * 86 + (SELECT count(*) FROM heavy) * 22)::BIGINT AS bits FROM up LEFT JOIN own USING (machine)")
def total_bits(s, sf):
    """Bits to and from each of eight machines: leaf counts up, heavy cells down, sampled points up (22 bits a cell, 64 more a tagged point)."""
    return distributed.summary(_machines(s, sf), WL.W01.grid, WL.W01.params, WL.W01.core_hash)[1]


# --- workloads to their end


WL5 = WL.instance(WL.CUST, 3, 2, 2.0**25)


@query("w05_coreset_three", O.chain(WL5, *O.UP_TO_CORESET) + "SELECT tag, x0, level, p0, w FROM core")
def three(s, sf):
    return built(s, sf, WL5).coreset


_N11, _P11 = _near_sql(WL.W11, 2)


@query("w12_purity_free", f"WITH {O.points(WL.EMB, ('label',))}, c AS (SELECT {_P11} AS j, label, count(*) AS n FROM pts GROUP BY 1, 2) SELECT j::INTEGER AS j, sum(n)::BIGINT AS size, max(n) AS most, max(n)::DOUBLE / sum(n) AS purity FROM c GROUP BY j")
def purity_free(s, sf):
    """By cluster of nearest centres: its size and the share of its commonest label."""
    a = C.nearest(pts(s, sf, WL.W11, ("label",)), WL.W11.centres, 2)
    return measures.purity(a, "label")


@query("w12_purity_balanced")
def purity_balanced(s, sf):
    """The same under a capacity of 1.1 times an equal share, by the summary and its extension."""
    i = WL.W11
    p = store.staged(pts(s, sf, i, ("label",)))  # projected once, not in each of the 45 comparisons of two centres
    b = coreset.build(p, i.grid, i.params, i.core_hash)
    n, weight = p.count(), b.coreset.agg(F.sum("w")).first()[0]
    assigned, _ = assign.assign_summary(b.coreset, i.centres, 1.1 * max(n, weight) / 10, 2, i.spec.d)
    return measures.purity(assign.extend(p, b, assigned, i.centres), "label")


_REAL = [f"CAST(round(({m.sql}) * 1e6) AS BIGINT)" for m in WL.EMB.dimensions]
_SPREAD = "CAST(sum(s2) AS DOUBLE) - sum(CAST(s1 AS DOUBLE) * CAST(s1 AS DOUBLE) / n)"


@query("w11_projected_against_raw", f"WITH {O.points(WL.EMB, ('embedding',))}, a AS (SELECT {_P11} AS j, embedding FROM pts), e AS (SELECT j, generate_subscripts(embedding, 1) AS m, CAST(round(unnest(embedding) * 1e6) AS BIGINT) AS v FROM a), y AS ("
       + " UNION ALL ".join(f"SELECT j, {k} AS m, {v} AS v FROM a" for k, v in enumerate(_REAL)) + f"), sums AS (SELECT j, m, count(*) AS n, sum(v) AS s1, sum(v * v) AS s2, 0 AS own FROM e GROUP BY j, m UNION ALL SELECT j, m, count(*), sum(v), sum(v * v), 1 FROM y GROUP BY j, m), spread AS (SELECT j, own, any_value(n) AS n, ({_SPREAD}) / 1e12 AS v FROM sums GROUP BY j, own) "
       "SELECT r.j::INTEGER AS j, r.n, round(r.v, 3) AS raw, round(p.v, 3) AS projected FROM spread r JOIN spread p USING (j) WHERE r.own = 0 AND p.own = 1")
def projected_against_raw(s, sf):
    """By cluster of the projected space: the squared distances to its mean in all 64 columns, and in the four projected ones: four times the raw one on average for clusters that the projection did not choose, less for these."""
    i = WL.W11
    a = C.nearest(pts(s, sf, i, ("embedding",)), i.centres, 2).select("j", "embedding")

    def whole(c):
        return F.round(c * 1e6).cast("long")

    def spread(values, name):
        sums = values.groupBy("j", "m").agg(F.count("*").alias("n"), F.sum(F.col("v").cast("decimal(20,0)")).alias("s1"), F.sum((F.col("v") * F.col("v")).cast("decimal(20,0)")).alias("s2"))
        squared = F.col("s1").cast("double") * F.col("s1").cast("double") / F.col("n")
        return sums.groupBy("j").agg(F.max("n").alias("n"), F.round((F.sum("s2").cast("double") - F.sum(squared)) / 1e12, 3).alias(name))

    raw = spread(a.select("j", F.posexplode("embedding").alias("m", "e")).select("j", "m", whole(F.col("e")).alias("v")), "raw")
    own = spread(a.select("j", F.posexplode(F.array(*(whole(F.expr(m.expression)) for m in i.spec.dimensions))).alias("m", "v")), "projected")
    return raw.join(own.drop("n"), "j").select("j", "n", "raw", "projected")


def _sized(i, m, factor):
    return i._replace(params=i.params._replace(m=m, guess=i.params.guess * factor))


_SWEEP = [(m, f) for m in (8.0, 32.0, 128.0) for f in (1.0, 8.0)]


@query("w19_size_sweep", " UNION ALL ".join(f"SELECT * FROM ({O.chain(_sized(WL.W06, m, f), *O.UP_TO_CORESET)} SELECT {m!r}::DOUBLE AS m, {f!r}::DOUBLE AS factor, (SELECT count(*) FROM heavy) AS n_heavy, count(*) AS n_summary FROM core)" for m, f in _SWEEP))
def size_sweep(s, sf):
    """Heavy cells and rows of the summary for each rate and each multiple of the guess."""
    out = None
    for m, f in _SWEEP:
        b = built(s, sf, _sized(WL.W06, m, f))
        heavy = b.heavy.agg(F.count("*").alias("n_heavy"))
        one = heavy.join(F.broadcast(b.coreset.agg(F.count("*").alias("n_summary"))), F.lit(True)).select(F.lit(m).alias("m"), F.lit(f).alias("factor"), "n_heavy", "n_summary")  # one row each
        out = one if out is None else out.unionByName(one)
    return out


_N14, _P14 = _near_sql(WL.W14, 2)


@query("w14_cluster_composition", f"WITH {O.points(WL.DOC)}, a AS (SELECT tag, {_P14} AS j FROM pts) SELECT j::INTEGER AS j, count(*) AS size, count(CASE WHEN quality = 1 THEN 1 END) AS good, count(CASE WHEN quality = 0 THEN 1 END) AS bad, count(CASE WHEN toxic = 1 THEN 1 END) AS toxic FROM a LEFT JOIN labels ON tag = doc_id GROUP BY j")
def cluster_composition(s, sf):
    a = C.nearest(pts(s, sf, WL.W14), WL.W14.centres, 2).join(table(s, sf, "labels"), F.col("tag") == F.col("doc_id"), "left")
    return a.groupBy("j").agg(F.count("*").alias("size"), F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("quality") == 0).alias("bad"), F.count_if(F.col("toxic") == 1).alias("toxic"))


_BOTH = WL.DOC._replace(table="(SELECT doc_id, text, n_chars, 0 AS item FROM documents UNION ALL SELECT item_id, text, length(text), 1 FROM benchmark)")


@query("w21_leakage_cells", f"WITH {O.points(_BOTH, ('item',))}, {O.leaves(WL.W14)} SELECT c0, c1, count(CASE WHEN item = 0 THEN 1 END) AS n_documents, count(CASE WHEN item = 1 THEN 1 END) AS n_items FROM leaf GROUP BY c0, c1 HAVING count(CASE WHEN item = 1 THEN 1 END) > 0")
def leakage_cells(s, sf):
    """Leaf cells of the documents' lattice that benchmark items lie in, with the documents there: where a copied item has to be looked for."""
    i = WL.W14
    docs = table(s, sf, "documents").select("text", F.col("n_chars").cast("long").alias("n_chars"), F.lit(0).alias("item"))
    items = table(s, sf, "benchmark").select("text", F.length("text").cast("long").alias("n_chars"), F.lit(1).alias("item"))
    met = P.discretize(docs.unionByName(items), i.spec, ["item"]).select("item", *i.grid.leaf(i.spec.coordinates))
    return met.groupBy("c0", "c1").agg(F.count_if(F.col("item") == 0).alias("n_documents"), F.count_if(F.col("item") == 1).alias("n_items")).where("n_items > 0")


def _region_centres(s, sf):
    """The mean lattice point of each region's customers: five rows."""
    nation = F.broadcast(table(s, sf, "nation").select("n_nationkey", "n_regionkey"))
    met = P.discretize(table(s, sf, "customer"), WL.CUSTG, ["c_nationkey"]).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    rows = met.groupBy("n_regionkey").agg(*(F.floor(F.avg(x) + 0.5).alias(x) for x in ("x0", "x1"))).orderBy("n_regionkey").collect()
    return [(r["x0"], r["x1"]) for r in rows]


@query("w16_free_territories", f"WITH {O.points(WL.CUSTG, ('c_nationkey',))}, z AS (SELECT row_number() OVER (ORDER BY n_regionkey) - 1 AS j, CAST(floor(avg(x0) + 0.5) AS BIGINT) AS z0, CAST(floor(avg(x1) + 0.5) AS BIGINT) AS z1 FROM pts JOIN nation ON c_nationkey = n_nationkey GROUP BY n_regionkey), a AS (SELECT tag, min(struct_pack(cost := (x0 - z0) * (x0 - z0) + (x1 - z1) * (x1 - z1), j := j)) AS b FROM pts, z GROUP BY tag) SELECT b.j::INTEGER AS j, count(*) AS load, sum(b.cost)::BIGINT AS cost FROM a GROUP BY 1")
def free_territories(s, sf):
    """Customers by the nearest of the regions' mean points, without a capacity."""
    return C.nearest(pts(s, sf, WL.W16), _region_centres(s, sf), 2).groupBy("j").agg(F.count("*").alias("load"), F.sum("cost").alias("cost"))


@query("w16_capacitated_territories")
def capacitated_territories(s, sf):
    """The same centres when none may serve over 1.05 times the largest region's customers' equal share."""
    i, z = WL.W16, _region_centres(s, sf)
    p, b = pts(s, sf, i), built(s, sf, i)
    n, weight = p.count(), b.coreset.agg(F.sum("w")).first()[0]
    assigned, _ = assign.assign_summary(b.coreset, z, 1.05 * max(n, weight) / len(z), 2, 2)
    return assign.extend(p, b, assigned, z).groupBy("j").agg(F.count("*").alias("load"), F.sum("cost").alias("cost"))


@query("w17_warehouses")
def warehouses(s, sf):
    """Four warehouses for the lattice of parts' prices and suppliers' balances, placed from the summary under a capacity; their loads on all lineitem rows."""
    line = table(s, sf, "lineitem")
    met = line.join(table(s, sf, "part").select("p_partkey", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey")).join(table(s, sf, "supplier").select("s_suppkey", "s_acctbal"), F.col("l_suppkey") == F.col("s_suppkey"))
    spec = P.PointSpec("supply", "", (P.Dimension("p_retailprice", 900, 2100), P.Dimension("s_acctbal", -1000, 10000)), 8)
    i = WL.instance(spec, 4, 2, 2.0**24)
    p = store.staged(P.discretize(P.tag_by_hash(met, line.columns), spec, ("tag",)))  # joined and tagged once, not in each step of the hashes
    b = coreset.build(p, i.grid, i.params, i.core_hash)
    b = b._replace(coreset=store.staged(b.coreset))
    n, weight = p.count(), b.coreset.agg(F.sum("w")).first()[0]
    z, _ = solvers.solve(b.coreset, 4, max(n, weight) / 4, 2, 2)
    assigned, _ = assign.assign_summary(b.coreset, z.tolist(), 1.2 * max(n, weight) / 4, 2, 2)
    routed = store.staged(partition.routed_points(p, b.heavy, i.grid))
    return assign.extend(p, b, assigned, z.tolist(), routed=routed).groupBy("j").agg(F.count("*").alias("load"), F.sum("cost").alias("cost"))


@query("b00_solutions_compared")
def solutions_compared(s, sf):
    """By method: the cost of all customers at their nearest of the centres that it finds for three clusters of at most 1.2 equal shares, and its largest cluster."""
    i = WL5
    p, b = pts(s, sf, i), built(s, sf, i)
    n = p.count()
    t = 1.2 * n / 3
    found = {
        "summary": solvers.solve(b.coreset, 3, n / 3, 2, 1)[0].tolist(),
        "three passes": baselines.three_pass(p, 3, t, 2, 1)[0],
        "chunks": baselines.hierarchy(p, 3, t, 2, 1)[0],
        "facilities": baselines.merged_facilities(p, 3, t, 2, 1, 40_000.0)[0],
        "library": baselines.library_kmeans(p, 3, 1)[0],
    }
    out = None
    for method, z in found.items():
        a = C.nearest(p, z, 2)
        one = a.agg(F.sum("cost").alias("cost")).join(F.broadcast(C.size_vector(a, 3).agg(F.max("size").alias("largest"))), F.lit(True)).select(F.lit(method).alias("method"), "cost", "largest")  # one row each
        out = one if out is None else out.unionByName(one)
    return out
