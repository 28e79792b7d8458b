"""The methods against brute force, worked examples and their invariants."""

import itertools
import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from balclust import workloads as WL
from balclust.functions import points as P
from balclust.operators import cellstore, coreset, distributed, estimate, flow, halfspace, partition, solvers
from balclust.operators import cost as C
from balclust.plans import params as PR

SF = "/root/testdata/sf0.001"
FX1 = [(1, 4), (2, 4), (2, 5), (3, 4), (3, 5), (4, 4)]
FX1_Z = [(2, 4), (7, 4)]


def frame(spark, points):
    return spark.createDataFrame([(k, *map(int, p)) for k, p in enumerate(points)], "tag long, " + ", ".join(f"x{m} long" for m in range(len(points[0]))))


@given(st.lists(st.integers(-50, 50), min_size=3, max_size=3), st.lists(st.integers(-50, 50), min_size=3, max_size=3), st.sampled_from([1, 1.5, 2, 3]))
def test_power_triangle_inequality(a, b, r):
    dist = lambda x, y: math.dist(x, y)
    o = [0, 0, 0]
    assert dist(a, b) ** r <= 2 ** (r - 1) * (dist(a, o) ** r + dist(o, b) ** r) * (1 + 1e-9) + 1e-9


@given(st.integers(1, 64), st.fractions(0, 64, max_denominator=1000), st.integers(-1, 6))
def test_integer_shift_equals_real_shift(x, v, level):
    side = 2 ** (6 - level)
    assert math.floor((x - v) / side) == (x - math.ceil(v)) // side


def test_worked_example_costs(spark):
    df = frame(spark, FX1)
    got = {r.t: r.cost for r in C.two_centre_cost(df, *FX1_Z, spark.createDataFrame([(t,) for t in range(2, 7)], "t long")).collect()}
    assert got == {2: None, 3: 44, 4: 29, 5: 14, 6: 9}
    assert C.plain_cost(df, FX1_Z).first()[0] == 9
    x = np.array(FX1)
    assert [flow.capacitated(x, np.ones(6), np.array(FX1_Z), t, 2) for t in (2, 3, 4, 5, 6)] == [math.inf, 44, 29, 14, 9]
    diffs = sorted(r.diff for r in df.select(*C.order_key(["x0", "x1"], *FX1_Z, 2)[:1]).collect())
    assert diffs == [-35, -25, -25, -15, -15, -5]


def test_sweep_equals_every_assignment(spark):
    rng = random.Random(3)
    for r in (1, 2, 3):
        points = [(rng.randint(1, 30), rng.randint(1, 30)) for _ in range(7)]
        z = [(rng.randint(1, 30), rng.randint(1, 30)) for _ in range(2)]
        got = {x.t: x.cost for x in C.two_centre_cost(frame(spark, points), *z, spark.createDataFrame([(t,) for t in range(4, 8)], "t long"), r).collect()}
        for t in range(4, 8):
            want = solvers.brute_force(np.array(points), np.array(z), t, r) * (1 if r == 2 else P.MICRO)
            assert abs(got[t] - want) <= 10


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10_000))
def test_flow_is_optimal_certified_and_nearly_whole(seed):
    rng = np.random.default_rng(seed)
    n, k = int(rng.integers(3, 8)), int(rng.integers(2, 4))
    x, z = rng.integers(1, 20, (n, 2)), rng.integers(1, 20, (k, 2))
    t = math.ceil(n / k) + int(rng.integers(0, 2))
    assert abs(flow.capacitated(x, np.ones(n), z, t, 2) - solvers.brute_force(x, z, t, 2)) < 1e-6
    w = rng.random(n) + 0.1
    cap = np.full(k, w.sum() / k * (1.02 + rng.random()))
    cost = flow.costs(x, z, 2)
    share, price = flow.transport(cost, w, cap)
    value = flow.value(cost, share)
    assert np.allclose(share.sum(axis=1), w) and (share.sum(axis=0) <= cap + 1e-6).all()
    assert abs(value - flow.dual_value(cost, w, cap, price)) <= 1e-6 * max(1, value)
    whole, splits = flow.remove_splits(cost, share)
    assert splits <= k - 1
    assert (w * cost[np.arange(n), whole]).sum() <= value + 1e-6
    assert np.bincount(whole, w, k).max() <= cap[0] + (k - 1) * w.max() + 1e-6


def test_a_cycle_of_equal_costs_is_cancelled():
    cost = np.ones((2, 2))
    whole, splits = flow.remove_splits(cost, np.array([[0.5, 0.5], [0.5, 0.5]]))
    assert splits <= 1 and len(whole) == 2


def test_crossed_pairs_are_never_optimal():
    rng = np.random.default_rng(1)
    for _ in range(200):
        p, q, a, b = rng.integers(1, 50, (4, 2))
        d = lambda x, y: ((x - y) ** 2).sum()
        if d(p, a) - d(p, b) < d(q, a) - d(q, b):
            assert d(p, a) + d(q, b) < d(q, a) + d(p, b)


def test_ties_exchange_into_order():
    x = np.array([(2, 4), (2, 5)])
    out = flow.canonical(x, np.arange(2), np.array([1, 0]), np.array(FX1_Z), 2)
    assert out.tolist() == [0, 1]
    assert flow.bottleneck(x, np.ones(2), np.array(FX1_Z), 2) <= flow.bottleneck(x, np.ones(2), np.array(FX1_Z), 1)
    assert flow.bottleneck(x, np.ones(2), np.array(FX1_Z), 0.5) == math.inf


def naive(points, grid, params):
    """Top-down marking and parts by recursion."""
    levels = grid.levels
    leaf = [tuple(x - u + (1 << levels) for x, u in zip(p, grid.shift)) for p in points]
    key = lambda c, i: tuple(v >> (levels - i) for v in c)
    heavy, parts = set(), {}
    open_ = {(-1, key(c, -1)) for c in leaf}
    for i in range(-1, levels + 1):
        held = {}
        for c in leaf:
            held.setdefault(key(c, i), []).append(c)
        for cell, own in held.items():
            if (i, cell) not in open_:
                continue
            if i < levels and len(own) >= params.cell_threshold(i):
                heavy.add((i, cell))
                open_ |= {(i + 1, key(c, i + 1)) for c in own}
            elif i >= 0:
                p = (i, tuple(v >> 1 for v in cell))
                parts[p] = parts.get(p, 0) + len(own)
    return heavy, parts


def cluster(n=400, d=2, levels=6, seed=2):
    rng = np.random.default_rng(seed)
    x = np.clip(np.rint(np.concatenate([rng.normal(20, 3, (n // 2, d)), rng.uniform(1, 2**levels, (n - n // 2, d))])), 1, 2**levels)
    return x.astype(int).tolist()


@pytest.mark.parametrize("d", [1, 2, 3])
def test_parts_equal_the_recursion_for_any_guess(spark, d):
    points = cluster(d=d)
    grid = P.grid(d, 6, 5)
    df = frame(spark, points).cache()
    leaves = partition.leaf_counts(df, grid).cache()
    cells = partition.cell_counts(leaves, grid).cache()
    rungs = {(r.guess_log2, r.level): (r.n_heavy, r.mass) for r in partition.ladder(cells, grid, 2, d, 16).collect()}
    for e in (2, 9, 12, 16):
        params = PR.derive(3, 2, d, 6, 2.0**e)
        heavy, parts = naive(points, grid, params)
        marked = partition.mark_exact(cells, grid, params).cache()
        assert {(r.level, tuple(r[k] for k in grid.key_names)) for r in marked.where("kind = 'heavy'").collect()} == heavy
        got = {(r.level, tuple(r[f"p{m}"] for m in range(d))): r["size"] for r in partition.part_sizes(marked, grid).collect()}
        assert got == parts
        routed = {(r.level, tuple(r[f"p{m}"] for m in range(d))) for r in partition.leaf_levels(leaves, cells, grid, params).collect()}
        assert routed == set(parts) and sum(parts.values()) == (len(points) if heavy else 0)
        for level in range(-1, 7):
            assert rungs[e, level] == (sum(h[0] == level for h in heavy), sum(n for (i, _), n in parts.items() if i == level))
        if e == 9:
            chain = partition.mark_cells(cells, grid, params)
            assert sorted(map(tuple, chain.select(*marked.columns).collect())) == sorted(map(tuple, marked.collect()))


def test_theory_profile_keeps_the_input(spark):
    points = cluster(200)
    grid = P.grid(2, 6, 1)
    params = PR.derive(8, 2, 2, 6, 2.0, profile="theory")
    built = coreset.build(frame(spark, points), grid, params, P.hash_family("t", "core", 8))
    rows = built.coreset.collect()
    assert len(rows) == 200 and {r.w for r in rows} == {1.0} and {r.level for r in rows} == {6}
    assert built.params.size_bound > 1e60 and params.gamma < 1e-8


def test_weights_are_unbiased_over_seeds(spark):
    points = cluster(600)
    grid, df = P.grid(2, 6, 1), frame(spark, points).cache()
    params = PR.derive(2, 2, 2, 6, 2.0**17, m=16)
    totals = []
    for s in range(12):
        built = coreset.build(df, grid, params, P.hash_family(s, "core", 8))
        kept = coreset.important_parts(built.parts, params).agg(F.sum("size")).first()[0]
        totals.append(built.coreset.agg(F.sum("w")).first()[0] / kept)
    assert abs(np.mean(totals) - 1) < 0.15 and np.std(totals) > 0


def test_hash_is_independent_over_a_small_field():
    """All polynomials of degree 2 over a small prime: any three points are uniform together."""
    p, counts = 5, {}
    for a, b, c in itertools.product(range(p), repeat=3):
        values = tuple((a * x * x + b * x + c) % p for x in (0, 1, 3))
        counts[values] = counts.get(values, 0) + 1
    assert len(counts) == p**3 and set(counts.values()) == {1}


def test_hash_column_is_the_polynomial(spark):
    h = P.hash_family("x", "f", 5)
    row = spark.createDataFrame([(7, 11, 13)], "tag long, x0 long, x1 long").select(P.poly_hash(["tag", "x0", "x1"], h)).first()[0]
    both = []
    for p in h:
        point = ((7 * p.fold + 11) % P.FIELD * p.fold + 13) % P.FIELD
        acc = 0
        for c in p.coefficients:
            acc = (acc * point + c) % P.FIELD
        both.append(acc)
    assert row == both[0] * P.FIELD + both[1] < P.RANGE
    assert len({p.fold for f in ("cells", "parts", "core") for p in P.hash_family("x", f, 5)}) == 6


def test_regions_and_transfer(spark):
    rng = random.Random(5)
    z = [(10, 10), (50, 12), (30, 55)]
    x = np.array([(rng.randint(1, 64), rng.randint(1, 64)) for _ in range(60)])
    sizes = np.array([20, 20, 20])
    out = flow.reassign(x, np.arange(60), 1.0, np.array(z), sizes, 2)
    df = spark.createDataFrame([(k, int(a), int(b), 0, int(j)) for k, ((a, b), j) in enumerate(zip(x, out))], "tag long, x0 long, x1 long, level int, j int")
    assert all(r.ok for r in halfspace.separable(df, z, 2).collect())
    got = halfspace.regions(df, halfspace.derive(df, z, 2), z, 2).collect()
    assert all(r.region == r.j + 1 for r in got)
    one = halfspace.regions(df, halfspace.derive(df, z[:1], 2), z[:1], 2)
    assert {r.region for r in one.collect()} == {1}


def test_cell_store(spark):
    shape = cellstore.Shape(50)
    rng = random.Random(1)
    keys = [rng.randrange(1 << 62) for _ in range(40)]
    updates = [(k, 1) for k in keys for _ in range(rng.randint(1, 4))]
    gone = [rng.randrange(1 << 62) for _ in range(150)]
    updates += [(k, 1) for k in gone] + [(k, -1) for k in gone]
    rng.shuffle(updates)
    df = spark.createDataFrame(updates, "key long, sign int").withColumn("machine", F.col("key") % 3)
    want = {}
    for k, s in updates:
        want[k] = want.get(k, 0) + s
    want = {k: v for k, v in want.items() if v}
    whole = cellstore.sketch(df.drop("machine"), shape)
    assert whole.count() <= shape.rows
    assert cellstore.decode(whole.collect(), shape) == want
    merged = cellstore.merge(cellstore.sketch(df, shape, ("machine",)).drop("machine"))
    assert cellstore.decode(merged.collect(), shape) == want
    crowded = spark.createDataFrame([(rng.randrange(1 << 62), 1) for _ in range(900)], "key long, sign int")
    assert cellstore.decode(cellstore.sketch(crowded, shape).collect(), shape) is None
    negative = spark.createDataFrame([(5, -1)], "key long, sign int")
    assert cellstore.decode(cellstore.sketch(negative, shape).collect(), shape) is None
    assert cellstore.decode([], shape) == {}


def test_machines_do_not_matter(spark):
    grid = P.grid(2, 6, 3)
    df = frame(spark, cluster())
    want = sorted(map(tuple, partition.cell_counts(partition.leaf_counts(df, grid), grid).collect()))
    bits = []
    for s in (1, 2, 8):
        m = df.withColumn("machine", (F.col("tag") % s).cast("int"))
        assert sorted(map(tuple, distributed.cells_of_machines(m, grid).collect())) == want
        bits.append(distributed.messages(distributed.local_cells(m, grid, 3), grid, 10**6, 0).agg(F.sum("bits")).first()[0])
    assert bits[0] <= bits[1] <= bits[2] <= 8 * bits[0]
    few = distributed.messages(distributed.local_cells(df.withColumn("machine", F.lit(0)), grid, 5), grid, 1, 0).first()
    assert few.failed and few.bits == 1


def test_estimates_at_full_rate_are_exact(spark):
    grid = P.grid(2, 6, 3)
    df = frame(spark, cluster())
    params = PR.derive(3, 2, 2, 6, 2.0**8)
    cells = estimate.good_cells(estimate.estimate_cells(df, grid, params, P.hash_family(1, "cells", 8)), params)
    assert cells.where("NOT good").count() <= 0.1 * cells.count()


def test_degenerate_inputs(spark):
    grid = P.grid(1, 0, 1)
    params = PR.derive(1, 2, 1, 0, 1.0)
    one = spark.createDataFrame([(0, 1)], "tag long, x0 long")
    built = coreset.build(one, grid, params, P.hash_family(1, "core", 8))
    assert built.coreset.count() == 1
    empty = one.limit(0)
    assert coreset.build(empty, grid, params, P.hash_family(1, "core", 8)).coreset.count() == 0
    assert C.plain_cost(empty, [(1,)]).first()[0] == 0
    assert [r["size"] for r in C.size_vector(C.nearest(empty, [(1,)]), 1).collect()] == [0]
    for bad in ({"k": 0}, {"r": 0.5}, {"epsilon": 0}):
        with pytest.raises(ValueError):
            PR.derive(**({"k": 1, "r": 2, "d": 1, "levels": 3, "guess": 1.0} | bad))


def test_tags_tell_equal_points_apart(spark):
    spec = P.PointSpec("t", "t", (P.Dimension("v", 0, 10),), 3, order=("v", "id"))
    df = spark.createDataFrame([(1.0, k) for k in range(5)] + [(-0.0, 9), (0.0, 10)], "v double, id int")
    got = P.points(df, spec).collect()
    assert sorted((r.x0, r.tag) for r in got) == [(1, k) for k in range(1, 8)] if len({r.x0 for r in got}) == 1 else sorted(r.tag for r in got if r.x0 == min(x.x0 for x in got)) == [1, 2, 3, 4, 5, 6, 7][: sum(r.x0 == min(x.x0 for x in got) for r in got)]
    assert P.tag_by_hash(df, ["v", "id"]).select("tag").distinct().count() == 7


def test_monotone_costs(spark):
    df = frame(spark, cluster(300))
    z = WL.W04.centres
    costs = [r.cost for r in C.two_centre_cost(df, *z, spark.createDataFrame([(t,) for t in (150, 180, 220, 300)], "t long")).orderBy("t").collect()]
    assert costs == sorted(costs, reverse=True) and costs[-1] == C.plain_cost(df, z).first()[0]


def test_plans_keep_points_in_place(spark):
    """The scan is pruned, and no plan joins points with points or without keys."""
    df = WL.load(spark, SF, WL.ORD)
    text = coreset.build(df, WL.W04.grid, WL.W04.params, WL.W04.core_hash).coreset._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoop" not in text and "Python" not in text
    assert "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double,o_orderdate:timestamp_ntz>" in text


def test_points_are_routed_without_a_shuffle(spark):
    """Few heavy cells go to the points: no exchange above the points' side, and the same parts as by the join over leaves."""
    i = WL.W04
    points = WL.load(spark, "/root/testdata/sf0.001", i.spec)
    heavy = partition.heavy_cells(partition.cell_counts(partition.leaf_counts(points, i.grid), i.grid), i.params).select("level", *i.grid.key_names, "n")
    rows = partition.held(heavy, i.grid)
    near = partition.route(points, rows, i.grid)
    plan = near._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan and "SortMergeJoin" not in plan
    key = lambda df: sorted((r.tag, r.level, r.p0, r.p1) for r in df.collect())
    assert key(near) == key(partition.routed_points(points, heavy, i.grid, rows))
    keyed = points.select("*", *i.grid.leaf(i.spec.coordinates))
    far = keyed.join(partition.deepest(keyed.select(*i.grid.names).distinct(), heavy, i.grid), i.grid.names)
    assert key(near) == key(far)


def test_parts_from_heavy_cells_equal_parts_from_marks(spark):
    i = WL.W01
    cells = partition.cell_counts(partition.leaf_counts(WL.load(spark, "/root/testdata/sf0.001", i.spec), i.grid), i.grid)
    heavy = partition.heavy_cells(cells, i.params).select("level", *i.grid.key_names, "n")
    key = lambda df: sorted((r.level, r.p0, r.p1, r["size"]) for r in df.collect())
    assert key(partition.parts_of_cells(heavy, i.grid)) == key(partition.part_sizes(partition.mark_exact(cells, i.grid, i.params), i.grid))


def test_a_stream_summary_refuses_a_sketch_that_is_too_small(spark):
    from balclust.operators import cellstore
    from balclust.streaming import dynamic as D

    i = WL.W07
    points = WL.load(spark, "/root/testdata/sf0.001", i.spec).withColumn("op", F.lit(1))
    hashes = {"cells": i.cell_hash, "parts": i.part_hash, "points": i.core_hash}
    shape = cellstore.Shape(8)
    sketches = cellstore.sketch(D.summary_updates(points, i.grid, i.params, hashes), shape, ("family", "level"))
    assert D.sketched_summary(spark, sketches, i.grid, i.params, shape) is None


def test_the_sweep_splits_a_narrow_band_of_differences(spark):
    """All differences close together: buckets by quantiles still hold about equally many."""
    df = spark.range(4000).select(F.col("id").alias("tag"), (F.col("id") % 1000 + 1).alias("x0"), F.lit(5).cast("long").alias("x1"))
    got = {r["m"]: r["cost"] for r in C.two_centre_sweep(df, (500, 5), (501, 5)).collect()}
    x = sorted((k % 1000 + 1 for k in range(4000)), key=lambda v: (v - 500) ** 2 - (v - 501) ** 2)
    run = sum((v - 501) ** 2 for v in x)
    for m, v in enumerate(x, 1):
        run += (v - 500) ** 2 - (v - 501) ** 2
        if m in got:
            assert got[m] == run
    assert len(got) == 1000
