"""What the second round's findings showed: results that grow go to files, states and sketches that grow with their input, exact sums."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from pyspark.sql import functions as F

from balclust import catalogue
from balclust import workloads as WL
from balclust.operators import cost as C
from balclust.operators import cellstore, flow, partition
from balclust.streaming import dynamic as D

SF = "/root/testdata/sf0.001"


def test_sessions_do_not_pass_through_the_driver(spark, monkeypatch):
    """the sessions are as many as the input makes, so no table in the driver's memory holds them."""
    monkeypatch.setattr(D, "run", lambda *a, **k: pytest.fail("a table in the driver's memory"))
    got = catalogue.queries()["stream_session_users"](spark, SF)
    assert got.agg({"n": "sum"}).first()[0] == spark.read.parquet(f"{SF}/events.parquet").count()


def test_points_of_a_group_are_counted_at_once(spark):
    """one state holds the points of a group; a point goes at zero, whichever of its updates comes first."""
    names = ["tag", "x0", "x1"]
    frame = lambda rows: pd.DataFrame(rows, columns=["op", *names])
    held, changed = D.settled(None, iter([frame([(1, 1, 5, 5), (1, 2, 6, 6)]), frame([(-1, 3, 7, 7)])]), names)
    assert sorted(map(tuple, changed.to_numpy().tolist())) == [(1, 5, 5, 1), (2, 6, 6, 1), (3, 7, 7, -1)]
    held, changed = D.settled(held, iter([frame([(-1, 1, 5, 5), (1, 3, 7, 7), (1, 2, 6, 6)])]), names)
    assert sorted(map(tuple, changed.to_numpy().tolist())) == [(1, 5, 5, 0), (2, 6, 6, 2), (3, 7, 7, 0)]
    assert np.frombuffer(held, np.int64).tolist() == [2, 6, 6, 2]
    assert D.settled(held, iter([]), names)[0] == held and not len(D.settled(held, iter([]), names)[1])


@pytest.mark.parametrize("name", ["stream_exact_survivors", "stream_state_processor"])
def test_survivors_of_groups(spark, name, monkeypatch):
    """With a few groups, so that each state holds many points."""
    monkeypatch.setattr(D, "GROUPS", 3)
    got = {r["tag"] for r in catalogue.queries()[name](spark, SF).collect()}
    assert got == {r[0] for r in spark.read.parquet(f"{SF}/events.parquet").where("event_id % 5 >= 1").select("event_id").collect()}


def test_cubed_cost_beyond_64_bits(spark, tmp_path):
    """as many rows as pass 2^63 in millionths of cubes still add up, to the last digit."""
    few = spark.read.parquet(f"{SF}/lineitem.parquet").limit(20)
    few.write.parquet(str(tmp_path / "few" / "lineitem.parquet"))
    few.sparkSession.range(100_000).join(few.limit(1), how="cross").drop("id").withColumn("l_extendedprice", F.lit(104_999.0)).withColumn("l_quantity", F.lit(50.0)).write.parquet(str(tmp_path / "many" / "lineitem.parquet"))
    run = catalogue.queries()["m22_cost_w01_r3"]
    assert run(spark, str(tmp_path / "few")).dtypes == [("cost", "bigint")]
    i = WL.W01
    one = C.nearest(WL.load(spark, str(tmp_path / "many"), i.spec), i.centres, 3).select("cost").distinct().collect()
    assert len(one) == 1 and run(spark, str(tmp_path / "many")).first()["cost"] == 100_000 * one[0]["cost"] >= 1 << 63


ON_TABLES = {"a17_sketch_bits": "lineitem", "b11_rates_by_scope": "orders", "m07_thresholds": "lineitem", "m10_parameters": "lineitem", "m27_tie_exchange": "supplier", "m30_transfer": "customer", "signed_event_source": "events"}


@pytest.mark.parametrize("name", ON_TABLES)
def test_jobs_that_read_a_table(spark, name, tmp_path):
    """The twin names the table, results agree, and a job without the table fails."""
    con = duckdb.connect()
    con.execute(f"CREATE VIEW {ON_TABLES[name]} AS SELECT * FROM read_parquet('{SF}/{ON_TABLES[name]}.parquet')")
    sql = con.execute(catalogue.oracle_sql()[name])
    columns = [d[0] for d in sql.description]
    frame = catalogue.queries()[name](spark, SF)
    assert sorted(frame.columns) == sorted(columns)
    assert sorted(map(tuple, frame.select(*columns).collect()), key=repr) == sorted(sql.fetchall(), key=repr)
    with pytest.raises(Exception):  # noqa: B017,PT011  (whichever reader finds that there is no such table)
        catalogue.queries()[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("seed", range(6))
def test_transport_from_prices_costs_the_same(seed, monkeypatch):
    """begun with prices, as large inputs are, the assignment costs what it costs from the nearest centres, and its prices certify it."""
    rng = np.random.default_rng(seed)
    x, z, w = rng.integers(0, 60, (300, 2)), rng.integers(0, 60, (6, 2)), rng.choice([1.0, 2.5, 64.0], 300)
    cost, capacity = flow.costs(x, z, 2), np.full(6, w.sum() / 6 * [1.0, 1.1, 2.0][seed % 3])
    cold = flow.value(cost, flow.transport(cost, w, capacity)[0])
    monkeypatch.setattr(flow, "COLD", 0)
    share, price = flow.transport(cost, w, capacity)
    assert flow.value(cost, share) == pytest.approx(cold) == pytest.approx(flow.dual_value(cost, w, capacity, price))
    assert (share.sum(axis=0) <= capacity * (1 + 1e-9)).all()


def test_warehouses_join_and_tag_once(spark):
    """what is left to run reads staged points alone, not the three tables again; a level written out for each value made steps that are interpreted."""
    left = catalogue.queries()["w17_warehouses"](spark, SF)
    assert not [f for f in left.inputFiles() if "lineitem" in f or "supplier" in f]
    assert left.agg({"load": "sum"}).first()[0] == spark.read.parquet(f"{SF}/lineitem.parquet").count()
    for values in ({-1: 5, 0: 2**62, 1: 7}, {0: 0.5, 1: 2.0, 3: 4.0}):
        column = partition.by_level("level", values)
        assert str(column).count("level") == 1
        got = spark.createDataFrame([(k,) for k in (-2, -1, 0, 1, 2, 3, 4, None)], "level int").select("level", column.alias("v")).collect()
        assert {r["level"]: r["v"] for r in got} == {k: values.get(k) for k in (-2, -1, 0, 1, 2, 3, 4, None)}


def test_keys_of_one_residue_are_told_apart(spark):
    """The hashes of a sketch saw a key modulo 2^31 - 1 alone, so that two keys of one residue shared every bucket."""
    shape = cellstore.Shape(50)
    rows = [(5 + k * cellstore.FIELD, 1) for k in range(20)] + [(7, 1), (7, -1)]
    sketch = cellstore.sketch(spark.createDataFrame(rows, "key long, sign long"), shape)
    held = sketch.collect()
    want = {5 + k * cellstore.FIELD: 1 for k in range(20)}
    assert cellstore.decode(held, shape) == want
    keys, counts = cellstore.peel(np.array([[r["rep"], r["bucket"], *(r[c] for c in cellstore.SUMS)] for r in held]), shape)
    assert dict(zip(keys.tolist(), counts.tolist())) == want
    assert cellstore.peel(np.array([[r["rep"], r["bucket"], *(r[c] for c in cellstore.SUMS)] for r in held]), cellstore.Shape(50, seed=2)) is None


def test_stream_summary_from_many_shares(spark, monkeypatch):
    """With shares of 30 keys, so that each family has many sketches, the summary is that of one sketch each."""
    found = [sorted(map(tuple, catalogue.queries()["w08_stream_coreset"](spark, SF).collect()))]
    monkeypatch.setattr(D, "shares", lambda params, grid, most, own=D.shares: own(params, grid, most, 30))
    assert max(D.shares(WL.W07.params, WL.W07.grid, 1000).values()) > 30
    assert sorted(map(tuple, catalogue.queries()["w08_stream_coreset"](spark, SF).collect())) == found[0]
