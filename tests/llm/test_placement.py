from collections import Counter

import duckdb
import pytest

from balclust.llm import placement


def brute(shards, slots):
    """Each shard's whole order of preference, then turns."""
    prefer = []
    for s in shards:
        offset, step = placement._number(f"{s}/offset") % slots, placement._number(f"{s}/step") % (slots - 1) + 1
        prefer.append([(offset + k * step) % slots for k in range(slots)])
        assert sorted(prefer[-1]) == list(range(slots))
    table, nexts = {}, [0] * len(shards)
    while len(table) < slots:
        for k in range(len(shards)):
            free = next((s for s in prefer[k][nexts[k] :] if s not in table), None)
            if free is None:
                break
            nexts[k] = prefer[k].index(free) + 1
            table[free] = k
    return [table[s] for s in range(slots)]


def test_table_equals_turns():
    for n, slots in ((1, 7), (3, 101), (10, 251)):
        shards = [f"s{k}" for k in range(n)]
        assert placement.fill(shards, slots) == brute(shards, slots)


def test_even_weighted_and_stable():
    shards = [f"s{k}" for k in range(20)]
    full = placement.fill(shards, 10_007)
    assert max(Counter(full).values()) - min(Counter(full).values()) <= 1
    less = placement.fill(shards[:-1], 10_007)
    moved = sum(a != b for a, b in zip(full, less) if a != 19)
    assert moved < 0.15 * 10_007
    heavy = Counter(placement.fill(shards, 10_007, [3] + [1] * 19))
    assert 2.8 < heavy[0] / heavy[1] < 3.2
    for bad in ([], ["a"]):
        with pytest.raises(ValueError):
            placement.fill(bad, 10)


def test_query_equals_sql_and_edges(spark, tmp_path):
    df = spark.createDataFrame([(None, 1, 5), (3, 1, 5), (3, 1, 5), (10**15, None, 5)], "doc_id long, n_chars long, slot int")
    path = str(tmp_path / "documents.parquet")
    df.write.parquet(path)
    got = sorted(map(tuple, placement.op5(spark, str(tmp_path)).collect()), key=str)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{path}/*.parquet')")
    assert got == sorted(con.execute(placement.op5_sql()).fetchall(), key=str)
    assert placement.place(df.limit(0), "doc_id", ["a", "b"], 7).count() == 0


def test_columns_of_any_name_come_back(spark):
    df = spark.createDataFrame([(5, "a", "b", 1)], "slot long, row string, `_slot` string, `_shard` int")
    (r,) = placement.place(df, "slot", ["x", "y", "z"]).collect()
    assert r.asDict().keys() == {"row", "_slot", "_shard", "slot", "shard"} and (r.row, r._slot, r._shard) == ("a", "b", 1)
