import __spark_entry__ as entry
from balclust import register


def test_contract(spark):
    queries, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 120
    assert set(register.QUERIES) <= set(queries)
    assert entry.entry(spark).count() > 0


def test_summary_survives_its_store(spark, tmp_path):
    from balclust import workloads as WL
    from balclust.queries_methods import built
    from balclust.sources import store

    made = built(spark, "/root/testdata/sf0.001", WL.W04)
    store.save(made, str(tmp_path))
    back = store.load(spark, str(tmp_path))
    assert back.params == made.params and back.grid == made.grid
    assert sorted(map(tuple, back.coreset.select(made.coreset.columns).collect())) == sorted(map(tuple, made.coreset.collect()))
