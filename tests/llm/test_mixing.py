import hashlib
import random
import re
from collections import Counter

import duckdb
from pyspark.sql import functions as F

from balclust.llm import mixing


def water(sizes):
    """Targets by repeated sharing-out of what is above the cap."""
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)}
    total, capped = sum(sizes.values()), set()
    while True:
        free = [s for s in names if s not in capped]
        rest = total - sum(3 * sizes[s] for s in capped)
        share = {s: rest * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > 3 * sizes[s] + 1e-9}
        if not over:
            return share | {s: 3 * sizes[s] for s in capped}
        capped |= over


def table(seed=1, n=400):
    rng = random.Random(seed)
    names = ["b", "a", "é", "Z", None, "zz", "tiny"]
    rows = []
    for k in range(n):
        s = rng.choices(names, [200, 40, 40, 20, 20, 80, 1])[0]
        size = rng.choice([0, 1, 5, 80, 700, 3000])
        rows.append((k, rng.choice(["", " ", None]) if not size else "\n".join(["wörd"] * size), s, 3))
    return rows + rows[:5] + [(None, "null id here", "a", 3), (None, "null id here", "a", 3), (7, "same id other text", "b", 3)]


def test_targets_taken_and_sql(spark, tmp_path):
    rows = table()
    path = str(tmp_path / "documents.parquet")
    spark.createDataFrame(rows, "doc_id long, text string, source string, size int").repartition(3).write.parquet(path)
    got = mixing.op8(spark, str(tmp_path)).collect()
    sizes = Counter()
    for _, t, s, _ in rows:
        sizes[s] += len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    assert sorted((r.doc_id or -1, r["size"]) for r in got) == sorted((i or -1, len((t or "").split())) for i, t, _, _ in rows)
    want = water(sizes)
    by_size = {n: s for s, n in sizes.items()}
    assert len(by_size) == len(sizes)
    taken = Counter()
    for r in got:
        assert 0 <= r.taken <= 3 * r["size"]
        assert abs(r.target - want[by_size[r.source_size]]) < 1e-6 * max(1, r.target)
        taken[by_size[r.source_size]] += r.taken
    assert all(abs(taken[s] - want[s]) <= 1 for s in sizes)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{path}/*.parquet')")
    assert sorted(map(tuple, got), key=str) == sorted(con.execute(mixing.OP8_SQL).fetchall(), key=str)
    again = mixing.op8(spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got), key=str) == sorted(map(tuple, again), key=str)


def test_draws_permute_blocks_and_fill_shards(spark):
    sources = spark.createDataFrame([("sa", 10_000, 0, 25_500.0), ("sb", 3_000_000, 1, 500_000.4), ("sc", 5, 2, 15.0), ("sd", 0, 3, 0.0)], "source_key string, source_size long, place long, target double")
    drawn = mixing.draws(sources, 100)
    rows = drawn.collect()
    words = Counter()
    for r in rows:
        words[r.source_key] += r.taken
    assert words == {"sa": 25_500, "sb": 500_000, "sc": 15}
    times = Counter((r.source_key, r["index"]) for r in rows)
    assert {times["sa", k] for k in range(100)} == {2, 3}
    assert max(v for (s, _), v in times.items() if s == "sb") == 1
    assert sum(r.n_blocks for r in mixing.shard_counts(drawn).collect()) == len(rows)


def test_edges(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, source string")
    assert mixing.mixture(empty).count() == 0
    blank = spark.createDataFrame([(1, " ", "a"), (2, None, None)], "doc_id long, text string, source string")
    assert [(r["size"], r.target, r.taken) for r in mixing.mixture(blank).collect()] == [(0, 0.0, 0)] * 2


def test_applied_mix_has_the_words_taken(spark):
    df = spark.createDataFrame([(k, "lang", s, t, len(t)) for k, s, t, _ in ((i, s, t or "", 0) for i, t, s, _ in table(2, 60))], "doc_id long, lang string, source string, text string, n_chars long")
    mixed = mixing.apply(df)
    assert mixed.columns == df.columns
    total = df.select(mixing.word_count(df.text).alias("n")).groupBy().sum("n").first()[0]
    rows = mixed.collect()
    assert abs(sum(len(r.text.split()) for r in rows) - total) <= 7
    assert all(r.n_chars == len(r.text) for r in rows)


def test_applied_mix_has_the_words_of_the_drawn_blocks(spark):
    rng, block = random.Random(5), 10
    sizes = [rng.choice([3, 25, 130]) for _ in range(60)]
    rows = [(k, "x", "abc"[k % 3], "\n".join(f"d{k}w{i}" for i in range(n)), 0) for k, n in enumerate(sizes)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, source string, text string, n_chars long").repartition(3)
    order = {s: sorted((k for k in range(60) if "abc"[k % 3] == s), key=lambda k: (int(hashlib.md5(str(k).encode()).hexdigest()[:12], 16) % mixing.BUCKETS, k)) for s in "abc"}
    stream = {"s" + s: [f"d{k}w{i}" for k in order[s] for i in range(sizes[k])] for s in "abc"}
    totals = spark.createDataFrame([(s, len(w)) for s, w in stream.items()], "source_key string, source_size long")
    want = Counter()
    for r in mixing.draws(mixing.targets(totals), block).collect():
        want.update(stream[r.source_key][r["index"] * block : r["index"] * block + r.taken])
    texts = [r.text.split() for r in mixing.apply(df, block).collect()]
    assert Counter(w for t in texts for w in t) == want
    places = [[int(w.split("w")[1]) for w in t] for t in texts]
    assert all(p == sorted(set(p)) for p in places)
    assert any(p[0] > 0 for p in places)


def test_a_permutation_of_blocks_is_no_progression(spark):
    """One pass over each source draws every block once, in an order without a step or a run, and other passes and sources have orders of their own."""
    full = (178, 200, 1, 2, 3001)
    sources = spark.createDataFrame([(f"s{k}", 100 * n, k, 300.0 * n) for k, n in enumerate(full)], "source_key string, source_size long, place long, target double")
    orders = {}
    for r in mixing.draws(sources, 100).collect():
        orders.setdefault(r.source_key, []).append(r["index"])
    for k, n in enumerate(full):
        assert Counter(orders[f"s{k}"]) == Counter({i: 3 for i in range(n)})
    half = mixing.draws(spark.createDataFrame([("s0", 17_800, 0, 8900.0), ("s4", 300_100, 4, 150_050.0)], "source_key string, source_size long, place long, target double"), 100).collect()
    for name, n in (("s0", 178), ("s4", 3001)):
        drawn = sorted(r["index"] for r in half if r.source_key == name)
        gaps = Counter(b - a for a, b in zip(drawn, drawn[1:]))
        assert len(drawn) == len(set(drawn)) == -(-n // 2)
        # of a random half, half of the gaps are 1, a quarter 2, an eighth 3
        assert 0.3 < gaps[1] / len(drawn) < 0.7 and gaps[3] > 0 and max(gaps) < 30


def test_ids_in_steps_and_nulls_share_no_bucket(spark):
    ids = spark.createDataFrame([(1024 * k,) for k in range(5000)], "doc_id long")
    most = ids.select(mixing.bucket(F.col("doc_id"), 1024).alias("b")).groupBy("b").count().agg(F.max("count")).first()[0]
    assert most < 25


def test_applied_mix_keeps_columns_of_any_name(spark):
    names = ["_key", "_tie", "_copy", "_turn", "_size", "_taken", "row", "size", "copy", "ranges", "drawn", "tie", "key", "hash", "turn", "place"]
    rows = [(k, f"w{k} " * 50, "ab"[k % 2], *(f"{n}{k}" for n in names)) for k in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, " + ", ".join(f"`{n}` string" for n in names))
    mixed = mixing.apply(docs)
    assert mixed.columns == docs.columns
    got = mixed.collect()
    assert got and all(r[n] == f"{n}{r.doc_id}" for r in got for n in names)
