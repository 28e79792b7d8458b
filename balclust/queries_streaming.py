"""Streams: sketches of insertions and deletions, windows, sessions, late and repeated data, exact state, restart."""

from __future__ import annotations

from pyspark.sql import functions as F

from balclust import workloads as WL
from balclust.functions import points as P
from balclust.operators import cellstore
from balclust.plans import oracle as O
from balclust.queries_methods import verdict
from balclust.register import query, table
from balclust.sources import store
from balclust.streaming import dynamic as D

SHAPE = cellstore.Shape(400)


def _updates(s, sf, every=5, upto=1):
    return D.lattice_updates(D.signed(D.events_stream(s, sf), every, upto), WL.EV10)


_LEFT = "WITH " + O.points(WL.EV10).replace("FROM events", "FROM (SELECT * FROM events WHERE event_id % 5 >= 1)") + ", " + O.leaves(WL.W07)


@query("w07_stream_cells", _LEFT + " SELECT c0 >> 7 AS k0, c1 >> 7 AS k1, count(*) AS n FROM leaf GROUP BY 1, 2")
def stream_cells(s, sf):
    """One pass over insertions and deletions into a sketch of fixed size; its decoding is the cells of the survivors."""
    i = WL.W07
    sketch = D.run(cellstore.sketch(D.cell_updates(_updates(s, sf), i.grid, 3), SHAPE))
    return cellstore.decoded(s, sketch.collect(), SHAPE, 2, 11)


@query("w08_stream_heavy_churn", _LEFT.replace("event_id % 5 >= 1", "event_id % 10 >= 9") + " SELECT c0 >> 7 AS k0, c1 >> 7 AS k1, count(*) AS n FROM leaf GROUP BY 1, 2")
def heavy_churn(s, sf):
    i = WL.W07
    sketch = D.run(cellstore.sketch(D.cell_updates(_updates(s, sf, 10, 9), i.grid, 3), SHAPE))
    return cellstore.decoded(s, sketch.collect(), SHAPE, 2, 11)


@query("m37_stream_families", "SELECT true AS all_decoded, true AS equal_batch")
def stream_families(s, sf):
    """All families and levels in one streaming aggregation; each decodes to the sampled cells of the survivors."""
    i = WL.W07
    cuts = {("cells", level): P.threshold(0.5) for level in (0, 1, 2)} | {("core", level): P.threshold(0.25) for level in (1, 2)}
    hashes = {"cells": i.cell_hash, "core": i.core_hash}
    sketches = D.run(cellstore.sketch(D.family_updates(_updates(s, sf), i.grid, cuts, hashes), cellstore.Shape(80), ("family", "level"))).collect()
    left = P.points(table(s, sf, "events").where("event_id % 5 >= 1"), WL.EV10).withColumn("op", F.lit(1))
    batch = D.family_updates(left, i.grid, cuts, hashes).groupBy("family", "level", "key").agg(F.sum("sign").alias("n")).collect()
    decoded_, equal = True, True
    for family, level in cuts:
        found = cellstore.decode([r for r in sketches if r["family"] == family and r["level"] == level], cellstore.Shape(80))
        decoded_ &= found is not None
        equal &= found == {r["key"]: r["n"] for r in batch if r["family"] == family and r["level"] == level}
    return verdict(s, (decoded_, equal), "all_decoded boolean, equal_batch boolean")


#: Room for the keys of one share of a family and level of the stream's summary; a share is meant for D.SHARE of them.
STORE = cellstore.Shape(40_000)


def _stream_summary(name, every, upto):
    from balclust.queries_measures import _hashed_chain

    left = f"FROM (SELECT * FROM events WHERE event_id % {every} >= {upto})"

    @query(name, _hashed_chain(WL.W07).replace("FROM events", left) + "SELECT tag, x0, x1, level, p0, p1, w FROM core")
    def run(s, sf):
        """The summary from one pass over insertions and deletions: sketches of all three families at all levels, decoded; no survivor is kept.

        There are as many sketches as the number of events, known beforehand, asks for. Where one fails all are taken again with other hashes.
        """
        i = WL.W07
        hashes = {"cells": i.cell_hash, "parts": i.part_hash, "points": i.core_hash}
        dealt = D.shares(i.params, i.grid, table(s, sf, "events").count())
        for seed in (1, 2, 3):
            store_ = STORE._replace(seed=seed)
            sketches = D.run_sketches(D.summary_updates(_updates(s, sf, every, upto), i.grid, i.params, hashes), store_, dealt)
            made = D.sketched_summary(s, sketches, i.grid, i.params, store_)
            if made is not None:
                return made.coreset
        raise ValueError("a sketch is too full to be decoded")


_stream_summary("m37_stream_coreset", 5, 1)
_stream_summary("w08_stream_coreset", 10, 9)


@query("m38_parallel_guesses", "SELECT true AS shared, true AS equal_batch")
def parallel_guesses(s, sf):
    """Guesses run side by side: those whose rates round to the same power of two share one sketch, and each decodes."""
    i = WL.W07
    cuts = D.guess_cuts(i.params, range(24, 32))
    levels = range(1, 3)
    shape = cellstore.Shape(80)
    sketches = D.run(cellstore.sketch(D.rate_updates(_updates(s, sf), i.grid, cuts, i.core_hash, levels), shape, ("family", "level"))).collect()
    left = P.points(table(s, sf, "events").where("event_id % 5 >= 1"), WL.EV10).withColumn("op", F.lit(1))
    batch = D.rate_updates(left, i.grid, cuts, i.core_hash, levels).groupBy("family", "level", "key").agg(F.sum("sign").alias("n")).collect()
    distinct = {(c[k], k) for c in cuts.values() for k in levels}
    equal = all(cellstore.decode([r for r in sketches if (r["family"], r["level"]) == (str(c), k)], shape) == {r["key"]: r["n"] for r in batch if (r["family"], r["level"]) == (str(c), k)} for c, k in distinct)
    return verdict(s, (len(distinct) < len(cuts) * len(levels), equal), "shared boolean, equal_batch boolean")


@query("stream_exact_survivors", "WITH " + O.points(WL.EV10).replace("FROM events", "FROM (SELECT * FROM events WHERE event_id % 5 >= 1)") + " SELECT tag, x0, x1 FROM pts")
def exact_survivors(s, sf):
    """State of the points that live, in groups; a point goes at zero; the last count of each key is what is left."""
    changes = D.run_batches(D.survivors(_updates(s, sf)))
    return changes.groupBy("tag", "x0", "x1").agg(F.min("n").alias("least"), F.count("*").alias("c"), F.sum("n").alias("s")).where("least > 0").select("tag", "x0", "x1")


@query("stream_state_processor", "WITH " + O.points(WL.EV10).replace("FROM events", "FROM (SELECT * FROM events WHERE event_id % 5 >= 1)") + " SELECT tag, x0, x1 FROM pts")
def state_processor(s, sf):
    """The same survivors by a state processor with a value per group of points, on the RocksDB store."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = s.conf.get(key, None)
    s.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        changes = D.run_batches(D.counted(_updates(s, sf)))
    finally:
        s.conf.set(key, before) if before else s.conf.unset(key)
    return changes.groupBy("tag", "x0", "x1").agg(F.min("n").alias("least")).where("least > 0").select("tag", "x0", "x1")


@query("m38_stream_summary", O.chain(WL.W07, *O.UP_TO_CORESET).replace("FROM events", "FROM (SELECT * FROM events WHERE event_id % 5 >= 1)") + "SELECT tag, x0, x1, level, p0, p1, w FROM core")
def stream_summary(s, sf):
    """The summary at the end of a stream: exact state of survivors, then the batch steps."""
    from balclust.operators import coreset

    return coreset.build(exact_survivors(s, sf), WL.W07.grid, WL.W07.params, WL.W07.core_hash).coreset


@query("stream_tumbling_cells", "SELECT date_trunc('day', ts) AS day, (event_id % 4)::BIGINT AS k, count(*) AS n FROM events GROUP BY 1, 2")
def tumbling(s, sf):
    agg = D.events_stream(s, sf).groupBy(F.window("ts", "1 day").alias("w"), (F.col("event_id") % 4).alias("k")).agg(F.count("*").alias("n"))
    return D.run(agg).select(F.col("w.start").alias("day"), "k", "n")


@query("stream_sliding_cells", "SELECT time_bucket(INTERVAL 6 HOUR, ts) - s * INTERVAL 6 HOUR AS start, count(*) AS n FROM events, (SELECT unnest([0, 1, 2, 3]) AS s) GROUP BY 1")
def sliding(s, sf):
    agg = D.events_stream(s, sf).groupBy(F.window("ts", "24 hours", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return D.run(agg).select(F.col("w.start").alias("start"), "n")


@query("stream_session_users", "WITH m AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, k")
def sessions(s, sf):
    e = D.events_stream(s, sf).withColumn("ts", D.instant(F.col("ts"))).withWatermark("ts", "1 day")
    agg = e.groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return D.run_complete(agg).select("user_id", D.naive(F.col("w.start")).alias("start"), "n")


@query("stream_dedup", "SELECT event_id, value FROM events")
def dedup(s, sf):
    """The stream replayed twice; each event counts once."""
    e = D.events_stream(s, sf).select("event_id", D.instant(F.col("ts")).alias("ts"), "value")
    twice = e.select("*", F.explode(F.array(F.lit(0), F.lit(1))).alias("copy")).withWatermark("ts", "1 day")
    return D.run_to_files(twice.dropDuplicatesWithinWatermark(["event_id"])).select("event_id", "value")


@query("stream_watermark_windows", "SELECT count(*) > 0 AS some, bool_and(n > 0) AS filled FROM (SELECT date_trunc('day', ts) AS d, count(*) AS n FROM events GROUP BY 1)")
def watermark(s, sf):
    agg = D.events_stream(s, sf).withColumn("ts", D.instant(F.col("ts"))).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return D.run(agg).agg((F.count("*") > 0).alias("some"), F.bool_and(F.col("n") > 0).alias("filled"))


@query("stream_static_assign", f"WITH {O.points(WL.EV10)} SELECT tag, {O.dist(['x0', 'x1'], WL.W07.centres[0], 2)} AS d FROM pts")
def static_assign(s, sf):
    z = s.createDataFrame([(0, *WL.W07.centres[0])], "j int, z0 long, z1 long")
    sdf = P.points(D.events_stream(s, sf), WL.EV10)
    met = sdf.join(F.broadcast(z), F.lit(True))  # one row
    return D.run_to_files(met.select("tag", ((F.col("x0") - F.col("z0")) * (F.col("x0") - F.col("z0")) + (F.col("x1") - F.col("z1")) * (F.col("x1") - F.col("z1"))).alias("d")))


@query("stream_stream_interval_join", "SELECT event_id FROM events WHERE event_id % 5 = 0")
def stream_join(s, sf):
    """Insertions met with their deletions within two days."""
    a = D.signed(D.events_stream(s, sf)).where("op = 1").select(F.col("event_id").alias("a"), D.instant(F.col("ts")).alias("ta")).withWatermark("ta", "3 days")
    b = D.signed(D.events_stream(s, sf)).where("op = -1").select(F.col("event_id").alias("b"), D.instant(F.col("ts")).alias("tb")).withWatermark("tb", "3 days")
    met = a.join(b, F.expr("a = b AND tb >= ta AND tb <= ta + INTERVAL 2 DAYS"))
    return D.run_to_files(met.select(F.col("a").alias("event_id")))


@query("stream_restart", _LEFT.replace("event_id % 5 >= 1", "true") + " SELECT c0 >> 7 AS k0, c1 >> 7 AS k1, count(*) AS n FROM leaf GROUP BY 1, 2")
def restart(s, sf):
    """A stopped stream goes on from its checkpoint: the second run sees the second half alone, and the sum is whole."""
    i = WL.W07
    folder, log, out = store.fresh(s, "arrivals"), store.fresh(s, "log"), store.fresh(s, "sums")
    e = table(s, sf, "events")
    for half in (0, 1):
        e.where(F.col("event_id") % 2 == half).write.mode("append").parquet(folder)
        stream = P.points(s.readStream.schema(e.schema).parquet(folder), WL.EV10).withColumn("op", F.lit(1))
        sketch = cellstore.sketch(D.cell_updates(stream, i.grid, 3), SHAPE)
        path = f"{out}-{half}"
        sketch.writeStream.outputMode("complete").option("checkpointLocation", log).foreachBatch(lambda df, _, p=path: df.write.mode("overwrite").parquet(p)).trigger(availableNow=True).start().awaitTermination()
    return cellstore.decoded(s, s.read.parquet(path).collect(), SHAPE, 2, 11)


@query("stream_window_difference", "SELECT true AS equal")
def window_difference(s, sf):
    """A sliding window as the difference of two sketches: all up to now less all up to the window's start."""
    i = WL.W07
    p = P.points(table(s, sf, "events"), WL.EV10, ("ts",)).withColumn("op", F.lit(1))
    late = F.col("ts") >= F.lit("2024-01-16").cast("timestamp_ntz")
    all_, early = (cellstore.sketch(D.cell_updates(x, i.grid, 3), SHAPE) for x in (p, p.where(~late)))
    less = early.select("rep", "bucket", *((-F.col(c)).alias(c) for c in cellstore.SUMS))
    found = cellstore.decode(cellstore.merge(all_.unionByName(less)).collect(), SHAPE)
    want = {r["key"]: r["n"] for r in D.cell_updates(p.where(late), i.grid, 3).groupBy("key").agg(F.sum("sign").alias("n")).collect()}
    return verdict(s, (found == want,), "equal boolean")
