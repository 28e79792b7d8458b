"""The relational operators around the methods: sources, joins, aggregations, windows, sets, functions, UDFs, SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from balclust import workloads as WL
from balclust.functions import points as P
from balclust.operators import cellstore, coreset, flow, partition
from balclust.operators import cost as C
from balclust.plans import oracle as O
from balclust.queries_methods import built, pts
from balclust.register import query, table
from balclust.sources import store

# --- sources and sinks


@query("scan_points_parquet", "SELECT l_quantity, l_extendedprice FROM lineitem WHERE l_quantity BETWEEN 10 AND 12")
def scan_points(s, sf):
    return table(s, sf, "lineitem").where("l_quantity BETWEEN 10 AND 12").select("l_quantity", "l_extendedprice")


@query("scan_explicit_schema", "SELECT o_orderkey, o_totalprice FROM orders")
def scan_schema(s, sf):
    return s.read.schema("o_orderkey BIGINT, o_totalprice DOUBLE").parquet(f"{sf}/orders.parquet")


for _kind, _name in (("csv", "supplier"), ("orc", "nation"), ("json", "region")):

    @query(f"{_kind}_roundtrip", f"SELECT * FROM {_name}")
    def roundtrip(s, sf, kind=_kind, name=_name):
        return store.read_back(table(s, sf, name), kind, **({"header": "true"} if kind == "csv" else {}))


@query("partition_pruned_level", O.chain(WL.W04, *O.UP_TO_CORESET) + "SELECT tag, x0, x1, w FROM core WHERE level = 5")
def pruned_level(s, sf):
    path = store.fresh(s, "levels")
    built(s, sf, WL.W04).coreset.write.partitionBy("level").parquet(path)
    return s.read.parquet(path).where("level = 5").select("tag", "x0", "x1", "w")


@query("bucketed_points", "SELECT a.o_orderkey, count(*) AS n FROM orders a JOIN orders b USING (o_orderkey) GROUP BY a.o_orderkey")
def bucketed(s, sf):
    """Two readers of one bucketed table join without a shuffle."""
    name = f"bucketed_{store.fresh(s, 't')[-32:]}"
    table(s, sf, "orders").select("o_orderkey", "o_totalprice").write.bucketBy(8, "o_orderkey").sortBy("o_orderkey").option("path", store.fresh(s, "bucketed")).saveAsTable(name)
    a, b = s.table(name), s.table(name).select("o_orderkey")
    return a.join(b, "o_orderkey").groupBy("o_orderkey").agg(F.count("*").alias("n"))


@query("signed_event_source", "SELECT event_id, 1 AS op, value FROM events UNION ALL SELECT event_id, -1, value FROM events WHERE event_id % 5 = 0")
def signed_source(s, sf):
    store.register_signed_events(s)
    return s.read.format("signed_events").option("path", f"{sf}/events.parquet").load()


# --- filters


@query("lattice_box_filter", f"WITH {O.points(WL.ORD)} SELECT tag, x0, x1 FROM pts WHERE x0 BETWEEN 100 AND 300 AND x1 > 512")
def box(s, sf):
    return pts(s, sf, WL.W04).where("x0 BETWEEN 100 AND 300 AND x1 > 512")


_A, _B = WL.W04.centres
_DIFF = f"({O.dist(['x0', 'x1'], _A, 2)}) - ({O.dist(['x0', 'x1'], _B, 2)})"


@query("half_space_filter", f"WITH {O.points(WL.ORD)} SELECT tag FROM pts WHERE {_DIFF} < 0 OR ({_DIFF} = 0 AND x0 < 500)")
def half_space(s, sf):
    diff = P.sqdist(["x0", "x1"], _A) - P.sqdist(["x0", "x1"], _B)
    return pts(s, sf, WL.W04).where(F.struct(diff, F.col("x0")) < F.struct(F.lit(0).cast("long"), F.lit(500).cast("long"))).select("tag")


@query("ring_filter", f"WITH {O.points(WL.ORD)} SELECT tag FROM pts WHERE {O.dist(['x0', 'x1'], _A, 2)} BETWEEN 1024 AND 65536")
def ring(s, sf):
    return pts(s, sf, WL.W04).where(P.sqdist(["x0", "x1"], _A).between(1024, 65536)).select("tag")


@query("predicates_mix", "SELECT p_partkey, p_name FROM part WHERE p_size IN (1, 5, 9) OR (p_name LIKE '%a%' AND p_brand IS NOT NULL AND regexp_matches(p_type, '[A-Z]+') AND p_retailprice BETWEEN 900 AND 950)")
def predicates(s, sf):
    p = table(s, sf, "part")
    return p.where(p.p_size.isin(1, 5, 9) | (p.p_name.like("%a%") & p.p_brand.isNotNull() & p.p_type.rlike("[A-Z]+") & p.p_retailprice.between(900, 950))).select("p_partkey", "p_name")


@query("sample_by_stratum")
def by_stratum(s, sf):
    return table(s, sf, "customer").sampleBy("c_mktsegment", {"BUILDING": 0.5, "MACHINERY": 0.1}, seed=3)


# --- joins


@query("join_points_parts", O.chain(WL.W01, *O.UP_TO_PARTS) + "SELECT level, count(*) AS n, sum(size)::BIGINT AS s FROM routed JOIN parts USING (level, p0, p1) GROUP BY level")
def join_parts(s, sf):
    i = WL.W01
    p = pts(s, sf, i)
    leaves = partition.leaf_counts(p, i.grid)
    cells = partition.cell_counts(leaves, i.grid)
    routed = partition.leaf_levels(leaves, cells, i.grid, i.params)
    parts = partition.part_sizes(partition.mark_exact(cells, i.grid, i.params), i.grid)
    met = p.select("*", *i.grid.leaf(i.spec.coordinates)).join(routed, i.grid.names).join(parts, ["level", "p0", "p1"])
    return met.groupBy("level").agg(F.count("*").alias("n"), F.sum("size").alias("s"))


@query("join_merge_hint", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY o_orderpriority")
def merge_hint(s, sf):
    return table(s, sf, "orders").join(table(s, sf, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def shuffle_hash(s, sf):
    return table(s, sf, "orders").join(table(s, sf, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("interval_join_insert_delete", "WITH d AS (SELECT event_id, ts + INTERVAL 24 HOUR AS gone FROM events WHERE event_id % 5 = 0) SELECT d.event_id, count(*) AS n FROM d JOIN events e ON e.user_id % 10 = d.event_id % 10 AND e.ts >= d.gone - INTERVAL 1 HOUR AND e.ts < d.gone GROUP BY d.event_id")
def interval_join(s, sf):
    """Events in the hour before a deletion, met by hour bins so that the join has an equality."""
    e = table(s, sf, "events").withColumn("hour", F.date_trunc("hour", "ts").cast("timestamp_ntz"))
    d = e.where("event_id % 5 = 0").select(F.col("event_id").alias("d_id"), (F.col("ts") + F.expr("INTERVAL 24 HOURS")).alias("gone"))
    d = d.withColumn("hour", F.explode(F.array(F.date_trunc("hour", "gone").cast("timestamp_ntz"), (F.date_trunc("hour", "gone") - F.expr("INTERVAL 1 HOUR")).cast("timestamp_ntz"))))
    met = e.join(d, (e.hour == d.hour) & (e.user_id % 10 == d.d_id % 10) & (e.ts >= d.gone - F.expr("INTERVAL 1 HOUR")) & (e.ts < d.gone))
    return met.groupBy(F.col("d_id").alias("event_id")).agg(F.count("*").alias("n"))


_VERSIONS = "(VALUES (TIMESTAMP '2024-01-01 00:00:00', 1), (TIMESTAMP '2024-01-09 12:00:00', 2), (TIMESTAMP '2024-01-20 00:00:00', 3)) AS v(valid_from, version)"


@query("asof_parameter_version", f"SELECT event_id, version FROM events ASOF JOIN {_VERSIONS} ON ts >= valid_from")
def asof(s, sf):
    """The version live at each event: union, sort within users' events by time, last value carried on; here by a bounded list of versions."""
    v = s.sql(f"SELECT CAST(valid_from AS TIMESTAMP_NTZ) AS valid_from, version FROM {_VERSIONS}")
    met = table(s, sf, "events").join(F.broadcast(v), F.col("ts") >= F.col("valid_from"))  # three versions
    return met.groupBy("event_id").agg(F.max_by("version", "valid_from").alias("version"))


@query("semi_heavy_ancestor", O.chain(WL.W04, "points", "leaves", "cells", "heavy") + "SELECT c.level, count(*) AS n FROM cells c SEMI JOIN heavy h ON h.level = c.level - 1 AND h.k0 = c.k0 >> 1 AND h.k1 = c.k1 >> 1 GROUP BY c.level")
def semi(s, sf):
    i = WL.W04
    cells = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)
    h = partition.heavy_cells(cells, i.params).select((F.col("level") + 1).alias("level"), F.col("k0").alias("q0"), F.col("k1").alias("q1"))
    keyed = cells.withColumns({"q0": F.expr("shiftright(k0, 1)"), "q1": F.expr("shiftright(k1, 1)")})
    return keyed.join(h, ["level", "q0", "q1"], "left_semi").groupBy("level").agg(F.count("*").alias("n"))


@query("anti_small_parts", O.chain(WL.W01, *O.UP_TO_PARTS, "important") + "SELECT level, count(*) AS n FROM routed ANTI JOIN important USING (level, p0, p1) GROUP BY level")
def anti(s, sf):
    i = WL.W01
    p = pts(s, sf, i)
    leaves = partition.leaf_counts(p, i.grid)
    cells = partition.cell_counts(leaves, i.grid)
    routed = partition.leaf_levels(leaves, cells, i.grid, i.params)
    big = coreset.important_parts(partition.part_sizes(partition.mark_exact(cells, i.grid, i.params), i.grid), i.params)
    met = p.select("*", *i.grid.leaf(i.spec.coordinates)).join(routed, i.grid.names)
    return met.join(big, ["level", "p0", "p1"], "left_anti").groupBy("level").agg(F.count("*").alias("n"))


@query("full_outer_diff", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT coalesce(a.k0, b.k0) AS k0, coalesce(a.n, 0) AS n4, coalesce(b.n, 0) AS n3 FROM (SELECT k0, sum(n)::BIGINT AS n FROM cells WHERE level = 4 GROUP BY k0) a FULL JOIN (SELECT k0, sum(n)::BIGINT AS n FROM cells WHERE level = 3 GROUP BY k0) b ON a.k0 = b.k0")
def full_outer(s, sf):
    i = WL.W04
    cells = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)
    a, b = (cells.where(F.col("level") == k).groupBy("k0").agg(F.sum("n").alias(f"n{k}")) for k in (4, 3))
    return a.join(b, "k0", "full").select("k0", F.coalesce("n4", F.lit(0)).alias("n4"), F.coalesce("n3", F.lit(0)).alias("n3"))


@query("star_join_region_capacity", "SELECT r_name, count(*) AS customers, ceil(count(*) / 5.0)::BIGINT AS capacity FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def star(s, sf):
    n, r = table(s, sf, "nation"), table(s, sf, "region")
    met = table(s, sf, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    return met.groupBy("r_name").agg(F.count("*").alias("customers"), F.ceil(F.count("*") / 5.0).cast("long").alias("capacity"))


_FOUR = WL.W06.centres


@query("nearest_three_centres", f"WITH {O.points(WL.EV12)}, e AS (SELECT tag, unnest([{', '.join(f'struct_pack(c := {O.dist(['x0', 'x1'], z, 2)}, j := {k})' for k, z in enumerate(_FOUR))}]) AS u FROM pts) SELECT tag, (u.j)::INTEGER AS j, rank FROM (SELECT tag, u, (row_number() OVER (PARTITION BY tag ORDER BY u))::INTEGER AS rank FROM e) WHERE rank <= 3")
def nearest_three(s, sf):
    ranked = F.slice(F.sort_array(F.array(*(F.struct(P.sqdist(["x0", "x1"], z).alias("c"), F.lit(k).alias("j")) for k, z in enumerate(_FOUR)))), 1, 3)
    return pts(s, sf, WL.W06).select("tag", F.posexplode(ranked).alias("p", "u")).select("tag", "u.j", (F.col("p") + 1).alias("rank"))


@query("document_label_join", "SELECT lang, quality, toxic, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents LEFT JOIN labels USING (doc_id) GROUP BY lang, quality, toxic")
def label_join(s, sf):
    d = table(s, sf, "documents").select("doc_id", "lang", "n_chars")
    return d.join(table(s, sf, "labels"), "doc_id", "left").groupBy("lang", "quality", "toxic").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


# --- aggregations


@query("distinct_cells_per_level", O.chain(WL.W06, "points", "leaves", "cells") + "SELECT level, count(*) AS n_cells FROM cells GROUP BY level")
def distinct_cells(s, sf):
    i = WL.W06
    return partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid).groupBy("level").agg(F.count("*").alias("n_cells"))


@query("approx_cells_per_level")
def approx_cells(s, sf):
    """Cells per level without exact distinct sets."""
    i = WL.W06
    keyed = pts(s, sf, i).select(*i.grid.leaf(i.spec.coordinates)).select("*", F.explode(F.array(*map(F.lit, range(13)))).alias("level"))
    return keyed.groupBy("level").agg(F.approx_count_distinct(F.struct(*i.grid.keys(F.col("level")))).alias("n_cells"))


@query("grouping_sets_kind_level", "SELECT l_returnflag, l_linestatus, count(*) AS n, grouping(l_returnflag)::TINYINT AS g FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linestatus), ())")
def grouping_sets(s, sf):
    l = table(s, sf, "lineitem")
    return l.groupingSets([[l.l_returnflag, l.l_linestatus], [l.l_linestatus], []], l.l_returnflag, l.l_linestatus).agg(F.count("*").alias("n"), F.grouping("l_returnflag").alias("g"))


@query("cube_machine_level", "SELECT (l_orderkey % 4)::INTEGER AS machine, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (1, 2)")
def cube(s, sf):
    return table(s, sf, "lineitem").select((F.col("l_orderkey") % 4).cast("int").alias("machine"), "l_linestatus").cube("machine", "l_linestatus").agg(F.count("*").alias("n"))


@query("rollup_level_parent", "SELECT l_linestatus, l_returnflag, sum(l_quantity)::BIGINT AS q FROM lineitem GROUP BY ROLLUP (l_linestatus, l_returnflag)")
def rollup(s, sf):
    return table(s, sf, "lineitem").rollup("l_linestatus", "l_returnflag").agg(F.sum("l_quantity").cast("long").alias("q"))


@query("region_tally_pivot", "SELECT event_type, count(CASE WHEN user_id % 3 = 0 THEN 1 END) AS r0, count(CASE WHEN user_id % 3 = 1 THEN 1 END) AS r1, count(CASE WHEN user_id % 3 = 2 THEN 1 END) AS r2 FROM events GROUP BY event_type")
def pivot(s, sf):
    e = table(s, sf, "events").withColumn("r", F.concat(F.lit("r"), (F.col("user_id") % 3).cast("string")))
    return e.groupBy("event_type").pivot("r", ["r0", "r1", "r2"]).agg(F.count(F.lit(1))).na.fill(0)


@query("conditional_counts", "SELECT event_type, count(*) AS n, count(CASE WHEN event_id % 5 = 0 THEN 1 END) AS deleted, bool_and(user_id >= 0) AS valid FROM events GROUP BY event_type")
def conditional(s, sf):
    return table(s, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("event_id") % 5 == 0).alias("deleted"), F.bool_and(F.col("user_id") >= 0).alias("valid"))


@query("part_moments", O.chain(WL.W04, *O.UP_TO_PARTS) + "SELECT level, count(*) AS n, round(avg(size), 4) AS mean, round(var_pop(size), 2) AS var FROM parts GROUP BY level")
def moments(s, sf):
    i = WL.W04
    cells = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)
    parts = partition.part_sizes(partition.mark_exact(cells, i.grid, i.params), i.grid)
    return parts.groupBy("level").agg(F.count("*").alias("n"), F.round(F.avg("size"), 4).alias("mean"), F.round(F.var_pop("size"), 2).alias("var"))


@query("radius_percentile", f"WITH {O.points(WL.ORD)} SELECT quantile_cont({O.dist(['x0', 'x1'], _A, 2)}::DOUBLE, 0.5) AS p50, quantile_cont({O.dist(['x0', 'x1'], _A, 2)}::DOUBLE, 0.9) AS p90 FROM pts")
def percentile(s, sf):
    d = P.sqdist(["x0", "x1"], _A).cast("double")
    return pts(s, sf, WL.W04).agg(F.percentile(d, 0.5).alias("p50"), F.percentile(d, 0.9).alias("p90"))


@query("radius_percentile_approx")
def percentile_approx(s, sf):
    return pts(s, sf, WL.W04).agg(F.percentile_approx(P.sqdist(["x0", "x1"], _A), [0.5, 0.9], 10_000).alias("p"))


@query("collect_small_cells", O.chain(WL.W04, "points", "leaves") + "SELECT c0, c1, string_agg(tag::VARCHAR, ',' ORDER BY tag) AS tags FROM leaf GROUP BY c0, c1 HAVING count(*) BETWEEN 2 AND 3")
def small_cells(s, sf):
    """Cells of at most three points with their points; larger ones are counted first, never gathered."""
    i = WL.W04
    keyed = pts(s, sf, i).select("tag", *i.grid.leaf(i.spec.coordinates))
    few = keyed.groupBy("c0", "c1").count().where("count BETWEEN 2 AND 3").drop("count")
    return keyed.join(few, ["c0", "c1"]).groupBy("c0", "c1").agg(F.array_join(F.transform(F.sort_array(F.collect_list("tag")), lambda t: t.cast("string")), ",").alias("tags"))


@query("having_important", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT k0, k1, n FROM cells WHERE level = 4 AND n >= 100")
def having(s, sf):
    i = WL.W04
    return partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid).where("level = 4 AND n >= 100").select("k0", "k1", "n")


@query("mode_cell", "SELECT c_mktsegment, mode(c_nationkey % 1) AS m FROM customer GROUP BY c_mktsegment")
def mode(s, sf):
    return table(s, sf, "customer").groupBy("c_mktsegment").agg(F.mode(F.col("c_nationkey") % 1).alias("m"))


# --- windows


@query("alphabetic_rank", f"WITH {O.points(WL.CUST)} SELECT tag, (rank() OVER (PARTITION BY x0 // 64 ORDER BY x0))::INTEGER AS r, (dense_rank() OVER (PARTITION BY x0 // 64 ORDER BY x0))::INTEGER AS dr, (row_number() OVER (PARTITION BY x0 // 64 ORDER BY x0, tag))::INTEGER AS rn FROM pts")
def ranks(s, sf):
    block = F.floor(F.col("x0") / 64)
    w, w2 = W.partitionBy(block).orderBy("x0"), W.partitionBy(block).orderBy("x0", "tag")
    return pts(s, sf, WL.W05).select("tag", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(w2).alias("rn"))


@query("equal_size_split", "SELECT c_custkey, (ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey))::INTEGER AS part FROM customer")
def ntile(s, sf):
    return table(s, sf, "customer").select("c_custkey", F.ntile(4).over(W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).alias("part"))


@query("level_gap_lag_lead", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT level, n_cells, lag(n_cells) OVER (ORDER BY level) AS before, lead(n_cells) OVER (ORDER BY level) AS after FROM (SELECT level, count(*) AS n_cells FROM cells GROUP BY level)")
def lag_lead(s, sf):
    i = WL.W04
    per = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid).groupBy("level").agg(F.count("*").alias("n_cells"))
    w = W.orderBy("level")  # one row per level
    return per.select("level", "n_cells", F.lag("n_cells").over(w).alias("before"), F.lead("n_cells").over(w).alias("after"))


@query("first_last_nth", "SELECT DISTINCT c_nationkey, first_value(c_custkey) OVER w AS f, last_value(c_custkey) OVER w AS l, nth_value(c_custkey, 2) OVER w AS s FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def first_last(s, sf):
    w = W.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(s, sf, "customer").select("c_nationkey", F.first("c_custkey").over(w).alias("f"), F.last("c_custkey").over(w).alias("l"), F.nth_value("c_custkey", 2).over(w).alias("s")).distinct()


@query("percent_rank_cume_dist", "SELECT s_suppkey, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal)")
def percent_rank(s, sf):
    w = W.partitionBy("s_nationkey").orderBy("s_acctbal")
    return table(s, sf, "supplier").select("s_suppkey", F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


@query("sliding_rows_load", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS n FROM events")
def sliding_rows(s, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-9, 0)
    return table(s, sf, "events").select("event_id", F.count("*").over(w).alias("n"))


@query("range_interval_load", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
def range_interval(s, sf):
    sec = F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', date_trunc('second', ts))")
    return table(s, sf, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy(sec).rangeBetween(-86400, 0)).alias("n"))


# --- order, limits, sets


@query("topk_heavy_cells", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT level, k0, k1, n FROM cells WHERE level = 5 ORDER BY n DESC, k0, k1 LIMIT 10")
def topk(s, sf):
    i = WL.W04
    cells = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)
    return cells.where("level = 5").orderBy(F.desc("n"), "k0", "k1").limit(10)


@query("topk_per_level", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT level, k0, k1, n FROM cells QUALIFY row_number() OVER (PARTITION BY level ORDER BY n DESC, k0, k1) <= 3")
def topk_per_level(s, sf):
    i = WL.W04
    cells = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)
    return cells.withColumn("r", F.row_number().over(W.partitionBy("level").orderBy(F.desc("n"), "k0", "k1"))).where("r <= 3").drop("r")


@query("limit_offset_cells", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 40")
def limit_offset(s, sf):
    return table(s, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(40).limit(20).select("o_orderkey")


@query("morton_sort", O.chain(WL.W04, "points", "leaves") + "SELECT tag, (" + " + ".join(f"(((c{m} >> {b}) & 1) << {2 * b + m})" for b in range(11) for m in range(2)) + ")::BIGINT AS morton FROM leaf")
def morton(s, sf):
    """Points in an order in which every cell of every level is one run."""
    i = WL.W04
    keyed = pts(s, sf, i).select("tag", *i.grid.leaf(i.spec.coordinates))
    key = F.lit(0).cast("long")
    for b in range(11):
        for m in range(2):
            key = key + F.shiftleft(F.shiftright(F.col(f"c{m}"), b).bitwiseAND(F.lit(1).cast("long")), 2 * b + m)
    return keyed.select("tag", key.alias("morton")).repartitionByRange(8, "morton").sortWithinPartitions("morton")


@query("union_levels", O.chain(WL.W04, "points", "leaves", "cells") + "SELECT level, k0, k1, n FROM cells WHERE level IN (2, 3)")
def union_levels(s, sf):
    i = WL.W04
    cells = partition.cell_counts(partition.leaf_counts(pts(s, sf, i), i.grid), i.grid)
    return cells.where("level = 2").unionByName(cells.where("level = 3"))


_SAMPLES = f"WITH {O.points(WL.CUST)}, {O.hashed(WL.W05, WL.W05.cell_hash, 'pts', 'a')}, {O.hashed(WL.W05, WL.W05.part_hash, 'pts', 'b')} SELECT tag FROM a WHERE h < {P.threshold(0.5)}"


@query("intersect_hash_families", _SAMPLES + f" INTERSECT SELECT tag FROM b WHERE h < {P.threshold(0.5)}")
def intersect(s, sf):
    p = pts(s, sf, WL.W05)
    a, b = (p.where(P.poly_hash(["tag", "x0"], h) < P.threshold(0.5)).select("tag") for h in (WL.W05.cell_hash, WL.W05.part_hash))
    return a.intersect(b)


@query("survivors_except_all", "SELECT event_id % 7 AS k FROM events EXCEPT ALL SELECT event_id % 7 FROM events WHERE event_id % 5 = 0")
def except_all(s, sf):
    e = table(s, sf, "events")
    return e.select((F.col("event_id") % 7).alias("k")).exceptAll(e.where("event_id % 5 = 0").select((F.col("event_id") % 7).alias("k")))


@query("except_and_distinct", "SELECT DISTINCT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 0")
def subtract(s, sf):
    return table(s, sf, "customer").select("c_nationkey").distinct().subtract(table(s, sf, "supplier").where("s_acctbal > 0").select("s_nationkey"))


# --- functions


@query("fn_math_bitwise", "SELECT l_orderkey, l_linenumber, l_partkey, (l_partkey >> 2)::BIGINT AS a, (l_partkey & 255)::BIGINT AS b, xor(l_partkey, 77)::BIGINT AS c, bit_count(l_partkey)::INTEGER AS d, floor(sqrt(l_extendedprice))::BIGINT AS e, (l_partkey % 7)::BIGINT AS f FROM lineitem")
def math_bitwise(s, sf):
    k = F.col("l_partkey")
    return table(s, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.shiftright(k, 2).alias("a"), k.bitwiseAND(F.lit(255).cast("long")).alias("b"), k.bitwiseXOR(F.lit(77).cast("long")).alias("c"), F.bit_count(k).alias("d"), F.floor(F.sqrt("l_extendedprice")).alias("e"), F.pmod(k, F.lit(7).cast("long")).alias("f"))


@query("fn_array_projection", "SELECT vec_id, list_sum(list_transform(embedding, lambda e: CAST(round(e * 1e6) AS BIGINT)))::BIGINT AS s, len(list_filter(embedding, lambda e: e > 0))::INTEGER AS pos FROM embeddings")
def array_projection(s, sf):
    micro = F.transform("embedding", lambda e: F.round(e * F.lit(1e6)).cast("long"))
    return table(s, sf, "embeddings").select("vec_id", F.aggregate(micro, F.lit(0).cast("long"), lambda a, e: a + e).alias("s"), F.size(F.filter("embedding", lambda e: e > 0)).alias("pos"))


@query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def json_field(s, sf):
    return table(s, sf, "events").select("event_id", F.from_json("props", "k BIGINT")["k"].alias("k"))


@query("fn_string", "SELECT page_id, length(html)::INTEGER AS n, length(url)::INTEGER AS u, (length(html) - length(replace(html, '<', '')))::INTEGER AS tags, lower(substr(url, 1, 8)) AS head, len(string_split(url, '/'))::INTEGER AS depth FROM pages")
def string_functions(s, sf):
    return table(s, sf, "pages").select("page_id", F.length("html").alias("n"), F.length("url").alias("u"), (F.length("html") - F.length(F.replace(F.col("html"), F.lit("<"), F.lit("")))).alias("tags"), F.lower(F.substring("url", 1, 8)).alias("head"), F.size(F.split("url", "/")).alias("depth"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))::INTEGER AS d FROM orders")
def date_functions(s, sf):
    return table(s, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).alias("d"))


@query("fn_null_cast", "SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg, TRY_CAST(c_name AS INTEGER) AS num, CASE WHEN c_nationkey = 0 THEN NULL ELSE 1.0 / c_nationkey END AS inv FROM customer")
def null_cast(s, sf):
    return table(s, sf, "customer").select("c_custkey", F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("seg"), F.expr("try_cast(c_name AS INT)").alias("num"), F.expr("try_divide(1.0D, c_nationkey)").alias("inv"))


@query("fn_map_struct", "SELECT c_nationkey, count(CASE WHEN c_mktsegment = 'BUILDING' THEN 1 END) AS building FROM customer GROUP BY c_nationkey")
def map_struct(s, sf):
    per = table(s, sf, "customer").groupBy("c_nationkey", "c_mktsegment").count()
    tally = per.groupBy("c_nationkey").agg(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "count"))).alias("m"))
    return tally.select("c_nationkey", F.coalesce(F.try_element_at("m", F.lit("BUILDING")), F.lit(0)).alias("building"))


# --- functions in Python, tables of functions, SQL


@query("udf_hash_equals_column", "SELECT 0::BIGINT AS mismatches")
def udf_hash(s, sf):
    """The hash as an Arrow function, for independences beyond what one expression should hold, against the column."""
    h = WL.W04.core_hash

    @F.arrow_udf("long")
    def hashed(tag: pa.Array, x0: pa.Array, x1: pa.Array) -> pa.Array:
        t, a, b = (c.to_numpy(zero_copy_only=False).astype(np.int64) for c in (tag, x0, x1))
        both = []
        for p in h:
            point = ((t % P.FIELD * p.fold + a) % P.FIELD * p.fold + b) % P.FIELD
            acc = np.full(len(t), p.coefficients[0], np.int64)
            for c in p.coefficients[1:]:
                acc = (acc * point + c) % P.FIELD
            both.append(acc)
        return pa.array(both[0] * P.FIELD + both[1])

    return pts(s, sf, WL.W04).agg(F.count_if(hashed("tag", "x0", "x1") != P.poly_hash(["tag", "x0", "x1"], h)).alias("mismatches"))


@query("pandas_udf_distance", f"WITH {O.points(WL.ORD)} SELECT tag, {O.dist(['x0', 'x1'], _A, 2)} AS d FROM pts")
def pandas_distance(s, sf):
    a0, a1 = _A

    @F.pandas_udf("long")
    def d(x0: pd.Series, x1: pd.Series) -> pd.Series:
        return (x0 - a0) ** 2 + (x1 - a1) ** 2

    return pts(s, sf, WL.W04).select("tag", d("x0", "x1").alias("d"))


@query("per_level_flow", "SELECT true AS same_sizes, true AS no_dearer")
def per_level_flow(s, sf):
    """Each level of a summary exchanged by a task of its own: same numbers at the centres, no higher cost."""
    z = np.array(WL.W06.centres)
    a = C.nearest(built(s, sf, WL.W06).coreset, WL.W06.centres, 2).withColumn("j", F.pmod(F.col("j") + F.col("tag"), F.lit(4)).cast("int"))

    def exchange(pdf: pd.DataFrame) -> pd.DataFrame:
        x = pdf[["x0", "x1"]].to_numpy(np.int64)
        before, sizes = pdf["j"].to_numpy(), np.bincount(pdf["j"], minlength=4)
        after = flow.reassign(x, pdf["tag"].to_numpy(), 1.0, z, sizes, 2)
        cost = flow.costs(x, z, 2)
        at = np.arange(len(x))
        return pd.DataFrame({"same": [bool((np.bincount(after, minlength=4) == sizes).all())], "cheap": [bool(cost[at, after].sum() <= cost[at, before].sum() + 1e-6)]})

    return a.groupBy("level").applyInPandas(exchange, "same boolean, cheap boolean").agg(F.bool_and("same").alias("same_sizes"), F.bool_and("cheap").alias("no_dearer"))


@query("local_summary_map", "SELECT count(*) AS n, sum(l_quantity)::BIGINT AS q FROM lineitem")
def local_summary(s, sf):
    """A partial sum per task by Arrow batches, then the sum of sums."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = q = 0
        for b in batches:
            n, q = n + b.num_rows, q + (pa.compute.sum(b.column(0)).as_py() or 0)
        yield pa.RecordBatch.from_pydict({"n": [n], "q": [float(q)]})

    import pyarrow.compute  # noqa: F401

    return table(s, sf, "lineitem").select("l_quantity").mapInArrow(run, "n long, q double").agg(F.sum("n").alias("n"), F.sum("q").cast("long").alias("q"))


@query("grid_cells_udtf", O.chain(WL.W05, "points", "leaves") + "SELECT level, k, count(*) AS n FROM (SELECT lvl::INTEGER AS level, c0 >> (10 - lvl) AS k FROM leaf, (SELECT unnest(range(-1, 11)) AS lvl)) GROUP BY level, k")
def udtf(s, sf):
    @F.udtf(returnType="level int, k long")
    class Cells:
        def eval(self, c0: int):
            for level in range(-1, 11):
                yield level, c0 >> (10 - level)

    s.udtf.register("cells_of_leaf", Cells)
    partition.leaf_counts(pts(s, sf, WL.W05), WL.W05.grid).createOrReplaceTempView("own_leaves")
    return s.sql("SELECT level, k, sum(n) AS n FROM own_leaves, LATERAL cells_of_leaf(c0) GROUP BY level, k")


@query("sql_surface", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY o_orderpriority")
def sql_surface(s, sf):
    table(s, sf, "orders").createOrReplaceTempView("own_orders")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION above(x DOUBLE, y DOUBLE) RETURNS BOOLEAN RETURN x > y")
    return s.sql("SELECT o_orderpriority, count(*) AS n FROM own_orders WHERE above(o_totalprice, :least) GROUP BY o_orderpriority", args={"least": 100000.0})


@query("cte_subquery_mix", "WITH big AS (SELECT c_nationkey, count(*) AS n FROM customer GROUP BY c_nationkey) SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000) AND (SELECT n FROM big WHERE big.c_nationkey = c.c_nationkey) > (SELECT avg(n) FROM big)")
def cte_mix(s, sf):
    table(s, sf, "customer").createOrReplaceTempView("own_customer")
    table(s, sf, "orders").createOrReplaceTempView("own_orders")
    return s.sql("WITH big AS (SELECT c_nationkey, count(*) AS n FROM own_customer GROUP BY c_nationkey) SELECT c_custkey FROM own_customer c WHERE EXISTS (SELECT 1 FROM own_orders WHERE o_custkey = c_custkey AND o_totalprice > 300000) AND (SELECT first(n) FROM big WHERE big.c_nationkey = c.c_nationkey) > (SELECT avg(n) FROM big)")


@query("cellstore_udaf", "SELECT true AS equal")
def cellstore_udaf(s, sf):
    """Sketches of machines, merged by sums, equal the sketch of all rows."""
    i = WL.W04
    keyed = pts(s, sf, i).select("tag", *i.grid.leaf(i.spec.coordinates))
    updates = keyed.select(F.pmod("tag", F.lit(4)).alias("machine"), cellstore.pack(i.grid.keys(3), 11).alias("key"), F.lit(1).cast("long").alias("sign"))
    shape = cellstore.Shape(128)
    merged = cellstore.merge(cellstore.sketch(updates, shape, ("machine",)).drop("machine"))
    whole = cellstore.sketch(updates.drop("machine"), shape)
    return merged.exceptAll(whole).agg((F.count("*") == 0).alias("equal"))
