"""Streams of insertions and deletions: sketches, exact survivors, windows.

The sketch's key space is its shape, so its state is of fixed size and needs no watermark. Stores that keep rows
use state that drops a key when its count comes to zero.
"""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from balclust.functions import points as P
from balclust.operators import cellstore, coreset, partition
from balclust.sources.store import shared_dir


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files; the table may be one file or a folder of them."""
    path = f"{sf_dir}/events.parquet"
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder = at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    return reader.parquet(path) if folder else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def instant(ts: Column) -> Column:
    """A time without zone as the instant it would be in UTC: watermarks want instants."""
    return F.timestamp_micros(F.timestamp_diff("MICROSECOND", F.lit("1970-01-01").cast("timestamp_ntz"), ts))


def naive(ts: Column) -> Column:
    """The way back."""
    return F.timestamp_add("MICROSECOND", F.unix_micros(ts), F.lit("1970-01-01").cast("timestamp_ntz"))


def signed(events: DataFrame, every: int = 5, upto: int = 1) -> DataFrame:
    """op (+1, -1), ts, event_id, value, sec: each event at its time, and a deletion a day later of those with event_id % every < upto."""
    gone = F.when(F.col("event_id") % every < upto, F.struct(F.lit(-1).cast("tinyint").alias("op"), (F.col("ts") + F.expr("INTERVAL 24 HOURS")).alias("at")))
    came = F.struct(F.lit(1).cast("tinyint").alias("op"), F.col("ts").alias("at"))
    both = F.filter(F.array(came, gone), lambda e: e.isNotNull())
    one = events.select("event_id", "value", "ts", F.explode(both).alias("e"))
    return one.select("e.op", F.col("e.at").alias("ts"), "event_id", "value", F.expr("hour(ts) * 3600 + minute(ts) * 60 + cast(second(ts) as int)").alias("sec"))


def lattice_updates(updates: DataFrame, spec: P.PointSpec) -> DataFrame:
    """op, tag, x0.. of signed events."""
    values = ["value", "sec"]
    return updates.select("op", F.col("event_id").cast("long").alias("tag"), *(P.lattice(F.col(v), m.low, m.high, spec.levels).alias(x) for v, m, x in zip(values, spec.dimensions, spec.coordinates, strict=True)))


def cell_updates(updates: DataFrame, grid: P.Grid, level: int, rate: int = P.RANGE, h: P.Hash | None = None) -> DataFrame:
    """key, sign of the cells of one level; with a hash only points below the rate."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    if h is not None and rate < P.RANGE:
        updates = updates.where(P.poly_hash(["tag", *coordinates], h) < rate)
    keyed = updates.select("op", *grid.leaf(coordinates))
    return keyed.select(cellstore.pack(grid.keys(level), grid.levels + 1).alias("key"), F.col("op").cast("long").alias("sign"))


def family_updates(updates: DataFrame, grid: P.Grid, cuts: dict[tuple[str, int], int], hashes: dict[str, P.Hash]) -> DataFrame:
    """family, level, key, sign: each update once for each family and level whose threshold its hash is below. One sketch serves all of them."""
    coordinates = [f"x{m}" for m in range(grid.d)]
    keyed = updates.select("op", *grid.leaf(coordinates), *(P.poly_hash(["tag", *coordinates], h).alias(f"h_{name}") for name, h in hashes.items()))
    hits = F.array(*(F.when(F.col(f"h_{family}") < cut, F.struct(F.lit(family).alias("family"), F.lit(level).alias("level"), cellstore.pack(grid.keys(level), grid.levels + 1).alias("key"))) for (family, level), cut in cuts.items()))
    return keyed.select(F.col("op").cast("long").alias("sign"), F.explode(F.filter(hits, lambda x: x.isNotNull())).alias("u")).select("u.family", "u.level", "u.key", "sign")


def guess_cuts(params, exponents: range) -> dict[int, dict[int, int]]:
    """guess_log2: threshold of each level's sample, rates rounded up to powers of two, so that guesses of one rate share a sketch."""
    out = {}
    for e in exponents:
        own = params._replace(guess=float(2**e))
        out[e] = {i: P.threshold(2.0 ** math.ceil(math.log2(own.rate(i)))) for i in range(params.levels + 1)}
    return out


def rate_updates(updates: DataFrame, grid: P.Grid, cuts: dict[int, dict[int, int]], h: P.Hash, levels: range) -> DataFrame:
    """level, cut, key, sign for all guesses together: one row for each level and distinct threshold that an update's hash is below."""
    return family_updates(updates, grid, {(str(cut), i): cut for i in levels for cut in {c[i] for c in cuts.values()}}, {str(cut): h for c in cuts.values() for cut in c.values()})


def run(stream: DataFrame, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """All that a bounded stream gives, by way of a table in memory: for results whose size is a parameter's."""
    name = f"t{uuid.uuid4().hex}"
    stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint or f"{shared_dir(stream.sparkSession)}/stream-{name}").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


def run_batches(stream: DataFrame, mode: str = "update") -> DataFrame:
    """All rows that a bounded stream emits in any mode, each micro-batch written to files: for results that grow with the input."""
    spark, path = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/batches-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path).select(*stream.columns)


def run_complete(stream: DataFrame) -> DataFrame:
    """What a bounded stream's complete mode holds at its end, written to files by the tasks: each micro-batch's result takes the place of the one before."""
    spark, path = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/complete-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(path)

    stream.writeStream.outputMode("complete").foreachBatch(put).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def run_to_files(stream: DataFrame) -> DataFrame:
    """All that a bounded stream appends, by way of files in the shared folder."""
    spark, path = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", f"{path}-log").option("path", path).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


#: Groups that points are dealt to by a hash. The state of one is the packed points in it that live: counts are added up for a group at once, not for each point.
GROUPS = 1024


def _dealt(updates: DataFrame, names: list[str]) -> DataFrame:
    return updates.select("op", *names, F.pmod(F.xxhash64(*names), F.lit(GROUPS)).cast("int").alias("dealt"))


def settled(held: bytes | None, batches: Iterator[pd.DataFrame], names: list[str]) -> tuple[bytes, pd.DataFrame]:
    """(the points of a group that live, packed as rows of whole numbers with the count last; the count of each point that the batches name, zero where it went)."""
    new = [b.groupby(names, sort=False)["op"].sum().reset_index(name="n").astype("int64") for b in batches]
    old = pd.DataFrame(np.frombuffer(held or b"", np.int64).reshape(-1, len(names) + 1), columns=[*names, "n"])
    named = pd.concat(new).groupby(names, sort=False)["n"].sum().reset_index() if new else old.iloc[:0]
    both = pd.concat([old.assign(new=False), named.assign(new=True)]).groupby(names, sort=False).agg(n=("n", "sum"), new=("new", "max")).reset_index()
    return both.loc[both["n"] != 0, [*names, "n"]].to_numpy(np.int64).tobytes(), both.loc[both["new"], [*names, "n"]]


def survivors(updates: DataFrame, schema: str = "tag long, x0 long, x1 long") -> DataFrame:
    """The points that a stream of updates leaves, by state that drops a point whose count is zero. updates: op, tag, x0, x1."""
    names = [f.split()[0] for f in schema.split(", ")]

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held, changed = settled(state.get[0] if state.exists else None, batches, names)
        if held:
            state.update((held,))
        elif state.exists:
            state.remove()
        yield changed

    return _dealt(updates, names).groupBy("dealt").applyInPandasWithState(step, f"{schema}, n long", "held binary", "update", GroupStateTimeout.NoTimeout)


def counted(updates: DataFrame) -> DataFrame:
    """tag, x0, x1, n of each changed point, by a state processor from whose value a point goes when its count is zero."""
    from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

    names = ["tag", "x0", "x1"]

    class Counter(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.held = handle.getValueState("held", "held binary")

        def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802,N803  (the engine's names)
            before = self.held.get()[0] if self.held.exists() else None
            held, changed = settled(None if before is None else bytes(before), rows, names)
            if held:
                self.held.update((held,))
            elif before is not None:
                self.held.clear()
            yield changed

        def close(self) -> None:
            pass

    return _dealt(updates, names).groupBy("dealt").transformWithStateInPandas(Counter(), "tag long, x0 long, x1 long, n long", "Update", "None")


#: Bits of a tag in a stored point.
TAG_BITS = 32


def point_key(grid: P.Grid) -> Column:
    """One 62-bit number of a tagged point: tag, then coordinates. A tag beyond TAG_BITS ends the query."""
    key = cellstore.pack([F.col("tag"), *(F.col(f"x{m}") for m in range(grid.d))], grid.levels + 1)
    return F.when(F.col("tag").between(0, (1 << TAG_BITS) - 1), key).otherwise(F.raise_error(F.lit("a tag does not fit into a key of the sketch")).cast("long"))


def sketch_cuts(params) -> dict[tuple[str, int], int]:
    """Threshold of each family and level: sizes of cells (levels from -1), sizes of parts, and points of the summary."""
    cells = {("cells", i): P.threshold(params.size_rates(i)[0]) for i in range(-1, params.levels + 1)}
    parts = {("parts", i): P.threshold(params.size_rates(i)[1]) for i in range(params.levels + 1)}
    return cells | parts | {("points", i): cut for i, cut in coreset.rates(params).items()}


def summary_updates(updates: DataFrame, grid: P.Grid, params, hashes: dict[str, P.Hash]) -> DataFrame:
    """family, level, key, sign of all three families at all levels; an update that no threshold takes has no row.

    The cells of a level are kept by their keys. For parts and for the summary's points the sampled points themselves are kept, since which
    part a point is in is known only at the end of the stream. Levels of one family and threshold share the rows of the first of them.
    """
    coordinates = [f"x{m}" for m in range(grid.d)]
    if grid.d * (grid.levels + 1) + TAG_BITS > 62:
        raise ValueError("a tagged point does not fit into a key of the sketch")
    cuts = sketch_cuts(params)
    keyed = updates.select("op", "tag", *coordinates, *grid.leaf(coordinates), *(P.poly_hash(["tag", *coordinates], h).alias(f"h_{name}") for name, h in hashes.items()))
    taken, seen = [], set()
    for (family, level), cut in cuts.items():
        if family != "cells" and (family, cut) in seen:
            continue
        seen.add((family, cut))
        key = cellstore.pack(grid.keys(level), grid.levels + 2) if family == "cells" else point_key(grid)
        taken.append(F.when(F.col(f"h_{family}") < cut, F.struct(F.lit(family).alias("family"), F.lit(level).alias("level"), key.alias("key"))))
    each = keyed.select(F.col("op").cast("long").alias("sign"), F.explode(F.filter(F.array(*taken), lambda x: x.isNotNull())).alias("u"))
    return each.select("u.family", "u.level", "u.key", "sign")


#: Keys of one family and level that a share of its sketches is meant for: half of what a sketch of 40,000 has room for.
SHARE = 20_000


def shares(params, grid: P.Grid, most: int, per: int = SHARE) -> dict[tuple[str, int], int]:
    """Sketches that the keys of each family and level are dealt to, from how many points may be met at most: about per keys in each."""
    out = {}
    for (family, level), cut in sketch_cuts(params).items():
        keys = most * cut / P.RANGE
        if family == "cells":
            keys = min(keys, ((1 << (level + 1)) + 1) ** grid.d)
        out[family, level] = max(1, math.ceil(keys / per))
    return out


def run_sketches(updates: DataFrame, shape: cellstore.Shape, dealt: dict[tuple[str, int], int]) -> DataFrame:
    """family, level, share, rep, bucket and sums over a bounded stream of summary_updates: the keys of each family and level are dealt to so many sketches.

    Each micro-batch adds up its signs by key, then its sketches, to files. What is kept between batches is the sketches, not the keys.
    """
    spark, path = updates.sparkSession, f"{shared_dir(updates.sparkSession)}/sums-{uuid.uuid4().hex}"
    by = ("family", "level", "share", "rep", "bucket")
    number = F.lit(1)
    for (family, level), n in dealt.items():
        number = F.when((F.col("family") == family) & (F.col("level") == level), n).otherwise(number) if n > 1 else number

    def put(batch: DataFrame, k: int) -> None:
        left = batch.groupBy("family", "level", "key").agg(F.sum("sign").alias("sign")).where("sign != 0")
        shared = left.withColumn("share", F.pmod(F.xxhash64("key"), number).cast("int"))
        cellstore.routed(shared, shape).groupBy(*by).agg(*(F.sum(c).alias(c) for c in cellstore.SUMS)).write.mode("overwrite").parquet(f"{path}/batch={k}")

    updates.writeStream.foreachBatch(put).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(path).groupBy(*by).agg(*(F.sum(c).alias(c) for c in cellstore.SUMS))


def sketched_summary(spark: SparkSession, sketches: DataFrame, grid: P.Grid, params, shape: cellstore.Shape) -> coreset.Summary | None:
    """The summary from decoded sketches of summary_updates alone: no survivor is kept. None where a sketch that is needed fails.

    sketches: family, level, rep, bucket and sums, and share where keys are dealt to several; each has the shape's number of rows at most and is
    decoded in a task. The driver gets the cells that pass their threshold.
    """
    cuts, path = sketch_cuts(params), f"{shared_dir(spark)}/decoded-{uuid.uuid4().hex}"
    by = tuple(c for c in ("family", "level", "share") if c in sketches.columns)
    tables = cellstore.decoded_tables(sketches, shape, by, ("family", "level"))
    tables.write.partitionBy("family", "level").parquet(path)
    found = spark.read.schema(tables.schema).parquet(path)
    failed = {(r["family"], r["level"]) for r in found.where("key IS NULL").select("family", "level").distinct().collect()}
    first: dict[tuple[str, int], int] = {}
    for (family, level), cut in cuts.items():
        first.setdefault((family, cut), level)

    limit, bits = partition.thresholds(params), grid.levels + 2
    scale = {level: P.RANGE / cuts["cells", level] for level in range(-1, params.levels + 1)}
    large = found.where((F.col("family") == "cells") & F.col("key").isNotNull() & (F.col("level") < params.levels)).where(F.col("n") * partition.by_level("level", scale) >= partition.by_level("level", limit))
    passed: dict[int, list] = {}
    for r in large.collect():  # no more than the guess's bound on heavy cells and those inside no heavy one
        passed.setdefault(r["level"], []).append((cellstore.unpack(r["key"], grid.d, bits), r["n"]))
    parents, heavy = None, []
    for level in range(-1, params.levels):
        if ("cells", level) in failed:
            return None
        own = [(place, n) for place, n in passed.get(level, []) if parents is None or tuple(k >> 1 for k in place) in parents]
        heavy += [(level, *place, float(n * scale[level])) for place, n in own]
        parents = {place for place, _ in own}
        if not own:
            break
    names = ["tag", *(f"x{m}" for m in range(grid.d))]
    key, wide = ["level", *(f"p{m}" for m in range(grid.d))], grid.levels + 1

    def routed(family: str) -> list[tuple[list[int], DataFrame]] | None:
        """The sampled points of each threshold with their parts, at the levels of that threshold."""
        levels: dict[int, list[int]] = {}
        for level in sorted({h[0] + 1 for h in heavy}):
            levels.setdefault(first[family, cuts[family, level]], []).append(level)
        if any((family, k) in failed for k in levels):
            return None
        out = []
        for k, own in levels.items():
            held = found.where((F.col("family") == family) & (F.col("level") == k))
            lanes = [F.expr(f"shiftright(key, {wide * (grid.d - m)})").alias(names[m]) if m == 0 else F.expr(f"shiftright(key, {wide * (grid.d - m)}) & {(1 << wide) - 1}").alias(names[m]) for m in range(grid.d + 1)]
            out.append((own, partition.route(held.select(*lanes), cell_rows, grid).where(F.col("level").isin(own))))
        return out

    cells = spark.createDataFrame(heavy, f"level int, {', '.join(f'{k} long' for k in grid.key_names)}, n double")
    cell_rows = cells.collect()
    parts, core = routed("parts"), routed("points")
    if parts is None or core is None:
        return None
    if not heavy:
        none = spark.createDataFrame([], ", ".join([*(f"{n} long" for n in names), "level int", *(f"{p} long" for p in key[1:]), "w double"]))
        return coreset.Summary(params, grid, cells, partition.parts_of_cells(cells, grid), none)
    each = {level: P.RANGE / cuts["parts", level] for level in range(params.levels + 1)}
    weight = {i: P.RANGE / cut for i, cut in coreset.rates(params).items()}
    sizes, sampled = None, None
    for _, df in parts:
        one = df.groupBy(*key).agg(F.count("*").alias("size")).select(*key, (F.col("size") * partition.by_level("level", each)).alias("size"))
        sizes = one if sizes is None else sizes.unionByName(one)
    for _, df in core:
        one = df.select(*names, *key, partition.by_level("level", weight).alias("w"))
        sampled = one if sampled is None else sampled.unionByName(one)
    some = coreset.important_parts(sizes, params)
    return coreset.Summary(params, grid, cells, sizes, sampled.join(F.broadcast(some.drop("size")), key).select(*names, *key, "w"))
