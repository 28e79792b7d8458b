"""Best-fit packing by the configuration linear program over the length histogram.

Pieces matter by their length alone, and there are at most LIMIT lengths, so the program has at most LIMIT
rows however many pieces there are. It is solved by multiplicative weights: each round prices all
lengths by a knapsack dynamic program, takes whole sequences of the most valuable fillings (configurations) through each length, and the prices
of what they cover fall. What the program leaves once its rounds place little goes by best fit, longest first; of the places where best
fit could take over the one with fewest sequences counts, its start among them, so that the plan is never longer than best fit's own.
Only the histogram and the table of places by length
(at most as many rows as there are configurations times their lengths, not as there are pieces) pass the driver.

A piece's place follows from its rank among the pieces of its length; ranks are taken in buckets, so
that no length lies in one task.

Defined cases: a null text is empty, one end token; repeated rows are pieces of their own; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import itertools
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from . import common, tokens

LIMIT, END = 4096, 1
#: Buckets in which the pieces of a length are ranked.
BUCKETS = 256
#: The share of a size's count that a round covers, how fast prices fall with it, the bends of the starting prices that are tried, the share of
#: pieces under which a round has placed little, the most room to spare of a round's configurations, how often
#: one of them takes another size for one that is used up, and at how many places best fit is tried for the rest.
STEP, FALL, BENDS, SLOW, SPARE, SWAPS, CUTS = 0.25, 0.2, (0.0, 0.5), 0.02, 64, 2, 8
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Plan(NamedTuple):
    """Places for the pieces of each length, by rank: those of ranks from first on lie in sequences from sequence on, one each, at offset."""

    length: np.ndarray
    first: np.ndarray
    sequence: np.ndarray
    offset: np.ndarray
    sequences: int


def price(values: np.ndarray, sizes: np.ndarray, most: np.ndarray, room: int) -> np.ndarray:
    """How many of each size make the most valuable set within the room, no more than most of each: a knapsack dynamic program.

    values, sizes, most: of the items offered. Copies are offered in powers of two, so that a bounded number of each is an ordinary item.
    """
    item, times = [], []
    for k, (s, m) in enumerate(zip(sizes.tolist(), np.minimum(most, room // sizes).tolist(), strict=True)):
        t = 1
        while m > 0:
            t = min(t, m)
            item.append(k)
            times.append(t)
            m, t = m - t, t * 2
    best = np.zeros(room + 1)
    chosen = np.zeros((len(item), room + 1), bool)
    for row, (k, t) in enumerate(zip(item, times, strict=True)):
        weight, gain = int(sizes[k]) * t, values[k] * t
        other = best[: room + 1 - weight] + gain
        better = other > best[weight:]
        chosen[row, weight:] = better
        best[weight:] = np.where(better, other, best[weight:])
    count, at = np.zeros(len(sizes), np.int64), int(np.argmax(best))
    for row in range(len(item) - 1, -1, -1):
        if chosen[row, at]:
            count[item[row]] += times[row]
            at -= int(sizes[item[row]]) * times[row]
    return count


def table(values: np.ndarray, sizes: np.ndarray, room: int) -> tuple[np.ndarray, np.ndarray]:
    """The unbounded knapsack over all sizes (ascending, distinct): best[c] is the most value that fits c, pick[c] one size of such a set, the largest of ties (-1: none that c - 1 has not)."""
    low, high = int(sizes[0]), int(sizes[-1])
    best, pick = np.zeros(room + 1), np.full(room + 1, -1)
    down, place = np.full(high + 1, -np.inf), np.full(high + 1, -1)
    down[high - sizes], place[sizes] = values, np.arange(len(sizes))
    for c in range(low, room + 1):
        top = min(high, c)
        found = down[high - top : high - low + 1] + best[c - top : c - low + 1]
        j = int(found.argmax())
        best[c] = best[c - 1]
        if found[j] > best[c] + 1e-12:
            best[c], pick[c] = found[j], place[top - j]
    return best, pick


def _start(sizes: np.ndarray, room: int, bend: float) -> np.ndarray:
    """Logarithms of the starting prices: the share of the room (bent, so that a token of a large size is dearer), plus one for sizes of which no two fit together."""
    return np.logaddexp((1 + bend) * np.log(sizes / room), np.where(2 * sizes > room, 0.0, -np.inf))


def _rounds(sizes: np.ndarray, counts: np.ndarray, room: int, bend: float = 0.0, whole: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray, int]]:
    """Configurations as (places of sizes, how many of each, how many sequences) that cover the counts, no size more often than it occurs. sizes: ascending.

    Multiplicative weights on the covering rows: the price of a size falls exponentially with the share of its count covered so far.
    Each round prices all sizes that are left by one knapsack table, and takes from it the best configuration through each
    size, the largest first: whole sequences up to STEP of that size's count. Configurations with more room to spare than the round allows wait; a round that
    places little makes the next one twice as lenient. Beyond SPARE the others are priced one at a time by the bounded knapsack until all is covered (whole), or left.
    """
    left, start, spare = counts.astype(np.int64).copy(), _start(sizes, room, bend), 0
    while left.any() and spare <= SPARE:
        some = np.flatnonzero(left)
        size, total, had = sizes[some], counts[some].tolist(), int(left.sum())
        logs = start[some] - FALL * (1 - left[some] / counts[some])
        value = np.exp(logs - logs.max())
        best, picks = table(value, size, room)
        now, pick, wide = left[some], picks.tolist(), size.tolist()
        have = now.tolist()
        for a in range(len(some) - 1, -1, -1):
            if not have[a]:
                continue
            used, rest, swaps = {a: 1}, room - wide[a], 0
            while rest > 0:
                at = pick[rest]
                if at < 0:
                    rest -= 1
                    continue
                if have[at] <= used.get(at, 0):  # used up: the best of the others, SWAPS times; then the size waits for a round with new prices
                    swaps += 1
                    if swaps > SWAPS:
                        break
                    free = now[: np.searchsorted(size, rest, "right")] > 0
                    free[[j for j, e in used.items() if j < len(free) and have[j] <= e]] = False
                    free = np.flatnonzero(free)[::-1]
                    if not len(free):
                        break
                    at = int(free[(value[free] + best[rest - size[free]]).argmax()])
                used[at] = used.get(at, 0) + 1
                rest -= wide[at]
            if room - sum(wide[j] * e for j, e in used.items()) > spare:
                continue
            n = min(min(have[j] // e for j, e in used.items()), max(1, -int(-total[a] * STEP // 1) // used[a]))
            for j, e in used.items():
                have[j] -= n * e
                now[j] = have[j]
            yield some[list(used)], np.array(list(used.values())), n
        left[some] = now
        if had - int(left.sum()) < SLOW * had:
            spare = max(1, 2 * spare)
    while whole and left.any():
        some = np.flatnonzero(left)
        logs = start[some] - FALL * (1 - left[some] / counts[some])
        each = price(np.exp(logs - logs.max()), sizes[some], left[some], room)
        some, each = some[each > 0], each[each > 0]
        n = int(np.min(left[some] // each))
        left[some] -= n * each
        yield some, each, n


def solve(sizes: np.ndarray, counts: np.ndarray, room: int, rounds: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The configurations of all rounds (or so many at most) as rows of a matrix, and their amounts."""
    found = list(itertools.islice(_rounds(sizes, counts, room), rounds))
    configs = np.zeros((len(found), len(sizes)), np.int64)
    for row, (used, each, _) in enumerate(found):
        configs[row, used] = each
    return configs, np.array([n for _, _, n in found], np.int64)


def _best_fit(sizes: np.ndarray, counts: np.ndarray, room: int) -> Iterator[tuple[int, list[tuple[int, int]]]]:
    """(how many sequences, [(size index, how many of it)]) by best fit, longest first, many like pieces at a time."""
    classes: dict[int, list[tuple[int, tuple]]] = {}
    for k in np.argsort(-sizes).tolist():
        size, left = int(sizes[k]), int(counts[k])
        while left:
            free = min((r for r in classes if r >= size), default=None)
            if free is None:
                each = min(room // size, left)
                full, rest = divmod(left, each)
                classes.setdefault(room - each * size, []).append((full, ((k, each),)))
                if rest:
                    classes.setdefault(room - rest * size, []).append((1, ((k, rest),)))
                break
            n, held = classes[free].pop()
            if not classes[free]:
                del classes[free]
            each = min(free // size, left)
            full = min(n, left // each)
            classes.setdefault(free - each * size, []).append((full, (*held, (k, each))))
            if n > full:
                classes.setdefault(free, []).append((n - full, held))
            left -= full * each
    for group in classes.values():
        for n, held in group:
            yield n, list(held)


def _hand_over(sizes: np.ndarray, counts: np.ndarray, room: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """The shortest plan that keeps the program's first configurations and leaves what is left to best fit; of ties the one with most configurations.

    The program runs once for each way to bend its starting prices. Looked at are all of its configurations, none, and CUTS - 1 places between; so no plan is longer than best fit's own.
    """
    least, chosen = None, (0, [])
    for found in (list(_rounds(sizes, counts, room, bend, whole=False)) for bend in BENDS):
        left, done, need = counts.copy(), 0, 0
        for k in sorted({round(len(found) * cut / CUTS) for cut in range(CUTS + 1)}):
            for used, each, n in found[done:k]:
                left[used] -= n * each
                need += n
            done = k
            now = (need + sum(n for n, _ in _best_fit(sizes, left, room)), -k)
            if least is None or now < least:
                least, chosen = now, (k, found, left.copy())
    k, found, left = chosen
    return [(n, list(zip(used.tolist(), each.tolist(), strict=True))) for used, each, n in found[:k]] + list(_best_fit(sizes, left, room))


def plan(sizes: np.ndarray, counts: np.ndarray, room: int = LIMIT) -> Plan:
    """Where the pieces of each length go. sizes: distinct lengths up to room; counts: how many of each."""
    order = np.argsort(sizes)
    sizes, left = sizes[order].astype(np.int64), counts[order].astype(np.int64)
    patterns: list[tuple[int, list[tuple[int, int]]]] = []
    for k in np.flatnonzero(sizes >= room).tolist():  # such a piece fills a sequence
        patterns.append((int(left[k]), [(k, 1)]))
        left[k] = 0
    some = np.flatnonzero(left)
    if len(some):
        patterns += [(n, [(int(some[u]), each) for u, each in held]) for n, held in _hand_over(sizes[some], left[some], room)]
    rank = np.zeros(len(sizes), np.int64)
    rows, sequence = [], 0
    for n, held in patterns:
        if not n:
            continue
        at = 0
        for k, each in held:
            for _ in range(each):
                rows.append((int(sizes[k]), int(rank[k]), sequence, at))
                rank[k] += n
                at += int(sizes[k])
        sequence += n
    rows.sort()
    table = np.array(rows, np.int64).reshape(-1, 4)
    return Plan(*table.T, sequence)


def _pieces(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = tokens.Encoder(path)
        for part in common.slices(batches, "text"):
            ids, where = encoder.encode(*common.text_bytes(common.column(part, "text")))
            end, rows = np.array([END], "<u4"), []
            for key, a, b in zip(common.column(part, "doc_id").to_pylist(), where[:-1].tolist(), where[1:].tolist(), strict=True):
                own = np.append(ids[a:b].astype("<u4"), end)
                for piece, start in enumerate(range(0, len(own), LIMIT)):
                    cut = own[start : start + LIMIT]
                    rows.append((key, piece, start, len(cut), zlib.crc32(cut.tobytes())))
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def pieces(docs: DataFrame, path: str | None = None) -> DataFrame:
    """Each text's ids and the end token, cut every LIMIT: doc_id, piece, start, length, ids_crc32."""
    return docs.select("doc_id", "text").mapInArrow(_pieces(path or tokens.vocabulary()), PIECES)


def _place(table: Plan):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Ranks and lengths as one ascending key: lengths are at most LIMIT, ranks below 2^50.
        keys = (table.length << 50) + table.first
        for b in batches:
            if not b.num_rows:
                continue
            length, rank = (common.column(b, c).to_numpy() for c in ("length", "rank"))
            at = np.searchsorted(keys, (length << 50) + rank, "right") - 1
            kept = [common.column(b, c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(table.sequence[at] + rank - table.first[at]), pa.array(table.offset[at])], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return run


def pack(cut: DataFrame) -> DataFrame:
    """cut (as pieces gives) with sequence_id and offset of each piece."""
    cut = common.stage(cut.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(BUCKETS)).cast("int")))
    buckets = cut.groupBy("length", "bucket").agg(F.count("*").alias("n"))
    histogram = buckets.groupBy("length").agg(F.sum("n").alias("n")).toPandas()  # at most LIMIT rows
    table = plan(histogram["length"].to_numpy(np.int64), histogram["n"].to_numpy(np.int64))
    before = W.partitionBy("length").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    base = buckets.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    inside = W.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")
    ranked = cut.withColumn("rank", F.row_number().over(inside).cast("long") - 1).join(base, ["length", "bucket"]).withColumn("rank", F.col("rank") + F.col("base"))
    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(_place(table), f"{PIECES}, sequence_id long, offset long")


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(pieces(common.documents(spark, sf_dir)))
