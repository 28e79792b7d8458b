"""A linear sketch of the non-empty cells of a level, and its decoding.

The sketch is a table of fixed size: for each repetition and bucket the sums of signs, of signed 16-bit lanes of the key, and of
signed fingerprints. Insertions and deletions in any order and on any machine add up to the same table. Decoding
peels buckets that hold one key; it gives all cells or says that it failed, never a part of them.
"""

from __future__ import annotations

import random
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from balclust.functions.points import FIELD

LANES = 4


class Shape(NamedTuple):
    """Parameters of a sketch for up to capacity keys."""

    capacity: int
    repetitions: int = 3
    seed: int = 1

    @property
    def buckets(self) -> int:
        return 2 * self.capacity + 1

    @property
    def rows(self) -> int:
        return self.buckets * self.repetitions

    @property
    def bits(self) -> int:
        return self.rows * 64 * (2 + LANES)

    def numbers(self, what: str, n: int) -> list[int]:
        rng = random.Random(f"{what} {self.seed}")
        return [rng.randrange(1, FIELD) for _ in range(n)]


def pack(keys: list[Column], bits: int) -> Column:
    """One 62-bit number of a cell's coordinates."""
    out = F.lit(0).cast("long")
    for k in keys:
        out = out * F.lit(1 << bits) + k.cast("long")
    return out


def unpack(key: int, d: int, bits: int) -> tuple[int, ...]:
    return tuple(key >> (bits * (d - 1 - m)) & ((1 << bits) - 1) for m in range(d))


#: Bits of a key that are one digit of its fold.
LOW = (1 << 30) - 1


def folded(key, fold: int):
    """A whole key, or an array of them, as one element of the field."""
    return (((key >> 60) * fold + (key >> 30 & LOW)) % FIELD * fold + (key & LOW)) % FIELD


def _poly(key: Column, numbers: list[int]) -> Column:
    """A polynomial of the key folded into the field. Each hash has a fold of its own (the last number): keys that one of them merges are told apart by the others."""
    *coefficients, fold = numbers
    high = (F.shiftright(key, 60) * F.lit(fold) + F.shiftright(key, 30).bitwiseAND(F.lit(LOW))) % F.lit(FIELD)
    low = (high * F.lit(fold) + key.bitwiseAND(F.lit(LOW))) % F.lit(FIELD)
    acc = F.lit(coefficients[0]).cast("long")
    for c in coefficients[1:]:
        acc = (acc * low + F.lit(c)) % F.lit(FIELD)
    return acc


def routed(updates: DataFrame, shape: Shape, key: str = "key", sign: str = "sign") -> DataFrame:
    """updates with a row for each repetition: rep, bucket, and what is summed. Other columns stay."""
    buckets = F.array(*(_poly(F.col(key), shape.numbers(f"bucket {rep}", 5)) % F.lit(shape.buckets) for rep in range(shape.repetitions)))
    lanes = [(F.col(sign) * (F.shiftright(F.col(key), 16 * q).bitwiseAND(F.lit(0xFFFF)))).alias(f"lane{q}") for q in range(LANES)]
    mark = (F.col(sign) * _poly(F.col(key), shape.numbers("mark", 5))).alias("mark")
    other = [c for c in updates.columns if c not in (key, sign)]
    return updates.select(*other, F.col(sign).cast("long").alias("n"), *lanes, mark, F.posexplode(buckets).alias("rep", "bucket"))


SUMS = ["n", *(f"lane{q}" for q in range(LANES)), "mark"]


def sketch(updates: DataFrame, shape: Shape, by: tuple[str, ...] = ()) -> DataFrame:
    """by.., rep, bucket, sums of signed updates (key long, sign). At most shape.rows rows for each value of by."""
    return routed(updates, shape).groupBy(*by, "rep", "bucket").agg(*(F.sum(c).alias(c) for c in SUMS))


def merge(sketches: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """The sum of sketches: that of all their updates together."""
    return sketches.groupBy(*by, "rep", "bucket").agg(*(F.sum(c).alias(c) for c in SUMS))


def decode(rows: list, shape: Shape) -> dict[int, int] | None:
    """Count by key of a sketch's rows (their number is the shape's), or None where it fails."""
    table: dict[tuple[int, int], list[int]] = {(r["rep"], r["bucket"]): [int(r[c]) for c in SUMS] for r in rows}
    bucket_of = [shape.numbers(f"bucket {rep}", 5) for rep in range(shape.repetitions)]
    mark_of = shape.numbers("mark", 5)

    def poly(key: int, numbers: list[int]) -> int:
        *coefficients, fold = numbers
        acc, low = coefficients[0], folded(key, fold)
        for c in coefficients[1:]:
            acc = (acc * low + c) % FIELD
        return acc

    def single(held: list[int]) -> int | None:
        n = held[0]
        if n == 0 or any(v % n for v in held[1 : 1 + LANES]):
            return None
        lanes = [v // n for v in held[1 : 1 + LANES]]
        if any(not 0 <= v <= 0xFFFF for v in lanes):
            return None
        key = sum(v << (16 * q) for q, v in enumerate(lanes))
        return key if poly(key, mark_of) * n == held[-1] else None

    out: dict[int, int] = {}
    waiting = list(table)
    while waiting:
        place = waiting.pop()
        key = single(table[place])
        if key is None or poly(key, bucket_of[place[0]]) % shape.buckets != place[1]:
            continue
        n = table[place][0]
        out[key] = out.get(key, 0) + n
        change = [n, *(n * (key >> (16 * q) & 0xFFFF) for q in range(LANES)), n * poly(key, mark_of)]
        for rep, coefficients in enumerate(bucket_of):
            other = (rep, poly(key, coefficients) % shape.buckets)
            held = table.get(other)
            if held is None:
                return None
            for k, c in enumerate(change):
                held[k] -= c
            waiting.append(other)
    if any(v for held in table.values() for v in held) or any(n < 0 for n in out.values()):
        return None
    return {k: n for k, n in out.items() if n}


def decoded(spark, rows: list, shape: Shape, d: int, bits: int) -> DataFrame | None:
    """k0.., n of a sketch, or None where it fails."""
    found = decode(rows, shape)
    if found is None:
        return None
    keys = np.array([unpack(k, d, bits) for k in found], np.int64).reshape(-1, d)
    import pandas as pd

    return spark.createDataFrame(pd.DataFrame({**{f"k{m}": keys[:, m] for m in range(d)}, "n": np.array(list(found.values()), np.int64)}))


def peel(table: np.ndarray, shape: Shape) -> tuple[np.ndarray, np.ndarray] | None:
    """(keys, counts) of a sketch with rows rep, bucket and sums, or None where it fails: as decode, all buckets with one key at once."""
    held = np.zeros((shape.rows, len(SUMS)), np.int64)
    held[table[:, 0] * shape.buckets + table[:, 1]] = table[:, 2:]
    bucket_of, mark_of = [shape.numbers(f"bucket {rep}", 5) for rep in range(shape.repetitions)], shape.numbers("mark", 5)

    def poly(key: np.ndarray, numbers: list[int]) -> np.ndarray:
        *coefficients, fold = numbers
        acc, low = np.full(len(key), coefficients[0]), folded(key, fold)
        for c in coefficients[1:]:
            acc = (acc * low + c) % FIELD
        return acc

    keys, counts, waiting = [], [], np.flatnonzero(held.any(axis=1))
    for _ in range(shape.rows):  # each round peels a key or is the last
        waiting = waiting[held[waiting, 0] != 0]
        n = held[waiting, 0]
        lanes, rest = np.divmod(held[waiting, 1 : 1 + LANES], n[:, None])
        key = sum(lanes[:, q] << (16 * q) for q in range(LANES))
        places = np.stack([rep * shape.buckets + poly(key, c) % shape.buckets for rep, c in enumerate(bucket_of)], axis=1)
        mark = poly(key, mark_of)
        alone = ~rest.any(axis=1) & (lanes >= 0).all(axis=1) & (lanes <= 0xFFFF).all(axis=1) & (key >= 0) & (mark * n == held[waiting, -1]) & (places == waiting[:, None]).any(axis=1)
        found = np.flatnonzero(alone)
        found = found[np.unique(key[found], return_index=True)[1]]
        if not len(found):
            break
        change = np.column_stack([n, n[:, None] * lanes, n * mark])[found]
        for rep in range(shape.repetitions):
            np.subtract.at(held, places[found, rep], change)
        keys.append(key[found])
        counts.append(n[found])
        waiting = np.unique(places[found])
    if held.any():
        return None
    names, place = np.unique(np.concatenate([np.zeros(0, np.int64), *keys]), return_inverse=True)
    total = np.zeros(len(names), np.int64)
    np.add.at(total, place, np.concatenate([np.zeros(0, np.int64), *counts]))
    return None if (total < 0).any() else (names[total != 0], total[total != 0])


def decoded_tables(sketches: DataFrame, shape: Shape, by: tuple[str, ...], keep: tuple[str, ...]) -> DataFrame:
    """keep.., key, n of many sketches, one for each value of by, each decoded in a task; one that fails gives a row without key. keep: some columns of by."""
    import pandas as pd

    def one(values: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        found = peel(rows[["rep", "bucket", *SUMS]].to_numpy(np.int64), shape)
        named = dict(zip(by, values, strict=True))
        out = pd.DataFrame({"key": [None], "n": [0]}) if found is None else pd.DataFrame({"key": found[0], "n": found[1]})
        return out.assign(**{c: named[c] for c in keep})[[*keep, "key", "n"]]

    types = dict(sketches.dtypes)
    return sketches.groupBy(*by).applyInPandas(one, ", ".join([*(f"{c} {types[c]}" for c in keep), "key long", "n long"]))
