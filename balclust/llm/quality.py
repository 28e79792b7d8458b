"""Quality classifier by positive-unlabelled learning.

Trusted positives (texts labelled good) and unlabelled web text train one linear model that minimises
the non-negative unbiased risk: with class prior p, p times the positives' loss as positives, plus what is left of the
unlabelled texts' loss as negatives once p times the positives' loss as negatives is taken off, never below
zero. Where a step finds that difference below zero it climbs back instead. The prior is estimated from
positives and unlabelled texts alone: a plain fit that tells the two apart gives a positive the score 1 / (1 + p).

The positives are at most POSITIVES labelled rows, chosen by a hash; the unlabelled texts are all rows of the training folds. Their features are
staged once, and each step sums its gradient over all of them on the executors, in whole numbers, so that sums do not depend on order.
Features are text statistics and hashed byte-pair shares of the whole text, computed over byte arrays.

Defined cases: a null text is empty and is scored; a null doc_id is held out; repeated rows each get their row (among the positives each
doc_id and text counts once); without positives or unlabelled texts every score is 0.5; a text longer than a slice is one step, whose arrays
take about 150 bytes a byte of it; an empty table gives an empty result; other columns, of whatever name, are ignored or come back as they were.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Most labelled rows that the fit uses; folds by CRC-32, of which fold 0 is held out; least score of a good text.
POSITIVES, FOLDS, LEAST = 6_000, 5, 0.3
PAIRS = 128
#: Steps of a fit, and the pull of weights to zero.
STEPS, DECAY = 16, 1e-4
#: What a standardised feature, a score and a raw feature are counted in: sums of whole numbers are the same in any order.
UNIT_X, UNIT_S, UNIT_RAW, CLIP = 256, 65_536, 4096, 8

_CLASSES = [b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz", b"0123456789", b".,;:", b"!?", b"#*$%&|<>@^~=+_", b"\"'()[]{}-/\\", b" \t\r\x0b\x0c", b"\n"]
_CLASS = np.full(256, len(_CLASSES), np.uint8)
for _k, _c in enumerate(_CLASSES):
    _CLASS[list(_c)] = _k
_PAIR = (common.mix(np.arange(1, 65_537, dtype=np.uint64)) % np.uint64(PAIRS)).astype(np.int64)


def features(data: np.ndarray, where: np.ndarray) -> np.ndarray:
    """One row of numbers for each text, for texts laid end to end that begin at where."""
    rows, size = len(where) - 1, np.diff(where)
    owner = np.repeat(np.arange(rows), size)
    n = np.maximum(size, 1)[:, None]
    kinds = np.bincount(owner * 16 + _CLASS[data], minlength=rows * 16).reshape(rows, 16)[:, : len(_CLASSES) + 1] / n
    pairs = np.zeros((rows, PAIRS))
    if len(data) > 1:
        key = _PAIR[data[:-1].astype(np.int64) * 256 + data[1:]]
        same = owner[:-1] == owner[1:]
        pairs = np.bincount(owner[:-1][same] * PAIRS + key[same], minlength=rows * PAIRS).reshape(rows, PAIRS) / n
    starts, stops = common.word_runs(data, where)
    bounds = np.searchsorted(starts, where)
    words = np.diff(bounds)
    many = np.maximum(words, 1)
    text_of = np.repeat(np.arange(rows), words)
    salt = common.mix(np.arange(1, rows + 1, dtype=np.uint64))
    hashed = common.RunHash(common.BYTE_WORDS[data])
    key = hashed(starts, stops) ^ salt[text_of]
    again = common.per_row(common.repeats(key)[1], bounds) / many
    chain = np.zeros(len(starts), bool)
    chain[1:] = key[1:] == key[:-1]
    odd_end = np.isin(_CLASS[data[stops - 1]], (4, 5)) if len(stops) else np.zeros(0, bool)
    length = stops - starts
    begins = np.unique(np.concatenate([where[:-1], np.flatnonzero(data == 10) + 1]))
    begins = begins[begins < len(data)]
    ends = np.append(begins[1:], len(data))
    line_of = np.searchsorted(where, begins, "right") - 1
    per_text = np.searchsorted(begins, where)
    lines = np.maximum(np.diff(per_text), 1)
    line_again = common.per_row(common.repeats(hashed(begins, ends) ^ salt[line_of])[1], per_text) / lines
    shares = np.stack([again, common.per_row(chain, bounds) / many, common.per_row(odd_end, bounds) / many, line_again, common.per_row(length > 20, bounds) / many, common.per_row(length == 1, bounds) / many], axis=1)
    scale = np.stack([np.log1p(words), np.log1p(size), common.per_row(length, bounds) / many / 10, words < 20, again * np.log1p(words)], axis=1)
    bent = np.concatenate([shares, kinds], axis=1)
    return np.concatenate([scale, bent, np.log(bent + 0.003), np.minimum(bent * 20, 1), pairs * 20], axis=1).astype(np.float32)


class Model(NamedTuple):
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8) @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(z.astype(np.float64), -30, 30)))


def _squash(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _standard(x: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Standardised features and a one at the end, as whole numbers of 1 / UNIT_X in floats."""
    out = np.full((len(x), x.shape[1] + 1), float(UNIT_X))
    out[:, :-1] = np.rint(np.clip((x - mean) / scale, -CLIP, CLIP) * UNIT_X)
    return out


def _moments(x: np.ndarray) -> np.ndarray:
    """Rows, and sums of features and of their squares, as whole numbers."""
    x = x.astype(np.float64)
    return np.concatenate([[len(x)], np.rint(x * UNIT_RAW).sum(axis=0), np.rint(x * x * UNIT_RAW).sum(axis=0)]).astype(np.int64)


def _curve(x: np.ndarray) -> np.ndarray:
    """Sums of products of the standardised features, as whole numbers."""
    return (x.T @ x).astype(np.int64).ravel()


def _slope(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Sums of the loss as negatives and of its gradient, as whole numbers."""
    z = x @ w / UNIT_X
    return np.append(np.rint(np.logaddexp(0, z) * UNIT_S).sum(), x.T @ np.rint(_squash(z) * UNIT_S)).astype(np.int64)


def _descend(good: np.ndarray, slope, curve: np.ndarray, prior: float | None) -> np.ndarray:
    """Weights that minimise the non-negative risk under the logistic loss, or with no prior the risk of telling positives from the unlabelled.

    good: standardised positives; slope(w): (mean loss as negatives, its gradient) over the unlabelled; curve: their mean products. A quarter of
    the curve bounds the risk's curvature everywhere, so that a step of its inverse never overshoots; momentum starts anew after each climb. Of the points looked at
    the one of least risk is given, a part below zero counting by its size.
    """
    good = good / UNIT_X
    bound = curve / 4 + (0 if prior is not None else good.T @ good / len(good) / 4) + max(DECAY, 1e-3) * np.eye(len(curve))
    w = np.zeros(len(curve))
    if prior is not None:
        w[-1] = np.log(prior / (1 - prior))
    ahead, run, least, best = w, 0, np.inf, w
    for _ in range(STEPS):
        loss, grad = slope(ahead)
        zp = good @ ahead
        if prior is None:
            grad = grad - good.T @ _squash(-zp) / len(good)
        else:
            rest, over = grad - prior * (good.T @ _squash(zp)) / len(good), loss - prior * np.logaddexp(0, zp).mean()
            risk = prior * np.logaddexp(0, -zp).mean() + abs(over)
            if risk < least:
                least, best = risk, ahead
            if over < 0:  # the unlabelled part has gone below zero: climb back by its gradient alone
                w = ahead = ahead + np.linalg.solve(bound, rest)
                run = 0
                continue
            grad = rest - prior * (good.T @ _squash(-zp)) / len(good)
        pull = DECAY * ahead
        pull[-1] = 0
        new = ahead - np.linalg.solve(bound, grad + pull)
        run += 1
        ahead, w = new + (new - w) * ((run - 1) / (run + 2)), new
    return w if prior is None else best


def _fit(good: np.ndarray, mean: np.ndarray, scale: np.ndarray, slope, curve: np.ndarray, prior: float | None) -> Model:
    good = _standard(good, mean, scale)
    if prior is None:
        held = float(_squash(good @ _descend(good, slope, curve, None) / UNIT_X).mean())
        prior = (1 - held) / held
    prior = min(0.98, max(0.02, prior))
    w = _descend(good, slope, curve, prior)
    return Model(mean, scale, w[:-1], float(w[-1]), prior)


def _unfit(width: int) -> Model:
    return Model(np.zeros(width), np.ones(width), np.zeros(width), 0.0, 0.5)


def _scale(moments: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    n, width = int(moments[0]), len(moments) // 2
    mean = moments[1 : width + 1] / UNIT_RAW / max(n, 1)
    return n, mean, np.sqrt(np.maximum(0, moments[width + 1 :] / UNIT_RAW / max(n, 1) - mean**2)) + 1e-3


def fit(good: np.ndarray, any_: np.ndarray, prior: float | None = None) -> Model:
    """A model from rows of features of trusted positives and of unlabelled texts, all at hand."""
    if not len(good) or not len(any_):
        return _unfit((any_ if len(any_) else good).shape[1])
    n, mean, scale = _scale(_moments(any_))
    x = _standard(any_, mean, scale)
    return _fit(good, mean, scale, lambda w: _mean_slope(_slope(x, w), n), _curve(x).reshape(x.shape[1], -1) / UNIT_X**2 / n, prior)


def _mean_slope(sums: np.ndarray, n: int) -> tuple[float, np.ndarray]:
    return sums[0] / UNIT_S / n, sums[1:] / UNIT_S / UNIT_X / n


def fold(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % FOLDS


def _featured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in common.slices(batches, "text"):
        x = features(*common.text_bytes(common.column(part, "text")))
        flat = pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), x.shape[1]).cast(pa.list_(pa.float32()))
        yield pa.RecordBatch.from_arrays([common.column(part, "doc_id"), common.column(part, "hash"), flat], ["doc_id", "hash", "x"])


WIDTH = features(np.zeros(0, np.uint8), np.zeros(2, np.int64)).shape[1]


def featured(docs: DataFrame) -> DataFrame:
    """doc_id, hash (of the text) and x (its features) of each row of docs (doc_id, text), staged."""
    return common.stage(docs.select("doc_id", "text", F.xxhash64("text").alias("hash")).mapInArrow(_featured, "doc_id long, hash long, x array<float>"))


def _rows(batch: pa.RecordBatch) -> np.ndarray:
    return common.column(batch, "x").flatten().to_numpy(zero_copy_only=False).reshape(-1, WIDTH)


#: Partial sums come to the driver from so many tasks, however many there are before.
PARTS = 16


def totals(table: DataFrame, kernel) -> np.ndarray:
    """The sum over all rows of what kernel (features of some rows -> whole numbers) gives; each task adds up its own first."""

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = 0
        for b in batches:
            for start in range(0, b.num_rows, 1 << 14):
                held = held + kernel(_rows(b.slice(start, 1 << 14)))
        if not isinstance(held, int):
            yield pa.RecordBatch.from_arrays([pa.array([held.tobytes()], pa.binary())], ["sums"])
        common.give_back()

    def together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.frombuffer(s, np.int64) for b in batches for s in common.column(b, "sums").to_pylist()]
        if held:
            yield pa.RecordBatch.from_arrays([pa.array([np.sum(held, axis=0).tobytes()], pa.binary())], ["sums"])

    parts = table.select("x").mapInArrow(own, "sums binary").repartition(PARTS).mapInArrow(together, "sums binary").collect()  # at most PARTS rows
    return np.sum([np.frombuffer(r.sums, np.int64) for r in parts], axis=0) if parts else kernel(np.zeros((0, WIDTH), np.float32))


def train(docs: DataFrame, labels: DataFrame, table: DataFrame | None = None, prior: float | None = None) -> Model:
    """A model of labels.quality from the folds that are not held out. Only the features of the trusted positives reach the driver. table: as featured gives of docs."""
    own = featured(docs) if table is None else table
    web = own.where(fold(F.col("doc_id")) != 0)
    known = labels.where(fold(F.col("doc_id")) != 0).where("quality = 1").select("doc_id").distinct()
    trusted = known.orderBy(F.xxhash64(F.col("doc_id"), F.lit(17)), "doc_id").limit(POSITIVES)
    # Rows of one id that are alike count once; of what is left again POSITIVES rows at most.
    rows = web.join(F.broadcast(trusted), "doc_id").groupBy("doc_id", "hash").agg(F.min("x").alias("x")).orderBy(F.xxhash64(F.col("doc_id"), F.lit(17)), "doc_id", "hash").limit(POSITIVES)
    sums = totals(web, _moments)
    n, mean, scale = _scale(sums)
    good = rows.select("doc_id", "hash", "x").toArrow().combine_chunks().sort_by([("doc_id", "ascending"), ("hash", "ascending")])
    if not good.num_rows or not n:
        return _unfit(WIDTH)
    good = np.array(good["x"].to_pylist(), np.float32)
    curve = totals(web, lambda x: _curve(_standard(x, mean, scale))).reshape(WIDTH + 1, -1) / UNIT_X**2 / n
    model = _fit(good, mean, scale, lambda w: _mean_slope(totals(web, lambda x: _slope(_standard(x, mean, scale), w)), n), curve, prior)
    if table is None:
        common.drop(docs.sparkSession, own)
    return model


def _scored(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, "text"):
            x = features(*common.text_bytes(common.column(part, "text")))
            score = model.score(x)
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(score)], [*part.schema.names, "_score"])

    return run


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """docs with _score of each row (in place of a column of that name); docs has a column text."""
    docs = docs.drop("_score")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(_scored(model), f"{fields}, _score double")


def _scored_table(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([common.column(b, "doc_id"), pa.array(model.score(_rows(b)), pa.float64())], ["doc_id", "score"])

    return run


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir).select("doc_id", "text")
    table = featured(docs)
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), table)
    found = table.select("doc_id", "x").mapInArrow(_scored_table(model), "doc_id long, score double")
    return found.select("doc_id", (fold(F.col("doc_id")) == 0).alias("held_out"), "score", (F.col("score") >= LEAST).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of docs that the classifier takes for good; all columns come back, one named _score too."""
    model = train(docs.select("doc_id", "text"), labels)
    rows = common.as_row(docs).withColumn("text", F.col("row.text"))
    kept = rows.mapInArrow(_scored(model), f"row {rows.schema['row'].dataType.simpleString()}, text string, _score double").where(F.col("_score") >= LEAST)
    return common.from_row(kept, docs.columns)
