"""Corpus-wide removal of repeated substrings by a prefix-free parse.

A rolling hash over GRAM bytes triggers a phrase boundary wherever it is the least among the
WINDOWS grams that one window of LENGTH bytes holds. So every window holds its trigger at a place
that its own bytes fix, and equal windows have equal triggers: the windows that share a trigger form a phrase,
a run of the text around the trigger in which each window begins. All windows of the corpus fall
into phrases, and two windows can only be equal if their phrases' triggers are.

The dictionary of distinct phrases takes the place of the corpus: of a phrase that occurs many
times only the first occurrence can hold a first window, and the others go whole. Where
different phrases share a trigger, their suffixes (the windows, by what precedes the trigger and what follows it
up to LENGTH) are sorted bytewise, which gives the corpus order to the depth that matters; a
window equal to its neighbour in that order goes unless it is the earliest. No rank of the whole parse is
needed, since a phrase carries the bytes that follow its trigger. A trigger that more than CROWD phrases share
is not kept together: its windows are dealt by hashes of their own and compared by the same sort.

Two passes: triggers and phrase hashes of all texts meet by trigger (packed arrays, first occurrences
of a phrase only from each task); then only the phrases whose triggers others share meet as bytes.
Phrases are told apart by 64-bit hashes of their bytes; windows are compared by their bytes.

Defined cases: a null text is empty; a text shorter than LENGTH loses nothing; repeated rows (doc_id and text
alike) are one document and each get its row; rows that share a doc_id but not the text follow each other by
a hash of the text; a null doc_id comes first; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  (pa.compute)
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

LENGTH, GRAM = 100, 24
WINDOWS = LENGTH - GRAM + 1
#: Bytes of text whose phrases share a bucket of triggers, the least number of buckets, and phrases that a task holds before it packs them.
BUCKET_BYTES, LEAST_BUCKETS, HELD = 32 << 20, 128, 200_000
#: Bytes of phrases whose windows are sorted at a time (or those of one trigger).
SORTED = 4 << 20
#: Bits that hold a place in a slice of texts; fixed, so that triggers are the same in any slice.
PLACE_BITS = 31
#: All windows of a run go; a phrase whose trigger other phrases share; one whose trigger more than CROWD share.
REPEATED, SHARED, CROWDED = 1, 2, 3
#: Phrases of one trigger that one task sorts together, about 0.4 MB of them; of more, each window is dealt by its own hash.
CROWD = 2_500

PHRASE = np.dtype([("trigger", "<u8"), ("phrase", "<u8"), ("doc", "<i8"), ("tie", "<i8"), ("start", "<i8"), ("count", "<i8")])


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each run of width values, by doubling."""
    out, have = values, 1
    while have < width:
        step = min(have, width - have)
        out = np.minimum(out[: len(out) - step], out[step:])
        have += step
    return out


def parse(data: np.ndarray, where: np.ndarray) -> dict[str, np.ndarray]:
    """The phrases of texts laid end to end: text, start (of the first window), count (of windows), place (of the trigger), trigger, phrase."""
    none = dict.fromkeys(("text", "start", "count", "place", "trigger", "phrase"), np.zeros(0, np.int64))
    if len(data) < LENGTH:
        return none
    runs = common.RunHash(common.BYTE_WORDS[data])
    at = np.arange(len(data) - GRAM + 1)
    grams = runs(at, at + GRAM)
    # The low bits hold the place: of hashes equal in their high bits the leftmost counts.
    bits = np.uint64(PLACE_BITS)
    least = _least((grams >> bits << bits) | at.astype(np.uint64), WINDOWS)
    trigger_at = (least & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
    edge = np.zeros(len(data) + 1, np.int64)
    size = np.diff(where)
    long = size >= LENGTH
    np.add.at(edge, where[:-1][long], 1)
    np.add.at(edge, where[1:][long] - LENGTH + 1, -1)
    valid = np.flatnonzero(np.cumsum(edge)[: len(trigger_at)] > 0)
    if not len(valid):
        return none
    place = trigger_at[valid]
    text = np.searchsorted(where, valid, "right") - 1
    heads = np.flatnonzero(np.append(True, (place[1:] != place[:-1]) | (text[1:] != text[:-1])))
    count = np.diff(np.append(heads, len(valid)))
    start, place = valid[heads], place[heads]
    phrase = common.mix(runs(start, start + count + LENGTH - 1) ^ (place - start).astype(np.uint64) * np.uint64(0x9FB21C651E98DF25))
    return {"text": text[heads], "start": start, "count": count, "place": place, "trigger": grams[place], "phrase": phrase}


def _changes(*columns: np.ndarray) -> np.ndarray:
    """Where a row differs from the one before; the first does."""
    out = np.zeros(len(columns[0]), bool)
    out[:1] = True
    for c in columns:
        out[1:] |= c[1:] != c[:-1]
    return out


def _split(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(the first occurrence of each phrase, by trigger; the other occurrences, by document). The same occurrence met twice counts once."""
    rows = rows[np.lexsort([rows["start"], rows["tie"], rows["doc"], rows["phrase"], rows["trigger"]])]
    new = _changes(rows["trigger"], rows["phrase"])
    head = rows[np.maximum.accumulate(np.where(new, np.arange(len(rows)), 0))]
    other = (rows["start"] != head["start"]) | (rows["doc"] != head["doc"]) | (rows["tie"] != head["tie"])
    again = rows[~new & other]
    return rows[new], again[np.lexsort([again["start"], again["tie"], again["doc"]])]


def _runs(rows: np.ndarray) -> dict[str, np.ndarray]:
    """Rows in order of document and start, those whose windows follow on merged."""
    if not len(rows):
        return {k: np.zeros(0, np.int64) for k in ("doc", "tie", "start", "count")}
    stop = rows["start"] + rows["count"]
    new = _changes(rows["doc"], rows["tie"])
    new[1:] |= rows["start"][1:] > stop[:-1]
    heads = np.flatnonzero(new)
    last = np.append(heads[1:], len(rows)) - 1
    start = rows["start"][heads]
    return {"doc": rows["doc"][heads], "tie": rows["tie"][heads], "start": start, "count": stop[last] - start}


PACKED = pa.schema([("bucket", pa.int64()), ("body", pa.binary()), ("doc", pa.int64()), ("tie", pa.int64()), ("start", pa.int64()), ("count", pa.int64())])
PLACED = pa.schema([("doc", pa.int64()), ("tie", pa.int64()), ("start", pa.int64()), ("count", pa.int64()), ("kind", pa.int32())])
BODIES = pa.schema([("trigger", pa.int64()), ("doc", pa.int64()), ("tie", pa.int64()), ("start", pa.int64()), ("count", pa.int64()), ("body", pa.binary())])
SPANS = pa.schema([("doc", pa.int64()), ("tie", pa.int64()), ("start", pa.int64()), ("stop", pa.int64())])


def _ddl(schema: pa.Schema) -> str:
    names = {pa.int64(): "long", pa.int32(): "int", pa.binary(): "binary"}
    return ", ".join(f"{f.name} {names[f.type]}" for f in schema)


def pack(rows: np.ndarray) -> bytes:
    """Phrases with their documents in a table of their own: 25 bytes for each phrase."""
    doc, index = np.unique(rows[["doc", "tie"]], return_inverse=True)
    parts = [np.array([len(doc), len(rows)], "<u8"), doc["doc"], doc["tie"], rows["trigger"], rows["phrase"], index.astype("<u4"), rows["start"].astype("<u4"), rows["count"].astype("u1")]
    return b"".join(np.ascontiguousarray(x).tobytes() for x in parts)


def unpack(body: bytes) -> np.ndarray:
    docs, n = np.frombuffer(body, "<u8", 2).tolist()
    at, out = 16, []
    for kind, size in (("<i8", docs), ("<i8", docs), ("<u8", n), ("<u8", n), ("<u4", n), ("<u4", n), ("u1", n)):
        out.append(np.frombuffer(body, kind, size, at))
        at += out[-1].nbytes
    doc, tie, trigger, phrase, index, start, count = out
    rows = np.zeros(n, PHRASE)
    for name, values in zip(PHRASE.names, (trigger, phrase, doc[index], tie[index], start, count), strict=True):
        rows[name] = values
    return rows


def _emit(rows: np.ndarray, buckets: int) -> Iterator[pa.RecordBatch]:
    first, again = _split(rows)
    bucket = (first["trigger"] >> np.uint64(32)).astype(np.int64) % buckets
    order = np.argsort(bucket, kind="stable")
    first, bucket = first[order], bucket[order]
    heads = np.flatnonzero(_changes(bucket))
    bodies = [pack(x) for x in np.split(first, heads[1:])] if len(first) else []
    none = pa.nulls(len(heads), pa.int64())
    yield pa.RecordBatch.from_arrays([pa.array(bucket[heads]), pa.array(bodies, pa.binary()), none, none, none, none], schema=PACKED)
    runs = _runs(again)
    away = (common.mix(runs["doc"].astype(np.uint64)) % np.uint64(buckets)).astype(np.int64)
    yield pa.RecordBatch.from_arrays([pa.array(away), pa.nulls(len(away), pa.binary()), *map(pa.array, runs.values())], schema=PACKED)


def _parse(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for part in common.slices(batches, "text", common.SLICE_BYTES // 4):
            data, where = common.text_bytes(common.column(part, "text"))
            found = parse(data, where)
            rows = np.zeros(len(found["text"]), PHRASE)
            for name in ("trigger", "phrase", "count"):
                rows[name] = found[name]
            rows["start"] = found["start"] - where[found["text"]]
            for name in ("doc", "tie"):
                rows[name] = common.column(part, name).to_numpy()[found["text"]]
            held.append(rows)
            size += len(rows)
            if size >= HELD:
                yield from _emit(np.concatenate(held), buckets)
                held, size = [], 0
        if size:
            yield from _emit(np.concatenate(held), buckets)

    return run


def _placed(rows: dict[str, np.ndarray] | np.ndarray, kind: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([*(pa.array(np.ascontiguousarray(rows[c])) for c in ("doc", "tie", "start", "count")), pa.array(np.full(len(rows["doc"]), kind, np.int32))], schema=PLACED)


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """By bucket of triggers, in order: which occurrences repeat an earlier one, and which first ones share their trigger with other phrases."""

    def settle(bodies: list[bytes]) -> Iterator[pa.RecordBatch]:
        first, again = _split(np.concatenate([unpack(b) for b in bodies]))
        heads = np.flatnonzero(_changes(first["trigger"]))
        size = np.diff(np.append(heads, len(first)))
        yield _placed(_runs(again), REPEATED)
        size = np.repeat(size, size)
        yield _placed(first[(size > 1) & (size <= CROWD)], SHARED)
        yield _placed(first[size > CROWD], CROWDED)

    held, at = [], None
    for batch in batches:
        runs = batch.filter(pa.compute.is_null(common.column(batch, "body")))
        yield _placed({c: common.column(runs, c).to_numpy() for c in ("doc", "tie", "start", "count")}, REPEATED)
        for bucket, body in zip(common.column(batch, "bucket").to_pylist(), common.column(batch, "body").to_pylist(), strict=True):
            if body is None:
                continue
            if bucket != at and held:
                yield from settle(held)
                held = []
            held.append(body)
            at = bucket
    if held:
        yield from settle(held)


def _signed(keys: np.ndarray) -> np.ndarray:
    return (keys ^ np.uint64(1 << 63)).view(np.int64)


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The bytes of shared phrases, and their triggers' hashes; of crowded ones each window by its own hash.

    Of crowded windows that are alike in a slice only the earliest goes on; the others come without bytes, as repeats.
    """
    for part in common.slices(batches, "text", common.SLICE_BYTES // 4):
        data, where = common.text_bytes(common.column(part, "text"))
        doc, tie = (common.column(part, c).to_numpy() for c in ("doc", "tie"))
        lists = common.column(part, "shared")
        flat = lists.flatten()
        start, kind = (pa.compute.struct_field(flat, c).to_numpy() for c in ("start", "kind"))
        owner = np.repeat(np.arange(part.num_rows), np.diff(lists.offsets.to_numpy()))
        found = parse(data, where)
        # Both sides name a phrase by where it starts in the slice.
        at = np.searchsorted(found["start"], np.unique(where[owner] + start)) if len(owner) else np.zeros(0, np.int64)
        crowded = np.isin(found["start"][at], where[owner[kind == CROWDED]] + start[kind == CROWDED])
        body = data.tobytes()

        def rows(at: np.ndarray, first: np.ndarray, count: np.ndarray, keys: np.ndarray, whole: bool = True) -> pa.RecordBatch:
            text = found["text"][at]
            cuts = [body[a:b] for a, b in zip(first.tolist(), (first + count + LENGTH - 1).tolist(), strict=True)] if whole else [None] * len(first)
            return pa.RecordBatch.from_arrays([pa.array(_signed(keys)), pa.array(doc[text]), pa.array(tie[text]), pa.array(first - where[text]), pa.array(count), pa.array(cuts, pa.binary())], schema=BODIES)

        plain = at[~crowded]
        yield rows(plain, found["start"][plain], found["count"][plain], found["trigger"][plain])
        many = np.repeat(at[crowded], found["count"][at[crowded]])
        if not len(many):
            continue
        begin = np.cumsum(found["count"][at[crowded]]) - found["count"][at[crowded]]
        first = found["start"][many] + np.arange(len(many)) - np.repeat(begin, found["count"][at[crowded]])
        keys = common.RunHash(common.BYTE_WORDS[data])(first, first + LENGTH)
        order = np.lexsort([first - where[found["text"][many]], tie[found["text"][many]], doc[found["text"][many]], keys])
        many, first, keys = many[order], first[order], keys[order]
        new = _changes(keys)
        head = np.maximum.accumulate(np.where(new, np.arange(len(keys)), 0))
        text, other = found["text"][many], found["text"][many[head]]
        same = (doc[text] == doc[other]) & (tie[text] == tie[other]) & (first - where[text] == first[head] - where[other])
        yield rows(many[new], first[new], np.ones(int(new.sum()), np.int64), keys[new])
        # What repeats goes in runs, dealt by where they start.
        gone, at = first[~same], many[~same]
        at, gone = at[np.argsort(gone)], np.sort(gone)
        heads = np.flatnonzero(np.append(True, (np.diff(gone) > 1) | (found["text"][at[1:]] != found["text"][at[:-1]]))) if len(gone) else np.zeros(0, np.int64)
        count = np.diff(np.append(heads, len(gone)))
        yield rows(at[heads], gone[heads], count, common.mix(gone[heads].astype(np.uint64)), whole=False)


def later_windows(bodies: list[bytes], group: np.ndarray, doc: np.ndarray, tie: np.ndarray, start: np.ndarray, count: np.ndarray) -> dict[str, np.ndarray]:
    """The runs of windows that equal an earlier one of the same group: doc, tie, start, count.

    Suffix order to depth LENGTH: windows are ranked by their next eight bytes at a time, and those whose rank is theirs alone drop out.
    """
    size = np.array([len(b) for b in bodies], np.int64)
    data = np.frombuffer(b"".join(bodies) + bytes(8), np.uint8).astype(np.uint64)
    word = np.zeros(len(data) - 7, np.uint64)
    for k in range(8):
        word = word << np.uint64(8) | data[k : len(data) - 7 + k]
    owner = np.repeat(np.arange(len(bodies)), count)
    inside = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    at = (np.cumsum(size) - size)[owner] + inside
    live, rank = np.arange(len(at)), group[owner]
    for depth in range(0, LENGTH, 8):
        nexts = word[at[live] + depth]
        if LENGTH - depth < 8:
            nexts = nexts >> np.uint64(8 * (8 - LENGTH + depth))
        order = np.lexsort([nexts, rank])
        new = _changes(rank[order], nexts[order])
        number = np.cumsum(new) - 1
        many = np.repeat((n := np.diff(np.append(np.flatnonzero(new), len(order)))) > 1, n)
        live, rank = live[order][many], number[many]
        if not len(live):
            break
    place = inside + start[owner]
    order = np.lexsort([place[live], tie[owner[live]], doc[owner[live]], rank])
    live, rank = live[order], rank[order]
    new = _changes(rank)
    head = live[np.maximum.accumulate(np.where(new, np.arange(len(live)), 0))] if len(live) else live
    gone = live[(place[live] != place[head]) | (doc[owner[live]] != doc[owner[head]]) | (tie[owner[live]] != tie[owner[head]])]
    rows = np.zeros(len(gone), PHRASE)
    rows["doc"], rows["tie"], rows["start"], rows["count"] = doc[owner[gone]], tie[owner[gone]], place[gone], 1
    return _runs(rows[np.lexsort([rows["start"], rows["tie"], rows["doc"]])])


def _sort(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Phrases in order of their triggers, a number of whole triggers at a time."""

    def settle(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(held)
        columns = {c: table[c].to_numpy() for c in ("trigger", "doc", "tie", "start", "count")}
        runs = later_windows(table["body"].to_pylist(), np.cumsum(_changes(columns["trigger"])), *(columns[c] for c in ("doc", "tie", "start", "count")))
        return pa.RecordBatch.from_arrays([*map(pa.array, (runs["doc"], runs["tie"], runs["start"], runs["start"] + runs["count"] + LENGTH - 1))], schema=SPANS)

    held: list[pa.RecordBatch] = []
    for batch in common.slices(batches, "body", SORTED // 4):
        known = pa.compute.is_null(common.column(batch, "body"))
        gone = batch.filter(known)
        if gone.num_rows:
            start, count = (common.column(gone, c).to_numpy() for c in ("start", "count"))
            yield pa.RecordBatch.from_arrays([common.column(gone, "doc"), common.column(gone, "tie"), pa.array(start), pa.array(start + count + LENGTH - 1)], schema=SPANS)
            batch = batch.filter(pa.compute.invert(known))
        if not batch.num_rows:
            continue
        held.append(batch)
        if sum(b.nbytes for b in held) < SORTED:
            continue
        table = pa.Table.from_batches(held).combine_chunks()
        trigger = table["trigger"].to_numpy()
        cut = int(np.flatnonzero(_changes(trigger))[-1])  # the last trigger may go on in the next batch
        if cut:
            yield settle(table.slice(0, cut).to_batches())
            held = table.slice(cut).to_batches()
    if held:
        yield settle(held)


def _rest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"]
    for part in common.slices(batches, "text"):
        rows = []
        for key, text, spans in zip(common.column(part, "doc_id").to_pylist(), common.raw_texts(part), common.column(part, "spans").to_pylist(), strict=True):
            kept, at, runs, removed = [], 0, 0, 0
            stop = -1
            for span in sorted((s["start"], s["stop"]) for s in spans or ()):
                if span[0] > stop:  # a new run; spans that touch are one
                    kept.append(text[max(at, 0) : span[0]])
                    runs += 1
                    removed += span[1] - span[0]
                elif span[1] > stop:
                    removed += span[1] - stop
                stop = max(stop, span[1])
                at = stop
            kept.append(text[at:])
            rest = b"".join(kept)
            rows.append((key, len(text), removed, runs, hashlib.sha256(rest).hexdigest(), rest))
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def repeated_spans(texts: DataFrame) -> DataFrame:
    """doc, tie, start, stop of byte runs that repeat earlier ones; runs may overlap. texts: doc, tie, text without nulls."""
    total = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(LEAST_BUCKETS, -(-total // BUCKET_BYTES))
    parsed = texts.mapInArrow(_parse(buckets), _ddl(PACKED)).repartition("bucket").sortWithinPartitions("bucket")
    placed = common.stage(parsed.mapInArrow(_meet, _ddl(PLACED)))
    common.release(texts.sparkSession)
    shared = placed.where(F.col("kind") >= SHARED).groupBy("doc", "tie").agg(F.collect_list(F.struct("start", "kind")).alias("shared"))
    bodies = texts.join(shared, ["doc", "tie"]).mapInArrow(_cut, _ddl(BODIES)).repartition("trigger").sortWithinPartitions("trigger")
    sorted_ = common.stage(bodies.mapInArrow(_sort, _ddl(SPANS)))
    common.release(texts.sparkSession)
    whole = placed.where(F.col("kind") == REPEATED).select("doc", "tie", "start", (F.col("start") + F.col("count") + LENGTH - 1).alias("stop"))
    return whole.unionByName(sorted_)


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the bytes that stay) of each row of docs (doc_id, text)."""
    texts = docs.select("doc_id", F.coalesce("doc_id", F.lit(-(1 << 63))).alias("doc"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("tie"), F.coalesce("text", F.lit("")).alias("text"))
    spans = repeated_spans(texts.select("doc", "tie", "text")).groupBy("doc", "tie").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))
    return texts.join(spans, ["doc", "tie"], "left").select("doc_id", "text", "spans").mapInArrow(_rest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(common.documents(spark, sf_dir)).drop("kept")
