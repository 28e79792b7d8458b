import hashlib
import random

import numpy as np
import pytest

from balclust.llm import repeats


def brute(docs):
    """docs: (doc_id, text) without equal pairs. Strings of 100 bytes in order of corpus, first ones remembered."""
    docs = sorted(docs, key=lambda d: -(1 << 63) if d[0] is None else d[0])
    seen, out = set(), {}
    for key, text in docs:
        body = (text or "").encode()
        gone = np.zeros(len(body) + 1, bool)
        for k in range(len(body) - 99):
            if (w := body[k : k + 100]) in seen:
                gone[k : k + 100] = True
            seen.add(w)
        kept = bytes(b for b, g in zip(body, gone) if not g)
        runs = int((np.diff(np.append(False, gone).astype(int)) == 1).sum())
        out[key] = (len(body), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest())
    return out


def corpus(seed, unit="word"):
    rng = random.Random(seed)
    words = [f"{unit}é{k}" for k in range(500)]
    prose = lambda n: " ".join(rng.choice(words) for _ in range(n))
    passages = [prose(60) for _ in range(4)] + ["x" * 400, "ab" * 150, prose(13)[:100], prose(13)[:99]]
    texts = [None, "", "short", "x" * 99, "x" * 100, "x" * 101, "y" * 5000, "abc" * 700]
    for k in range(60):
        parts = [prose(rng.randint(0, 40)) for _ in range(3)]
        for _ in range(rng.randint(0, 3)):
            parts.insert(rng.randrange(len(parts)), rng.choice(passages))
        texts.append(rng.choice(["", " ", "\n"]).join(parts))
        if k % 9 == 0:
            texts.append(texts[-1])
        if k % 7 == 0 and len(texts[-1]) > 50:
            texts.append(texts[-1][:30] + "!" + texts[-1][31:])
    return texts


@pytest.mark.parametrize("seed", [1, 2])
def test_query_equals_brute_force(spark, tmp_path, seed, monkeypatch):
    texts = corpus(seed)
    docs = [(None if k == 9 else 7 * k - 100, t) for k, t in enumerate(texts)]
    docs = docs[::2] + docs[1::2][::-1]
    df = spark.createDataFrame([(i, t, 1) for i, t in docs + docs[3:9]], "doc_id long, text string, tie int").repartition(4)
    df.write.parquet(str(tmp_path / "documents.parquet"))
    want = brute(docs)
    rows = repeats.op3(spark, str(tmp_path)).collect()
    assert len(rows) == len(docs) + 6
    for r in rows:
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == want[r.doc_id], r.doc_id


@pytest.mark.parametrize("crowd", [1, 2, 256])
def test_small_buffers_change_nothing(monkeypatch, crowd):
    """The same corpus through tiny packs and slices, by the functions that the tasks run, with triggers crowded or not."""
    import pyarrow as pa

    from balclust.llm import common

    texts = [t or "" for t in corpus(3)]
    docs = dict(enumerate(texts))
    monkeypatch.setattr(repeats, "CROWD", crowd)
    monkeypatch.setattr(repeats, "HELD", 50)
    monkeypatch.setattr(repeats, "SORTED", 2000)
    monkeypatch.setattr(common, "SLICE_BYTES", 4000)
    batch = pa.RecordBatch.from_pydict({"doc": pa.array(list(docs), pa.int64()), "tie": pa.array([0] * len(docs), pa.int64()), "text": texts})
    packed = pa.Table.from_batches(list(repeats._parse(5)(iter([batch]))), repeats.PACKED).sort_by("bucket")
    placed = pa.Table.from_batches(list(repeats._meet(iter(packed.to_batches(max_chunksize=7)))), repeats.PLACED).to_pylist()
    shared = {}
    for r in placed:
        if r["kind"] >= repeats.SHARED:
            shared.setdefault(r["doc"], []).append({"start": r["start"], "kind": r["kind"]})
    lists = pa.array(list(shared.values()), pa.list_(pa.struct([("start", pa.int64()), ("kind", pa.int32())])))
    part = pa.RecordBatch.from_pydict({"doc": pa.array(list(shared), pa.int64()), "tie": pa.array([0] * len(shared), pa.int64()), "text": [docs[k] for k in shared], "shared": lists})
    bodies = pa.Table.from_batches(list(repeats._cut(iter([part]))), repeats.BODIES).sort_by("trigger")
    spans = [(r["doc"], r["start"], r["start"] + r["count"] + 99) for r in placed if r["kind"] == repeats.REPEATED]
    spans += [(r["doc"], r["start"], r["stop"]) for r in pa.Table.from_batches(list(repeats._sort(iter(bodies.to_batches(max_chunksize=9)))), repeats.SPANS).to_pylist()]
    want = brute(list(docs.items()))
    for k, t in docs.items():
        gone = np.zeros(len(t.encode()), bool)
        for doc, a, b in spans:
            if doc == k:
                gone[a:b] = True
        assert int(gone.sum()) == want[k][1], k


def test_packing_round_trip():
    rng = np.random.default_rng(1)
    rows = np.zeros(1000, repeats.PHRASE)
    for name in ("trigger", "phrase"):
        rows[name] = rng.integers(0, 1 << 63, 1000, dtype=np.uint64)
    rows["doc"], rows["tie"], rows["start"], rows["count"] = rng.integers(-5, 5, 1000), rng.integers(-9, 9, 1000), rng.integers(0, 1 << 32, 1000), rng.integers(1, 78, 1000)
    assert (repeats.unpack(repeats.pack(rows)) == rows).all()


def test_empty_table(spark):
    assert repeats.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0
