import random
import zlib

import numpy as np
import pyarrow as pa

from balclust.llm import common, quality


def corpus(n=900, seed=1):
    """Good prose; bad: shouting, symbols, one word over and over."""
    rng = random.Random(seed)
    docs, labels = [], []
    for k in range(n):
        words = ["".join(rng.choice("abcdeimnorst") for _ in range(rng.randint(2, 9))) for _ in range(rng.randint(30, 200))]
        good = rng.random() < 0.75
        if not good:
            kind = rng.randrange(3)
            words = [w.upper() + "!!" for w in words] if kind == 0 else [w + rng.choice(["###", "$$$"]) for w in words] if kind == 1 else [words[0]] * len(words)
        docs.append((k, " ".join(words), "n"))
        if rng.random() < 0.5:
            labels.append((k, int(good), 0))
    return docs, labels


def auc(score, y):
    rank = np.argsort(np.argsort(score))
    good = y == 1
    return (rank[good].sum() - good.sum() * (good.sum() - 1) / 2) / (good.sum() * (~good).sum())


def test_held_out_accuracy_and_determinism(spark, tmp_path):
    docs, labels = corpus()
    docs += [(5000, None, "n"), (5001, "", "n"), (None, "a few words", "n"), (5003, "long text here " * 40_000, "n"), docs[0]]
    spark.createDataFrame(docs, "doc_id long, text string, score string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels + [(4, None, 1)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    rows = quality.op4(spark, str(tmp_path)).collect()
    assert len(rows) == len(docs)
    known = dict((k, q) for k, q, _ in labels)
    held = [(r.score, known[r.doc_id]) for r in rows if r.held_out and r.doc_id in known]
    assert auc(np.array([s for s, _ in held]), np.array([q for _, q in held])) > 0.97
    assert sum((s >= 0.3) == q for s, q in held) > 0.93 * len(held)
    for r in rows:
        assert 0 <= r.score <= 1 and r.predicted == (r.score >= 0.3)
        assert r.held_out == (r.doc_id is None or zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
    again = quality.op4(spark, str(tmp_path)).collect()
    assert sorted(map(tuple, rows), key=str) == sorted(map(tuple, again), key=str)


def test_without_labels_and_empty(spark):
    docs = spark.createDataFrame([(1, "text", 0)], "doc_id long, text string, _x int")
    none = spark.createDataFrame([], "doc_id long, quality int")
    model = quality.train(docs, none)
    assert [r._score for r in quality.scored(docs, model).collect()] == [0.5]
    assert quality.keep_good(docs.limit(0), none).count() == 0
    kept = quality.keep_good(docs, none)
    assert kept.columns == docs.columns and kept.count() == 1


def test_risk_is_non_negative_and_prior_is_found():
    rng = np.random.default_rng(0)
    good, bad = rng.normal(2, 1, (400, 5)), rng.normal(-2, 1, (400, 5))
    mixed = np.concatenate([rng.normal(2, 1, (300, 5)), bad[:300]])
    model = quality.fit(good.astype(np.float32), mixed.astype(np.float32))
    assert 0.35 < model.prior < 0.75
    known = quality.fit(good.astype(np.float32), mixed.astype(np.float32), 0.5)
    assert known.score(good).mean() > 0.9 and known.score(bad).mean() < 0.1


def test_features_of_a_text_do_not_depend_on_its_neighbours():
    texts = ["", "One two two.\nOne two two.\n", "ünï 12 ###", " ", "x", "tail\n"]
    together = quality.features(*common.text_bytes(pa.array(texts)))
    alone = np.concatenate([quality.features(*common.text_bytes(pa.array([t]))) for t in texts])
    assert np.array_equal(together, alone) and np.isfinite(together).all()


def test_repeated_rows_of_an_id_count_once(spark, monkeypatch):
    monkeypatch.setattr(quality, "POSITIVES", 50)
    docs, labels = corpus(120, seed=3)
    many = spark.createDataFrame(docs + docs[:2] * 300, "doc_id long, text string, score string")
    seen = []
    inner = quality._fit
    monkeypatch.setattr(quality, "_fit", lambda good, *rest: seen.append(len(good)) or inner(good, *rest))
    quality.train(many, spark.createDataFrame(labels, "doc_id long, quality int, toxic int"))
    assert 0 < seen[0] <= 50


def plain_risk(model, good, any_, w, b):
    """(the positives' part, the unlabelled part) of the unbiased risk, written out."""
    zp, zu = (np.clip((x - model.mean) / model.scale, -8, 8) @ w + b for x in (good, any_))
    return 0.5 * np.logaddexp(0, -zp).mean(), np.logaddexp(0, zu).mean() - 0.5 * np.logaddexp(0, zp).mean()


def test_steps_reach_the_least_risk():
    """Classes that overlap, so that the least risk is inside: random moves from the end point find nothing clearly better."""
    rng = np.random.default_rng(2)
    good, any_ = rng.normal(0.3, 1, (3000, 3)), np.concatenate([rng.normal(0.3, 1, (2000, 3)), rng.normal(-0.3, 1, (2000, 3))])
    model = quality.fit(good.astype(np.float32), any_.astype(np.float32), 0.5)
    best = sum(plain_risk(model, good, any_, model.weights, model.bias))
    assert plain_risk(model, good, any_, model.weights, model.bias)[1] > 0
    for s in (0.01, 0.1, 0.5):
        for _ in range(200):
            first, rest = plain_risk(model, good, any_, model.weights + rng.normal(0, s, 3), model.bias + rng.normal(0, s))
            assert first + max(0, rest) > best - 2e-3


def test_the_unlabelled_part_never_stays_below_zero():
    rng = np.random.default_rng(3)
    for apart in (0.7, 2.0, 4.0):
        good, any_ = rng.normal(apart, 1, (100, 5)), np.concatenate([rng.normal(apart, 1, (200, 5)), rng.normal(-apart, 1, (200, 5))])
        model = quality.fit(good.astype(np.float32), any_.astype(np.float32), 0.5)
        first, rest = plain_risk(model, good, any_, model.weights, model.bias)
        assert first < 0.12 and -0.02 < rest < 0.12


def test_columns_of_any_name_come_back(spark):
    docs = spark.createDataFrame([(1, "some text", "mine", 2)], "doc_id long, text string, `_score` string, row int")
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert quality.keep_good(docs, none).collect() == docs.collect()
