import random
import re

import corpus_pipeline
from tokenizers import Tokenizer

from balclust.llm import mixing, packing, quality, tokens
from tests.llm.test_quality import corpus
from tests.llm.test_secrets import brute as secrets_of


def groups(ids, texts):
    """For each row the smallest id of its group: all pairs compared by their sets of five-word shingles."""

    def shingles(text):
        words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
        return frozenset(tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))) if words else frozenset()

    sets, label = [shingles(t) for t in texts], list(ids)
    for i in range(len(ids)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both):
                low, high = sorted((label[i], label[j]))
                label = [low if x == high else x for x in label]
    return label


def test_stages_on_a_small_corpus(spark, tmp_path):
    docs, labels = corpus(300, seed=8)
    rng = random.Random(2)
    rows = [(k, t, "en", rng.choice(["a", "b", None]), len(t)) for k, t, _ in docs]
    rows += [(1000 + k, t, "en", "a", n) for k, t, _, _, n in rows[:20]]  # exact copies
    rows += [(2000 + k, t + " api_key=abcdef123456", "en", "b", n + 21) for k, t, _, _, n in rows[20:30]]
    rows += [(3000, None, None, None, None), (3001, "", "en", "a", 0)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    frame.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_classifier", "simhash_near_dedup", "secret_scans", "source_mix", "sequence_packing"]
    out, now = [], spark.read.parquet(str(tmp_path / "documents.parquet"))
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        now = stage(spark, now, str(tmp_path))
        path = str(tmp_path / name)
        now.write.parquet(path)
        now = spark.read.parquet(path)
        if k < 4:
            assert now.columns == frame.columns
        out.append(now.collect())
    # the classifier's rows are those it scores high
    score = {r.doc_id: r.predicted for r in quality.op4(spark, str(tmp_path)).collect()}
    assert sorted(r.doc_id for r in out[0]) == sorted(k for k, p in score.items() if p)
    good = {k for k, q, _ in labels if q == 1}
    assert len(good & {r.doc_id for r in out[0]}) > 0.97 * len(good)
    # of each group whose five-word shingle sets are linked by a Jaccard similarity of 0.8 one row stays
    assert sorted(r.doc_id for r in out[1]) == sorted(set(groups([r.doc_id for r in out[0]], [r.text for r in out[0]])))
    # secrets are gone, the rest is as it was
    before = {r.doc_id: r.text for r in out[1]}
    assert sorted(before) == sorted(r.doc_id for r in out[2])
    for r in out[2]:
        assert secrets_of(r.text)[:3] == (0, 0, 0)
        if not secrets_of(before[r.doc_id])[-1]:
            assert r.text == before[r.doc_id]
        assert r.n_chars == (None if r.text is None else len(r.text))
    # words by source follow the targets
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    total = sum(size(r.text) for r in out[2])
    assert abs(sum(size(r.text) for r in out[3]) - total) <= 3
    cleaned = {r.doc_id: r.text for r in out[2]}
    for r in out[3]:  # a row's words are the text's, or those of its drawn blocks in order
        words = iter((cleaned[r.doc_id] or "").split())
        assert all(w in words for w in r.text.split())
    # every token of every row has a place
    library = Tokenizer.from_file(tokens.vocabulary())
    want = sum(len(library.encode(r.text or "", add_special_tokens=False).ids) + 1 for r in out[3])
    assert sum(r.length for r in out[4]) == want
    held = {}
    for r in out[4]:
        held.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for places in held.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= packing.LIMIT
    assert mixing.MOST == 3


def test_run_equals_the_stages(spark, tmp_path):
    rows = [(k, f"plain words number {k} " * 10, "en", "a", 10) for k in range(30)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(k, 1, 0) for k in range(20)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    got = corpus_pipeline.run(spark, str(tmp_path))
    assert got.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    assert got.count() >= 1


def test_empty_table(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_stages_keep_columns_that_clash(spark, tmp_path):
    """Every stage but the last gives back the columns it got, whatever their names, with what they held."""
    names = ["_score", "_id", "_own", "_tie", "_blob", "blob", "path", "spans", "_size", "_taken", "_key", "_copy", "_turn", "row", "mark", "root", "size", "taken"]
    rows = [(k, f"plain words number {k} of this corpus, and token=abcdef{k:04d} too " * 3, "en", "ab"[k % 2], 1, *names) for k in range(12)]
    now = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{n}` string" for n in names))
    spark.createDataFrame([(k, 1, 0) for k in range(12)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES[:4]):
        columns = now.columns
        stage(spark, now, str(tmp_path)).write.parquet(str(tmp_path / name))
        now = spark.read.parquet(str(tmp_path / name))
        assert now.columns == columns
        got = now.collect()
        assert got and all(r[n] == n for r in got for n in names), name
