import random

import numpy as np
import pytest
import xxhash

from balclust.llm import simhash


def brute_mark(text, words=3):
    parts = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").translate({k: " " for k in (9, 10, 11, 12, 13)}).split(" ")
    parts = [p for p in parts if p]
    grams = [" ".join(parts[k : k + words]) for k in range(len(parts) - words + 1)] or [" ".join(parts)] * bool(parts)
    h = [xxhash.xxh64(g.encode(), seed=42).intdigest() for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(ids, marks):
    label = list(range(len(marks)))

    def root(k):
        while label[k] != k:
            k = label[k]
        return k

    for i in range(len(marks)):
        for j in range(i):
            if (marks[i] ^ marks[j]).bit_count() <= 3:
                label[root(i)] = root(j)
    groups = {}
    for k in range(len(marks)):
        groups.setdefault(root(k), []).append(ids[k])
    smallest = {r: min((i for i in g if i is not None), default=None) for r, g in groups.items()}
    return [smallest[root(k)] for k in range(len(marks))]


def corpus():
    rng = random.Random(3)
    texts = [None, "", " \t", "One", "one two", "ONE two\x0bthree", "é É Ü word ſ", "a b c d " * 3000]
    for k in range(40):
        words = [f"w{rng.randrange(400)}" for _ in range(rng.choice([5, 60, 400]))]
        texts.append(" ".join(words))
        for _ in range(rng.choice([0, 1, 3])):
            near = list(words)
            near[rng.randrange(len(near))] = "changed"
            texts.append(" ".join(near))
    return texts + texts[:6]


def test_query_equals_brute_force(spark, tmp_path):
    texts = corpus()
    ids = [None if k == 5 else 1000 - k for k in range(len(texts))]
    spark.createDataFrame([(i, t, "x") for i, t in zip(ids, texts)], "doc_id long, text string, mark string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    marks = [brute_mark(t) for t in texts]
    want = sorted(((i, f"{m:016x}", c) for i, m, c in zip(ids, marks, brute_components(ids, marks))), key=str)
    assert sorted(map(tuple, simhash.op9(spark, str(tmp_path)).collect()), key=str) == want


@pytest.mark.parametrize("frontier", [4, 1 << 18])
def test_trie_join_finds_every_pair(frontier, monkeypatch):
    monkeypatch.setattr(simhash, "FRONTIER", frontier)
    monkeypatch.setattr(simhash, "DIRECT", 2)
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 16, 60, dtype=np.uint64)
    flips = np.uint64(1) << rng.integers(0, 64, (4, 600)).astype(np.uint64)
    marks = np.unique(rng.choice(base, 600) ^ flips[0] ^ np.where(rng.random(600) < 0.5, flips[1], np.uint64(0)))
    got = set()
    for lead in range(4):
        turn = np.uint64(16 * lead)
        turned = marks if not lead else marks << turn | marks >> (np.uint64(64) - turn)
        order = np.argsort(turned)
        for i, j in simhash.trie_links(turned[order]):
            pairs = [tuple(sorted(p)) for p in zip(order[i].tolist(), order[j].tolist())]
            assert len(set(pairs)) == len(pairs)
            got.update(pairs)
    want = {(i, j) for j in range(len(marks)) for i in range(j) if int(marks[i] ^ marks[j]).bit_count() <= 3}
    assert got == want and len(want) > 100


def test_components_of_hubs_and_chains_of_hubs(spark):
    """Stars of many more links than salts, joined by chains, and one whose hub is its largest node."""
    edges = [(0, k) for k in range(1, 300)] + [(299, 1000)] + [(1000, 1000 + k) for k in range(1, 200)] + [(5000, k) for k in range(4000, 4100)]
    edges += [(b, a) for a, b in edges[::7]] + edges[:20]
    got = {r.node: r.root for r in simhash.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    nodes = {x for e in edges for x in e}
    assert got == {n: 0 if n < 4000 else 4000 for n in nodes - {0, 4000}}


def test_least_of_a_key_keeps_rows(spark):
    rows = spark.createDataFrame([(1, k % 90, k) for k in range(500)] + [(2, None, 7), (3, 5, 1)], "key long, value long, deal long")
    got = simhash.with_least(rows, "key", "value", "deal")
    assert got.count() == 502
    assert {(r.key, r.m) for r in got.collect()} == {(1, 0), (2, None), (3, 5)}


def test_components_of_chains_and_stars(spark):
    edges = [(k, k + 1) for k in range(60)] + [(1000, 1000 + k) for k in range(1, 80)] + [(2001, 2000), (2000, 2001), (3000, 3000)]
    got = {r.node: r.root for r in simhash.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(1, 61)} | {1000 + k: 1000 for k in range(1, 80)} | {2001: 2000}
    assert simhash.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_one_row_of_each_component_stays(spark):
    df = spark.createDataFrame([(2, "a b c d"), (1, "A b c d"), (1, "A b c d"), (None, "other words here now"), (None, "quite different again so"), (5, None), (6, "")], "doc_id long, text string")
    assert sorted(map(tuple, simhash.keep_one(df).collect()), key=str) == sorted([(1, "A b c d"), (None, "other words here now"), (None, "quite different again so"), (5, None)], key=str)
    assert simhash.keep_one(df.limit(0)).count() == 0


def five_word_set(text):
    parts = (text or "").lower().split()
    return {" ".join(parts[k : k + 5]) for k in range(max(1, len(parts) - 4))} if parts else set()


def test_stage_links_what_shares_four_fifths_of_its_shingles(spark):
    rng = random.Random(11)
    texts = []
    for _ in range(12):
        words = [f"w{rng.randrange(5000)}" for _ in range(200)]
        texts.append(" ".join(words))
        for edits in (1, 2, 3, 4, 5, 6, 8):
            near = list(words)
            for at in rng.sample(range(len(near)), edits):
                near[at] = f"new{rng.randrange(10**6)}"
            texts.append(" ".join(near))
    sets = [five_word_set(t) for t in texts]
    label = list(range(len(texts)))
    far = 0
    for i in range(len(texts)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                far += (brute_mark(texts[i]) ^ brute_mark(texts[j])).bit_count() > 3
                label = [label[j] if x == label[i] else x for x in label]
    assert far > 20 and len(set(label)) > 12
    first = {}
    for k, x in enumerate(label):
        first.setdefault(x, k)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    assert sorted(r.doc_id for r in simhash.keep_one(df).collect()) == sorted(first.values())


def test_kept_rows_keep_columns_of_any_name(spark):
    names = ["_id", "_tie", "_own", "tie", "hash", "root", "row", "id"]
    df = spark.createDataFrame([(k, "one two three four five six", *names) for k in (4, 2, 2)], "doc_id long, text string, " + ", ".join(f"`{n}` string" for n in names))
    assert [tuple(r) for r in simhash.keep_one(df).collect()] == [(2, "one two three four five six", *names)]


def test_groups_by_bits_equal_all_pairs(monkeypatch):
    """Sets of near copies and others: labels of all pairs compared plainly, with the table of bits and without."""
    rng = random.Random(6)
    words = [f"w{k}" for k in range(400)]
    bases = [[rng.choice(words) for _ in range(60)] for _ in range(4)]
    texts = [b"", b"one", b"ONE"]
    for k in range(90):
        x = list(bases[k % 4])
        for _ in range(rng.randrange(5)):
            x[rng.randrange(60)] = rng.choice(words)
        texts.append(" ".join(x).encode())
    sets = [simhash.shingle_set(t) for t in texts]
    want = list(range(len(sets)))
    for i in range(len(sets)):
        for j in range(i):
            both = len(set(sets[i].tolist()) & set(sets[j].tolist()))
            if 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both):
                low, high = sorted((want[i], want[j]))
                want = [low if x == high else x for x in want]
    for table in (simhash.TABLE, 0):
        monkeypatch.setattr(simhash, "TABLE", table)
        assert simhash.alike(sets, simhash.band_keys(sets)).tolist() == want


def test_stage_takes_candidates_from_fingerprints(spark, monkeypatch):
    """the trie join links the fingerprints of the stage's sets; what it links is compared although no band is shared, and the comparison decides."""
    rng = random.Random(4)
    words = [f"w{rng.randrange(5000)}" for _ in range(600)]
    texts = [" ".join(words), " ".join(words[:-1] + ["changed"]), " ".join(words[300:] + words[:20])]
    sets = [simhash.shingle_set(t.encode()) for t in texts]
    marks = simhash.majority(sets).view(np.int64).tolist()
    assert (marks[0] ^ marks[1]).bit_count() <= simhash.BUDGET
    near = simhash.marked_roots(spark.createDataFrame([*enumerate(marks), (3, marks[0])], "node long, mark long"))
    near = {r.node: r.near for r in near.collect()}
    assert near == {0: min(marks[:2]), 1: min(marks[:2]), 2: marks[2], 3: min(marks[:2])}
    keys = np.array([[near[k] & 0xFFFF, 10 + k] for k in range(3)], np.uint64)
    assert simhash.alike(sets, keys).tolist() == [0, 0, 2]
    assert simhash.alike(sets, np.array([[1, 10 + k] for k in range(3)], np.uint64)).tolist() == [0, 0, 2]
    asked, links = [], simhash.links
    monkeypatch.setattr(simhash, "links", lambda m: asked.extend(r.mark for r in m.collect()) or links(m))
    assert sorted(r.doc_id for r in simhash.keep_one(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()) == [0, 2]
    assert sorted(asked) == sorted(set(marks))
