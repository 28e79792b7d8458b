import itertools
import math
import random
import zlib

import numpy as np
import pytest
from tokenizers import Tokenizer

from balclust.llm import packing, tokens


def check(plan, sizes, counts, room):
    """Every piece has one place, and the places of a sequence are gapless and within the room."""
    taken = {}
    for s, n in zip(sizes.tolist(), counts.tolist()):
        rows = np.flatnonzero(plan.length == s)
        firsts = plan.first[rows]
        assert (np.diff(firsts) > 0).all() and firsts[0] == 0
        for k, r in enumerate(rows):
            stop = firsts[k + 1] if k + 1 < len(rows) else n
            for x in range(firsts[k], stop):
                taken.setdefault(int(plan.sequence[r] + x - firsts[k]), []).append((int(plan.offset[r]), s))
    assert sorted(taken) == list(range(plan.sequences))
    for held in taken.values():
        at = 0
        for offset, s in sorted(held):
            assert offset == at
            at += s
        assert at <= room
    assert sum(map(len, taken.values())) == counts.sum()


@pytest.mark.parametrize("seed", range(6))
def test_plans_are_whole_and_tight(seed):
    rng = np.random.default_rng(seed)
    room = [4096, 4096, 100, 64, 4096, 1000][seed]
    sizes = np.unique(rng.integers(1, room + 1, [400, 3, 60, 64, 900, 30][seed]))
    counts = rng.integers(1, [60, 2000, 5, 3, 2, 9][seed], len(sizes))
    plan = packing.plan(sizes, counts, room)
    check(plan, sizes, counts, room)
    fit = sum(n for n, _ in packing._best_fit(sizes, counts, room))
    assert plan.sequences <= 1.01 * fit + 1


def test_small_plans_against_the_optimum():
    rng = random.Random(4)
    for _ in range(6):
        items = [rng.randint(1, 10) for _ in range(6)]
        best = min(max(used) + 1 for used in itertools.product(range(6), repeat=6) if all(sum(i for i, u in zip(items, used) if u == b) <= 10 for b in range(6)))
        sizes, counts = np.unique(items, return_counts=True)
        plan = packing.plan(sizes, counts, 10)
        check(plan, sizes, counts, 10)
        assert plan.sequences <= best + 1


def test_pricing_is_the_best_knapsack():
    rng = np.random.default_rng(2)
    for _ in range(20):
        sizes, values, most = rng.integers(1, 9, 4), rng.random(4), rng.integers(0, 4, 4)
        got = packing.price(values, sizes, most, 15)
        best = max(float(np.dot(values, c)) for c in itertools.product(*(range(m + 1) for m in most)) if np.dot(sizes, c) <= 15)
        assert (got <= most).all() and got @ sizes <= 15 and abs(got @ values - best) < 1e-9


def test_fractional_cover():
    sizes, counts = np.array([30, 40, 60, 70]), np.array([50, 30, 20, 10])
    configs, amounts = packing.solve(sizes, counts, 100, 2000)
    assert (configs @ sizes <= 100).all() and (amounts @ configs >= counts - 1e-3).all()
    assert amounts.sum() < 1.2 * (sizes @ counts) / 100


def test_query_is_whole(spark, tmp_path):
    texts = [None, "", "one", "é ü " * 9000, "w" * 3000, *(f"doc {k} " * (k * 7 % 900) for k in range(120)), "one", "one"]
    spark.createDataFrame([(None if k == 2 else k, t, 1) for k, t in enumerate(texts)], "doc_id long, text string, piece int").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    library = Tokenizer.from_file(tokens.vocabulary())
    want = []
    for k, t in enumerate(texts):
        ids = np.array([*library.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        want += [(None if k == 2 else k, p, s, len(ids[s : s + 4096]), zlib.crc32(ids[s : s + 4096].tobytes())) for p, s in enumerate(range(0, len(ids), 4096))]
    got = packing.op10(spark, str(tmp_path)).collect()
    assert sorted((tuple(r)[:5] for r in got), key=str) == sorted(want, key=str)
    held = {}
    for r in got:
        held.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for rows in held.values():
        at = 0
        for offset, length in sorted(rows):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(held) <= math.ceil(sum(w[3] for w in want) / 4096) + 2


def test_empty_table(spark):
    assert packing.pack(packing.pieces(spark.createDataFrame([], "doc_id long, text string"))).count() == 0


def test_the_program_goes_on_until_every_piece_has_its_place():
    rng = np.random.default_rng(3)
    sizes = np.unique(np.concatenate([rng.integers(2049, 4096, 600), rng.integers(1, 600, 500)]))
    counts = np.where(sizes > 2048, 1, rng.integers(1, 40, len(sizes)))
    configs, amounts = packing.solve(sizes, counts, 4096)
    assert (configs @ sizes <= 4096).all() and (amounts == np.round(amounts)).all()
    assert (amounts @ configs == counts).all()
    plan = packing.plan(sizes, counts)
    check(plan, sizes, counts, 4096)
    fit = sum(n for n, _ in packing._best_fit(sizes, counts, 4096))
    assert plan.sequences <= 1.001 * fit
