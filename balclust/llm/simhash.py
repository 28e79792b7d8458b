"""SimHash near-duplicates: fingerprints by majority vote, linked by a self-join of binary tries.

Two fingerprints within the error budget agree on at least one of BLOCKS equal bit blocks. For each
block a trie over the fingerprints, rotated so that the block leads, is joined with itself: pairs of
nodes go down together, add up the bits in which their paths differ, and are dropped once the sum
exceeds the budget. Pairs of small nodes are compared at once. The nodes of one leading block
lie in one task; a task gives a spanning forest of its links rather than all of them, so that groups of
copies cost no more than their size. Forests of all tasks become components by alternating star contraction.

The query's contract is three words and three bits. The pipeline's stage links what shares 0.8 of its five-word
shingles. Its candidates are the sets whose fingerprints the trie join links and, since pairs at 0.8 differ in
about ten of 64 bits, those that share a band of least hashes; each link is an exact comparison of shingle sets.

Defined cases: a null text has no words and fingerprint zero, which links like any other; a text of
fewer words than a shingle is one shingle; repeated rows each get their row; a null path counts for no
component's smallest; of rows alike in doc_id and text the stage keeps one; a text longer than a slice is one step; an empty table gives an empty result;
other columns, of whatever name, are ignored or come back as they were.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WORDS, BUDGET, SEED = 3, 3, 42
#: Bit blocks of which one must agree; one more than the budget. 64 / BLOCKS bits lead each trie.
BLOCKS = BUDGET + 1
LEAD = 64 // BLOCKS
#: Pairs that one step of the trie join holds, and the size of node pairs compared directly.
FRONTIER, DIRECT = 1 << 18, 64
#: The pipeline's stage: words in a shingle and the similarity of shingle sets that links. Two sets of that similarity share
#: no band key with a chance of (1 - LEAST ** PER_BAND) ** BANDS, 1.3 in ten million.
STAGE_WORDS, LEAST, BANDS, PER_BAND = 5, 0.8, 40, 5
#: Tasks that the links of one node may be dealt to.
SALTS = 32


def shingle_hashes(text: bytes, words: int = WORDS) -> list[int]:
    """XXH64 of each run of so many lower-cased words, repeats included."""
    parts = text.lower().split()
    if not parts:
        return []
    line, n = b" ".join(parts), max(1, len(parts) - words + 1)
    stop = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    start = np.append(0, stop[:-1] + 1)
    digest = xxhash.xxh64_intdigest
    return [digest(line[a:b], SEED) for a, b in zip(start[:n].tolist(), stop[len(parts) - n :].tolist(), strict=True)]


def majority(hashes: list[np.ndarray]) -> np.ndarray:
    """The fingerprint of each array of hashes: bits set in over half of them."""
    out = np.zeros(len(hashes), np.uint64)
    size = np.array([len(h) for h in hashes], np.int64)
    full = np.flatnonzero(size)
    if not len(full):
        return out
    flat = np.concatenate([hashes[k] for k in full])
    heads = np.append(0, np.cumsum(size[full])[:-1])
    for byte in range(8):
        bits = np.unpackbits(((flat >> np.uint64(8 * byte)) & np.uint64(255)).astype(np.uint8)[:, None], axis=1, bitorder="little")
        votes = np.add.reduceat(bits, heads, axis=0, dtype=np.int64)
        won = np.packbits(2 * votes > size[full, None], axis=1, bitorder="little")[:, 0]
        out[full] |= won.astype(np.uint64) << np.uint64(8 * byte)
    return out


def _fingerprints(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, "text", common.SLICE_BYTES // 2):
            marks = majority([np.array(shingle_hashes(t, words), np.uint64) for t in common.raw_texts(part)])
            yield pa.RecordBatch.from_arrays([common.column(part, "doc_id"), common.column(part, "tie"), pa.array(marks.view(np.int64))], ["doc_id", "tie", "mark"])

    return run


def fingerprints(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """doc_id, tie (a hash of the text) and mark (the fingerprint as a signed number) of each row of docs (doc_id, text)."""
    return docs.select("doc_id", "text", F.xxhash64("text").alias("tie")).mapInArrow(_fingerprints(words), "doc_id long, tie long, mark long")


def _product(lo1: np.ndarray, hi1: np.ndarray, lo2: np.ndarray, hi2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All places (i of the first range, j of the second) of each pair of ranges."""
    wide = hi2 - lo2
    size = (hi1 - lo1) * wide
    within = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    wide = np.repeat(wide, size)
    return np.repeat(lo1, size) + within // wide, np.repeat(lo2, size) + within % wide


def trie_links(marks: np.ndarray, lead: int = LEAD, budget: int = BUDGET) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places i < j of all pairs of the sorted, distinct marks that agree on the leading bits and differ in at most budget bits."""
    n = len(marks)
    if n < 2:
        return
    tops = marks >> np.uint64(64 - lead)
    heads = np.flatnonzero(np.append(True, tops[1:] != tops[:-1]))
    ends = np.append(heads[1:], n)
    ones: dict[int, np.ndarray] = {}

    def middle(lo: np.ndarray, hi: np.ndarray, bit: int) -> np.ndarray:
        if bit not in ones:
            ones.clear()  # the deepest frontier goes first, so levels come back in runs
            ones[bit] = np.append(0, np.cumsum((marks >> np.uint64(bit)) & np.uint64(1), dtype=np.int64))
        return hi - (ones[bit][hi] - ones[bit][lo])

    waiting = [(63 - lead, np.stack([heads, ends, heads, ends, np.zeros_like(heads)]))]
    while waiting:
        bit, pairs = waiting.pop()
        if pairs.shape[1] > FRONTIER:
            half = pairs.shape[1] // 2
            waiting += [(bit, pairs[:, half:]), (bit, pairs[:, :half])]
            continue
        lo1, hi1, lo2, hi2, off = pairs
        small = ((hi1 - lo1) * (hi2 - lo2) <= DIRECT) | (bit < 0)
        if small.any():
            i, j = _product(lo1[small], hi1[small], lo2[small], hi2[small])
            near = (i < j) & (np.bitwise_count(marks[i] ^ marks[j]) <= budget)
            yield i[near], j[near]
        lo1, hi1, lo2, hi2, off = pairs[:, ~small]
        if not len(lo1):
            continue
        alone = lo1 == lo2
        m1, m2 = middle(lo1, hi1, bit), middle(lo2, hi2, bit)
        two = ~alone
        children = np.concatenate([
            np.stack([lo1, m1, lo2, m2, off]), np.stack([m1, hi1, m2, hi2, off]), np.stack([lo1, m1, m2, hi2, off + 1]),
            np.stack([m1[two], hi1[two], lo2[two], m2[two], off[two] + 1]),
        ], axis=1)
        live = (children[0] < children[1]) & (children[2] < children[3]) & (children[4] <= budget)
        live &= (children[0] != children[2]) | (children[1] - children[0] > 1)
        waiting.append((bit - 1, children[:, live]))


def contract(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Labels (the smallest place in each component) once links i-j are added."""
    a, b = label[i], label[j]
    while True:
        apart = a != b
        a, b = a[apart], b[apart]
        if not len(a):
            return label
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
        a, b = label[a], label[b]


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of a spanning forest of what this task's tries link; a task holds whole leading blocks."""
    parts = [(common.column(b, "block").to_numpy(), common.column(b, "turned").to_numpy()) for b in batches if b.num_rows]
    if not parts:
        return
    block, turned = (np.concatenate(x) for x in zip(*parts, strict=True))
    for k in range(BLOCKS):
        marks = np.unique(turned[block == k].view(np.uint64))
        label = np.arange(len(marks))
        for i, j in trie_links(marks):
            label = contract(label, i, j)
        moved = np.flatnonzero(label != np.arange(len(marks)))
        back = np.uint64(LEAD * k)
        straight = (marks >> back | marks << (np.uint64(64) - back)) if k else marks
        yield pa.RecordBatch.from_arrays([pa.array(straight[moved].view(np.int64)), pa.array(straight[label[moved]].view(np.int64))], ["a", "b"])


def links(marks: DataFrame) -> DataFrame:
    """a, b: links whose components are those of all pairs of marks within the budget. marks: mark, distinct."""
    turned = marks.select(F.col("mark"), F.explode(F.array(*(F.lit(k) for k in range(BLOCKS)))).alias("block")).select(
        "block", F.when(F.col("block") == 0, F.col("mark")).otherwise(F.expr(f"(mark << ({LEAD} * block)) | (mark >>> (64 - {LEAD} * block))")).alias("turned")
    )
    dealt = turned.repartition("block", F.expr(f"turned >>> {64 - LEAD}"))
    return dealt.mapInArrow(_forest, "a long, b long")


def with_least(rows: DataFrame, key: str, value: str, deal: str) -> DataFrame:
    """rows with m, the least value of their key. The rows of one key are dealt to up to SALTS tasks by a hash of deal; none but the salts that a key has are joined."""
    dealt = rows.withColumn("salt", F.pmod(F.xxhash64(deal), F.lit(SALTS)))
    least = dealt.groupBy(key).agg(F.min(value).alias("m"), F.collect_set("salt").alias("salts")).select(key, "m", F.explode("salts").alias("salt"))
    return dealt.join(least, [key, "salt"]).drop("salt")


def components(edges: DataFrame) -> DataFrame:
    """node, root: the smallest node that each node of edges (a, b) reaches."""
    edges = common.stage(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a != b").distinct())
    while True:
        # Done once every node points to one other that points nowhere.
        forks = edges.groupBy("a").count().where("count > 1").select("a")
        chains = edges.join(edges.select(F.col("b").alias("a")).distinct(), "a", "left_semi").select("a")
        if forks.unionByName(chains).isEmpty():
            return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        # Large neighbours of each node move to its smallest one, ...
        wide = with_least(both, "a", "b", "b").where("b > a").select(F.col("b").alias("a"), F.least("m", "a").alias("b")).distinct()
        # ... then the small ones, with the node itself.
        met = with_least(wide, "a", "b", "b")
        near = met.select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b"))
        before, edges = edges, common.stage(near.distinct())
        common.drop(edges.sparkSession, before)


def near_duplicates(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """doc_id, tie, mark, root (the smallest mark reachable) and component_id (the smallest doc_id reachable) of each row of docs (doc_id, text)."""
    marked = common.stage(fingerprints(docs, words))
    marks = common.stage(marked.groupBy("mark").agg(F.min("doc_id").alias("least")))
    found = components(links(marks.select("mark")))
    members = found.unionByName(found.select(F.col("root").alias("node"), "root").distinct())
    held = members.join(marks, members.node == marks.mark).select("mark", "root", "least")
    joined = with_least(held, "root", "least", "mark").select("mark", "root", F.col("m").alias("component_id"))
    named = marks.join(joined, "mark", "left").select("mark", F.coalesce("root", "mark").alias("root"), F.coalesce("component_id", "least").alias("component_id"))
    return marked.join(common.stage(named), "mark").select("doc_id", "tie", "mark", "root", "component_id")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(common.documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("mark"), 16, "0")).alias("fingerprint"), "component_id")


def _bands(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc_id, tie, node (a hash of the shingle set), mark (its fingerprint) and keys (its band keys) of each row."""
    for part in common.slices(batches, "text", common.SLICE_BYTES // 2):
        sets = [shingle_set(t) for t in common.raw_texts(part)]
        nodes = np.array([xxhash.xxh64_intdigest(s.tobytes(), SEED) for s in sets], np.uint64)
        marks = majority(sets)
        keys = [row.tobytes() for row in band_keys(sets)]
        yield pa.RecordBatch.from_arrays(
            [common.column(part, "doc_id"), common.column(part, "tie"), pa.array(nodes.view(np.int64)), pa.array(marks.view(np.int64)), pa.array(keys, pa.binary())], ["doc_id", "tie", "node", "mark", "keys"]
        )


def shingle_set(text: bytes, words: int = STAGE_WORDS) -> np.ndarray:
    return np.unique(np.array(shingle_hashes(text, words), np.uint64))


def band_keys(sets: list[np.ndarray]) -> np.ndarray:
    """For each set one 64-bit key a band, made of the least values of PER_BAND permutations; all empty sets have the same."""
    out = np.zeros((len(sets), BANDS), np.uint64)
    full = np.flatnonzero([len(s) for s in sets])
    if not len(full):
        return out
    flat = (np.concatenate([sets[k] for k in full]) >> np.uint64(32)).astype(np.uint32)
    heads = np.append(0, np.cumsum([len(sets[k]) for k in full])[:-1])
    turns = common.mix(np.arange(1, BANDS * PER_BAND + 1, dtype=np.uint64))
    odd, shift = (turns | np.uint64(1)).astype(np.uint32), (turns >> np.uint64(32)).astype(np.uint32)
    for band in range(BANDS):
        key = np.full(len(full), band + 1, np.uint64)
        for f in range(band * PER_BAND, (band + 1) * PER_BAND):
            key = common.mix(key * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat((flat ^ shift[f]) * odd[f], heads).astype(np.uint64))
        out[full, band] = key
    return out


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A spanning forest of the nodes that share a band key; a task holds whole keys."""
    parts = [(common.column(b, "key").to_numpy(), common.column(b, "node").to_numpy()) for b in batches if b.num_rows]
    if not parts:
        return
    key, node = (np.concatenate(x) for x in zip(*parts, strict=True))
    names, place = np.unique(node, return_inverse=True)
    order = np.argsort(key, kind="stable")
    same = np.flatnonzero(key[order][1:] == key[order][:-1])
    label = contract(np.arange(len(names)), place[order[same]], place[order[same + 1]])
    moved = np.flatnonzero(label != np.arange(len(names)))
    yield pa.RecordBatch.from_arrays([pa.array(names[moved]), pa.array(names[label[moved]])], ["a", "b"])


#: Bytes of one group's table of shared shingles; of a larger one pairs are compared set by set.
TABLE = 256 << 20


def _shared(sets: list[np.ndarray]) -> np.ndarray | None:
    """A row of bits for each set, one bit for each shingle that two sets or more hold; None if the table would be too large."""
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, place, times = np.unique(flat, return_inverse=True, return_counts=True)
    column = np.cumsum(times > 1) - 1
    wide = -(-int((times > 1).sum()) // 64)
    if len(sets) * wide * 8 > TABLE:
        return None
    out = np.zeros((len(sets), max(1, wide)), np.uint64)
    held = times[place] > 1
    at = column[place[held]]
    np.bitwise_or.at(out, (owner[held], at >> 6), np.uint64(1) << (at & 63).astype(np.uint64))
    return out


def alike(sets: list[np.ndarray], keys: np.ndarray, least: float = LEAST) -> np.ndarray:
    """Labels (the smallest place of each component) of the sets linked by a Jaccard similarity of at least so much. Pairs without a common key are not compared.

    A set meets all those before it in its bucket at once, by the bits of the shingles that they share.
    """
    label, size = np.arange(len(sets)), np.array([len(s) for s in sets])
    bits = _shared(sets)
    for band in range(keys.shape[1]):
        order = np.argsort(keys[:, band], kind="stable")
        cuts = np.flatnonzero(np.diff(keys[order, band])) + 1
        for bucket in np.split(order, cuts):
            if len(bucket) < 2 or (label[bucket] == label[bucket[0]]).all():
                continue
            for k in range(1, len(bucket)):
                j, others = bucket[k], bucket[:k]
                others = others[(label[others] != label[j]) & (np.minimum(size[others], size[j]) >= least * np.maximum(size[others], size[j]) - 1e-9)]
                if not len(others):
                    continue
                if bits is None:
                    both = np.array([len(np.intersect1d(sets[i], sets[j], assume_unique=True)) for i in others])
                else:
                    both = np.bitwise_count(bits[others] & bits[j]).sum(axis=1, dtype=np.int64)
                near = others[both >= least * (size[others] + size[j] - both) - 1e-9]
                if len(near):
                    joined = np.unique(np.append(label[near], label[j]))
                    label[np.isin(label, joined)] = joined[0]
    return label


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node, root of the nodes of each group, by an exact comparison of their shingle sets. Rows come sorted by group."""
    names, sets, keys, group = [], [], [], None

    def done() -> pa.RecordBatch:
        label = alike(sets, np.stack(keys))
        return pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array([names[k] for k in label], pa.int64())], ["node", "root"])

    for part in (p for b in batches for p in common.slices(iter([b]), "text")):
        for g, node, key, text in zip(common.column(part, "group").to_pylist(), common.column(part, "node").to_pylist(), common.column(part, "keys").to_pylist(), common.raw_texts(part), strict=True):
            if g != group:
                if names:
                    yield done()
                names, sets, keys, group = [], [], [], g
            names.append(node)
            sets.append(shingle_set(text))
            keys.append(np.frombuffer(key, np.uint64))
    if names:
        yield done()


def marked_roots(nodes: DataFrame) -> DataFrame:
    """node, near: nodes (node, mark) whose fingerprints are linked within the budget by the trie join have one near, the smallest mark reachable."""
    found = components(links(nodes.select("mark").distinct()))
    return nodes.select("node", "mark").join(found.select(F.col("node").alias("mark"), "root"), "mark", "left").select("node", F.coalesce("root", "mark").alias("near"))


def near_copies(docs: DataFrame) -> DataFrame:
    """doc_id, tie and root of each row of docs (doc_id, text): rows linked by a similarity of at least LEAST of their sets of five-word shingles share a root.

    Candidates are sets whose fingerprints the trie join links, and beside them, for those too far apart for its budget, sets that share a band key.
    Each group of candidates is then compared set by set in one task, linked fingerprints first; every distinct set's text moves there once.
    """
    hashed = docs.select("doc_id", "text", F.xxhash64("text").alias("tie"))
    marked = common.stage(hashed.mapInArrow(_bands, "doc_id long, tie long, node long, mark long, keys binary"))
    held = marked.groupBy("node").agg(F.min(F.coalesce("tie", F.lit(0))).alias("tie"), F.min("mark").alias("mark"), F.min("keys").alias("keys"))
    near = common.stage(marked_roots(held))
    # What the trie join found is the first of a node's keys; the keys of bands follow.
    nodes = held.join(near, "node").select("node", "tie", F.concat(F.unhex(F.lpad(F.hex("near"), 16, "0")), "keys").alias("keys"))
    width = 8
    cut = F.explode(F.expr(f"transform(sequence(0, {BANDS}), b -> xxhash64(b, substring(keys, b * {width} + 1, {width})))"))
    met = components(nodes.select("node", cut.alias("key")).repartition("key").mapInArrow(_meet, "a long, b long"))
    groups = met.unionByName(met.select(F.col("root").alias("node"), "root").distinct()).select("node", F.col("root").alias("group"))
    chosen = nodes.join(groups, "node")
    texts = hashed.select("tie", "text").join(chosen, "tie").dropDuplicates(["node"])
    found = common.stage(texts.select("group", "node", "keys", "text").repartition("group").sortWithinPartitions("group").mapInArrow(_compare, "node long, root long"))
    return marked.join(found, "node", "left").select("doc_id", "tie", F.coalesce("root", "node").alias("root"))


def keep_one(docs: DataFrame) -> DataFrame:
    """docs with one row of each component of near copies: that of the smallest doc_id (null last), then of the smallest hash of the text."""
    best = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tie")).alias("best")
    kept = near_copies(docs).groupBy("root").agg(best).select("best.doc_id", "best.tie")
    hashed = common.as_row(docs).select("row", F.col("row.doc_id").alias("id"), F.xxhash64("row.text").alias("hash"))
    met = hashed.join(kept, F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("hash") == F.col("tie")))
    return common.from_row(met.dropDuplicates(["id", "hash"]), docs.columns)
