"""Token counts by rank-synchronous merging of ragged arrays.

Texts become one byte array, cut into pre-tokens by class tables; all new pre-tokens of a slice
become one flat symbol array with one run per pre-token. In each round every run
finds its adjacent pair of lowest rank and merges all of that pair's occurrences at once;
rounds go on until no run has a ranked pair. The symbols that survive are the tokens.

ASCII white space never joins tokens, so a text is the sum of its words. Words with an apostrophe,
a "<" or a point from 0x180 on are normalised and cut by the vocabulary file's own rules instead,
and those with a special string are encoded by the library. A bounded memo spares known runs.

Defined cases: a null text is empty; the empty text has no tokens; a text longer than a slice is one step, whose arrays take about
60 bytes a byte of it; repeated rows each get their row (there are no ties to break); an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import json
import os
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common

LIMIT = 2048
#: Pre-tokens that a worker remembers; beyond that it starts anew.
MEMO = 400_000


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    """Where the installed vocabulary package keeps a file."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


class MergeRanks:
    """Pair ranks of a byte-pair vocabulary, looked up for whole arrays of pairs."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            file = json.load(f)
        model = file["model"]
        self.suffix = model.get("end_of_word_suffix") or ""
        self.ids: dict[str, int] = model["vocab"]
        self.special = [a["content"].encode() for a in file["added_tokens"]]
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        self.size = max(self.ids.values()) + 1
        key = np.array([self.ids[a] * self.size + self.ids[b] for a, b in pairs], np.int64)
        made = np.array([self.ids[a + b] for a, b in pairs], np.int64)
        order = np.argsort(key, kind="stable")
        self.key, self.rank, self.made_by_rank = key[order], order, made
        # A sparse table answers for nearly all pairs; those whose place another pair took are looked up in the sorted keys.
        self.slot_key, self.slot_rank = np.full(1 << 20, -1, np.int64), np.zeros(1 << 20, np.int32)
        place = self._slot(key)
        self.slot_key[place], self.slot_rank[place] = key, np.arange(len(key))

    @staticmethod
    def _slot(key: np.ndarray) -> np.ndarray:
        return (key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(44)).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The rank of each pair; the number of merges where there is none."""
        wanted = left * self.size + right
        place = self._slot(wanted)
        held = self.slot_key[place]
        out = np.where(held == wanted, self.slot_rank[place], len(self.key))
        other = np.flatnonzero((held != wanted) & (held >= 0))
        at = np.minimum(np.searchsorted(self.key, wanted[other]), len(self.key) - 1)
        out[other] = np.where(self.key[at] == wanted[other], self.rank[at], len(self.key))
        return out

    def merge(self, symbols: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbols, and how many of each run, that are left once no pair has a rank. Runs are laid end to end."""
        none, runs = len(self.key), len(length)
        owner = np.repeat(np.arange(runs), length)
        kept: list[tuple[np.ndarray, np.ndarray]] = []
        while len(symbols):
            joined = owner[1:] == owner[:-1]
            rank = np.full(len(symbols), none, np.int64)
            rank[:-1][joined] = self.ranks(symbols[:-1][joined], symbols[1:][joined])
            heads = np.flatnonzero(np.append(True, ~joined))
            least = np.minimum.reduceat(rank, heads)
            size = np.diff(np.append(heads, len(symbols)))
            live = least < none
            moving = np.repeat(live, size)
            kept.append((owner[~moving], symbols[~moving]))
            # In a chain of overlapping hits (a a a) every second one merges, from the left.
            place = np.flatnonzero(moving & (rank == np.repeat(least, size)))
            if not len(place):
                break
            chain = np.append(True, (np.diff(place) > 1) | ~joined[place[1:] - 1])
            start = np.maximum.accumulate(np.where(chain, np.arange(len(place)), 0))
            place = place[(np.arange(len(place)) - start) % 2 == 0]
            symbols = symbols.copy()
            symbols[place] = self.made_by_rank[rank[place]]
            moving[place + 1] = False
            symbols, owner = symbols[moving], owner[moving]
        if not kept:
            return symbols, np.zeros(runs, np.int64)
        owner, symbols = (np.concatenate(x) for x in zip(*kept, strict=True))
        order = np.argsort(owner, kind="stable")
        return symbols[order], np.bincount(owner, minlength=runs)

    def odd_words(self, words: list[bytes]) -> list[list[int]]:
        """Token ids of words that the fast splitter leaves out, split by the library (words with special strings: encoded by it)."""
        out: list[list[int]] = [[] for _ in words]
        pieces, owner = [], []
        for k, w in enumerate(words):
            text = w.decode("utf-8", "replace")
            if any(s in w for s in self.special):
                out[k] = self.library.encode(text, add_special_tokens=False).ids
                continue
            for piece, _ in self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(text)):
                if piece:
                    pieces.append(piece)
                    owner.append(k)
        runs = [[s for s in [*map(self.ids.get, p[:-1]), self.ids.get(p[-1] + self.suffix)] if s is not None] for p in pieces]  # a symbol outside the vocabulary makes no token
        left, size = self.merge(np.array([s for r in runs for s in r], np.int64), np.array([len(r) for r in runs], np.int64))
        for k, ids in zip(owner, np.split(left, np.cumsum(size)[:-1]) if runs else [], strict=True):
            out[k].extend(ids.tolist())
        return out


def _byte_symbols(ranks: MergeRanks) -> tuple[np.ndarray, np.ndarray]:
    """Symbol ids of each byte, inside a pre-token and at its end; printable bytes stand for themselves, the others for the points from 256 on, in order."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    points = dict(zip(plain, plain, strict=True))
    points |= {b: 256 + k for k, b in enumerate(b for b in range(256) if b not in points)}
    inner = np.array([ranks.ids[chr(points[b])] for b in range(256)], np.int64)
    return inner, np.array([ranks.ids[chr(points[b]) + ranks.suffix] for b in range(256)], np.int64)


def _point_tables() -> tuple[np.ndarray, np.ndarray]:
    """For points below 0x180: lower case, and class (0 space, 1 letter, 2 number, 3 other, 4 not for the fast splitter)."""
    lower, kind = np.arange(0x180), np.zeros(0x180, np.uint8)
    for p in range(0x180):
        c = chr(p)
        lower[p] = ord(c.lower()) if len(c.lower()) == 1 else p
        kind[p] = 0 if c in " \t\n\v\f\r\x85\xa0" else {"L": 1, "N": 2}.get(unicodedata.category(c)[0], 3)
        if c in "'<" or len(c.lower()) != 1 or lower[p] >= 0x180:
            kind[p] = 4
    return lower, kind


class Encoder:
    """Token ids of many texts at a time. Pre-tokens met before are remembered by a 64-bit hash, up to MEMO of them."""

    def __init__(self, path: str):
        self.ranks = MergeRanks(path)
        self.inner, self.last = _byte_symbols(self.ranks)
        lower, kind = _point_tables()
        self.kind1 = np.full(256, 4, np.uint8)
        self.kind1[:128] = kind[:128]
        self.lower1 = np.arange(256, dtype=np.uint8)
        self.lower1[:128] = lower[:128]
        self.lower, self.kind = lower, kind
        self.odd: dict[bytes, list[int]] = {}
        #: Ids of the odd words of the slice at hand; places beyond the store's end mean these.
        self.extra = np.zeros(0, np.int32)
        self.forget()

    def forget(self) -> None:
        self.known, self.start, self.size, self.store = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int32)

    def _lookup(self, keys: np.ndarray, low: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the ids of each run lie in self.store, and how many."""
        if len(self.known) > MEMO:
            self.forget()
        distinct, first, back = np.unique(keys, return_index=True, return_inverse=True)
        at = np.searchsorted(self.known, distinct)
        fresh = np.ones(len(distinct), bool) if not len(self.known) else self.known[np.minimum(at, len(self.known) - 1)] != distinct
        a, b = starts[first[fresh]], stops[first[fresh]]
        length = b - a
        ends = np.cumsum(length)
        data = low[np.repeat(a - ends + length, length) + np.arange(ends[-1] if len(ends) else 0)]
        symbols = self.inner[data]
        symbols[ends - 1] = self.last[data[ends - 1]]
        left, size = self.ranks.merge(symbols, length)
        begin = len(self.store) + np.cumsum(size) - size
        self.store = np.concatenate([self.store, left.astype(np.int32)])
        known = np.concatenate([self.known, distinct[fresh]])
        order = np.argsort(known)
        self.known, self.start, self.size = known[order], np.concatenate([self.start, begin])[order], np.concatenate([self.size, size])[order]
        at = np.searchsorted(self.known, distinct)[back]
        return self.start[at], self.size[at]

    def runs(self, data: np.ndarray, where: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place in the bytes, begin in self.store followed by self.extra, number of ids) of each pre-token or odd word, in order."""
        kind, low = self.kind1[data], self.lower1[data]
        lead = np.flatnonzero((data >= 0xC2) & (data <= 0xC5))
        point = ((data[lead].astype(np.int64) & 0x1F) << 6) | (data[np.minimum(lead + 1, len(data) - 1)] & 0x3F)
        low_point = self.lower[point]
        kind[lead] = kind[lead + 1] = self.kind[point]
        low[lead], low[lead + 1] = 0xC0 | (low_point >> 6), 0x80 | (low_point & 0x3F)
        tail = np.zeros(len(data), bool)
        tail[lead + 1] = True
        odd_place, self.extra = np.zeros(0, np.int64), np.zeros(0, np.int32)
        odd_ids: list[list[int]] = []
        if (kind == 4).any():
            starts, stops = common.word_runs(data, where)
            odd = np.add.reduceat(kind == 4, starts) > 0
            starts, stops = starts[odd], stops[odd]
            body = data.tobytes()
            words = [body[a:b] for a, b in zip(starts.tolist(), stops.tolist(), strict=True)]
            fresh = list(set(words) - self.odd.keys())
            if len(self.odd) + len(fresh) > MEMO // 4:
                self.odd.clear()
                fresh = list(set(words))
            self.odd.update(zip(fresh, self.ranks.odd_words(fresh), strict=True))
            odd_place, odd_ids = starts, [self.odd[w] for w in words]
            cover = np.zeros(len(data) + 1, np.int8)
            cover[starts] += 1
            cover[stops] -= 1
            kind[np.cumsum(cover[:-1], dtype=np.int8) > 0] = 0
        first = kind > 0
        same = kind[1:] == kind[:-1]
        same[where[(where > 0) & (where < len(data))] - 1] = False
        first[1:] &= ~same | (kind[1:] == 2)
        first &= ~tail
        starts = np.flatnonzero(first)
        # a run ends where the next begins or where its class ends
        gap = np.flatnonzero((kind[1:] == 0) & (kind[:-1] > 0)) + 1
        nexts = np.append(starts[1:], len(data))
        ends = np.append(gap, len(data))
        stops = np.minimum(nexts, ends[np.searchsorted(ends, starts, "right")])
        begin, size = self._lookup(common.RunHash(common.BYTE_WORDS[low])(starts, stops), low, starts, stops)
        if len(odd_place):
            n = np.array([len(x) for x in odd_ids], np.int64)
            begin = np.concatenate([begin, len(self.store) + np.cumsum(n) - n])
            self.extra = np.array([i for x in odd_ids for i in x], np.int32)
            place = np.concatenate([starts, odd_place])
            order = np.argsort(place, kind="stable")
            return place[order], begin[order], np.concatenate([size, n])[order]
        return starts, begin, size

    def count(self, data: np.ndarray, where: np.ndarray) -> np.ndarray:
        if not len(data):
            return np.zeros(len(where) - 1, np.int64)
        place, _, size = self.runs(data, where)
        return common.per_row(size, np.searchsorted(place, where))

    def encode(self, data: np.ndarray, where: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts end to end, and where each text's begin (one more: the end)."""
        if not len(data):
            return np.zeros(0, np.int32), np.zeros(len(where), np.int64)
        place, begin, size = self.runs(data, where)
        ends = np.cumsum(size)
        store = np.concatenate([self.store, self.extra]) if len(self.extra) else self.store
        ids = store[np.repeat(begin - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)]
        return ids, np.append(0, ends)[np.searchsorted(place, where)]


def _map(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(path)
        for part in common.slices(batches, "text"):
            data, where = common.text_bytes(common.column(part, "text"))
            count = encoder.count(data, where)
            yield pa.RecordBatch.from_arrays([common.column(part, "doc_id"), pa.array(np.diff(where)), pa.array(count), pa.array(count > LIMIT)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return run


def count_tokens(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of each row of docs (doc_id, text)."""
    return docs.select("doc_id", "text").mapInArrow(_map(path or vocabulary()), "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(common.documents(spark, sf_dir))
