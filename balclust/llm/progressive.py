"""Media columns: progressive JPEG, written and read in numpy.

A stored form keeps its payload in quantised DCT coefficients, the format's unit, and so without loss:
each byte is one coefficient of a 4:2:0 image whose quantisation steps are all one. The encoder writes
an interleaved scan of DC terms and, for each component, two bands of AC terms with their lowest bit
left out (spectral selection), and then scans that add that bit (successive approximation).

The decoder accumulates the scans of any progressive Huffman image of one or three components into
coefficient arrays. It runs all restart intervals of all images of a like frame in step, one symbol of each interval at a
time, over one array of the joined bits. Coefficients times quantisation steps go through the inverse
transform in exact integers, chroma is upsampled to full resolution, and RGB tensors come out.

Defined cases: a null text is empty, its payload is all padding; a text longer than a batch is one step, whose arrays take about 200 bytes a byte
of it; repeated rows each get their row (there are no ties to break); an empty table gives an empty result; other columns are ignored. A null image has a null
tensor; what isn't such an image, or ends early, raises ValueError.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common

UNIT, PAD, MCU = 576, 255, 384
#: Blocks (units of a scan) in a restart interval.
RESTART = 6

# The order in which a block's coefficients are sent.
ZIGZAG = np.array([
    0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28,
    35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63,
])


class Scan(NamedTuple):
    components: tuple[int, ...]
    first: int
    last: int
    high: int
    low: int


class Component(NamedTuple):
    key: int
    across: int
    down: int
    table: int


class Frame(NamedTuple):
    """What images decoded together share. blocks: of each component, across and down, whole MCUs."""

    width: int
    height: int
    components: tuple[Component, ...]

    @property
    def mcus(self) -> tuple[int, int]:
        h, v = max(c.across for c in self.components), max(c.down for c in self.components)
        return -(-self.width // (8 * h)), -(-self.height // (8 * v))

    def grid(self, k: int) -> tuple[int, int]:
        across, down = self.mcus
        return across * self.components[k].across, down * self.components[k].down

    def own(self, k: int) -> tuple[int, int]:
        """Blocks of component k that a scan of it alone sends."""
        h, v = max(c.across for c in self.components), max(c.down for c in self.components)
        c = self.components[k]
        return -(-(-(-self.width * c.across // h)) // 8), -(-(-(-self.height * c.down // v)) // 8)

    def order(self, parts: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray, int]:
        """(component, block) in the order of a scan, and how many make one unit of it."""
        if len(parts) == 1:
            wide, high = self.own(parts[0])
            rows, columns = np.divmod(np.arange(wide * high), wide)
            return np.full(wide * high, parts[0]), rows * self.grid(parts[0])[0] + columns, 1
        across, down = self.mcus
        kinds, places = [], []
        y, x = np.divmod(np.arange(across * down), across)
        for k in parts:
            c = self.components[k]
            for dy in range(c.down):
                for dx in range(c.across):
                    kinds.append(np.full(len(x), k))
                    places.append((y * c.down + dy) * self.grid(k)[0] + x * c.across + dx)
        return np.stack(kinds, 1).ravel(), np.stack(places, 1).ravel(), len(kinds)


class Table(NamedTuple):
    """A Huffman table: lengths and symbols in order of code; code and size by symbol; symbol and size by the next 16 bits."""

    counts: tuple[int, ...]
    symbols: tuple[int, ...]
    code: np.ndarray
    size: np.ndarray
    next_symbol: np.ndarray
    next_size: np.ndarray


def huffman(counts: tuple[int, ...], symbols: tuple[int, ...]) -> Table:
    code, size = np.zeros(256, np.int64), np.zeros(256, np.int64)
    look, width = np.zeros(1 << 16, np.uint8), np.zeros(1 << 16, np.uint8)
    value, k = 0, 0
    for length, n in enumerate(counts, 1):
        for _ in range(n):
            s = symbols[k]
            code[s], size[s] = value, length
            span = slice(value << (16 - length), (value + 1) << (16 - length))
            look[span], width[span] = s, length
            value, k = value + 1, k + 1
        value <<= 1
    return Table(counts, symbols, code, size, look, width)


# The tables of our stored form (counts by length, symbols): of a payload's coefficients, halved, nearly all are 5 to 7 bits long.
DC_TABLE = huffman((0, 0, 0, 12, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0), tuple(range(12)))
AC_TABLE = huffman((0, 3, 1, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0), (6, 5, 7, 0, 4, 8, 3, 2, 1, 9))
SCRIPT = (
    Scan((0, 1, 2), 0, 0, 0, 1), Scan((0,), 1, 5, 0, 1), Scan((1,), 1, 63, 0, 1), Scan((2,), 1, 63, 0, 1), Scan((0,), 6, 63, 0, 1),
    Scan((0, 1, 2), 0, 0, 1, 0), Scan((0,), 1, 63, 1, 0), Scan((1,), 1, 63, 1, 0), Scan((2,), 1, 63, 1, 0),
)
YUV420 = (Component(1, 2, 2, 0), Component(2, 1, 1, 0), Component(3, 1, 1, 0))
#: A byte's coefficient is so much larger: halved, no coefficient is zero.
LIFT = 2
#: MCUs that fit below each other in one image of the format.
TALLEST = 4095


def frame_for(mcus: int) -> Frame:
    across = -(-mcus // TALLEST)
    return Frame(16 * across, 16 * -(-mcus // across), YUV420)


def _segment(marker: int, body: bytes) -> bytes:
    return bytes([0xFF, marker]) + (len(body) + 2).to_bytes(2, "big") + body


_TABLES = _segment(0xDB, b"\0" + b"\1" * 64) + b"".join(_segment(0xC4, bytes([kind, *t.counts, *t.symbols])) for kind, t in ((0x00, DC_TABLE), (0x10, AC_TABLE))) + _segment(0xDD, RESTART.to_bytes(2, "big"))
_STARTS = [_segment(0xDA, bytes([len(x.components), *(b for c in x.components for b in (c + 1, 0)), x.first, x.last, x.high << 4 | x.low])) for x in SCRIPT]


def _head(frame: Frame, payload: int) -> bytes:
    parts = b"".join(bytes([c.key, c.across << 4 | c.down, c.table]) for c in frame.components)
    size = frame.height.to_bytes(2, "big") + frame.width.to_bytes(2, "big")
    return b"\xff\xd8" + _segment(0xFE, b"payload %d" % payload) + _segment(0xC2, b"\x08" + size + bytes([len(frame.components)]) + parts) + _TABLES


def _bit_length(x: np.ndarray) -> np.ndarray:
    return np.frexp(np.abs(x).astype(np.float64))[1].astype(np.int64)


def _write(value: np.ndarray, size: np.ndarray, lanes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of the lanes, end to end, and where each begins. value, size: codes in order; lanes: where each lane's codes begin (one more: the end)."""
    ends = np.append(0, np.cumsum(size))
    bits = np.diff(ends[lanes])
    start = np.append(0, np.cumsum(-(-bits // 8)))
    at = ends[:-1] + np.repeat(8 * start[:-1] - ends[lanes[:-1]], np.diff(lanes))
    words = np.zeros(start[-1] // 4 + 3, np.uint32)
    some = size > 0
    value, size, at = value[some].astype(np.uint64), size[some], at[some]
    wide = value << (64 - size - (at & 31)).astype(np.uint64)
    heads = np.flatnonzero(np.append(True, np.diff(at >> 5) > 0)) if len(at) else np.zeros(0, np.int64)
    if len(heads):
        both = np.bitwise_or.reduceat(wide, heads)
        place = at[heads] >> 5
        words[place] |= (both >> np.uint64(32)).astype(np.uint32)
        words[place + 1] |= (both & np.uint64(0xFFFFFFFF)).astype(np.uint32)
    out = words.byteswap().view(np.uint8)[: start[-1]].copy()
    out[start[1:] - 1] |= ((1 << (-bits % 8)) - 1).astype(np.uint8)
    return out, start


def _stuff(body: np.ndarray, start: np.ndarray, turn: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes with zeros after 255 and a restart marker before each lane that isn't an image's first. turn: a lane's number in its image."""
    extra = np.zeros(len(body) + 1, np.int64)
    extra[1:] += body == 255
    marked = start[:-1][turn > 0]
    extra[marked] += 2
    shift = np.cumsum(extra)
    out = np.zeros(len(body) + shift[-1], np.uint8)
    place = np.arange(len(body)) + shift[:-1]
    out[place] = body
    out[place[marked] - 2], out[place[marked] - 1] = 255, 0xD0 + (turn[turn > 0] - 1) % 8
    lane = start[:-1] + shift[start[:-1]] - 2 * (turn > 0)
    return out, np.append(lane, len(out))


def encode(payloads: np.ndarray, where: np.ndarray) -> list[bytes]:
    """A progressive image of each payload; payloads lie end to end and begin at where."""
    size = np.diff(where)
    count = -(-size // MCU)
    frames = [frame_for(n) for n in count.tolist()]
    area = np.array([f.mcus[0] * f.mcus[1] for f in frames], np.int64)
    first = np.append(0, np.cumsum(area))
    sent = np.full(first[-1] * MCU, PAD, np.int64)
    sent[np.arange(len(payloads)) + np.repeat(first[:-1] * MCU - where[:-1], size)] = payloads
    blocks = (sent + LIFT).reshape(-1, 6, 64)  # by MCU: four of luma, two of chroma; coefficients in the order they are sent
    parts: list[list[bytes]] = [[_head(f, n)] for f, n in zip(frames, size.tolist(), strict=True)]
    strips = all(f.mcus[0] == 1 for f in frames)
    for scan, head in zip(SCRIPT, _STARTS, strict=True):
        if len(scan.components) > 1:
            body, units, each = blocks[:, :, :1].reshape(-1, 1), area, 6
        else:
            k = scan.components[0]
            own = blocks[:, :4].reshape(-1, 64) if k == 0 else blocks[:, 3 + k]
            if k == 0 and not strips:  # a scan of luma alone goes row by row over the image
                turn = [np.argsort(f.order((0, 1, 2))[1][f.order((0, 1, 2))[0] == 0]) + 4 * a for f, a in zip(frames, first[:-1].tolist(), strict=True)]
                own = own[np.concatenate(turn)]
            body, units, each = own[:, scan.first : scan.last + 1], area * (4 if k == 0 else 1), 1
        lanes_each = -(-units // RESTART)
        turn = np.arange(lanes_each.sum()) - np.repeat(np.cumsum(lanes_each) - lanes_each, lanes_each)
        lane_units = np.minimum(RESTART, np.repeat(units, lanes_each) - turn * RESTART)
        lane_blocks = np.append(0, np.cumsum(lane_units * each))
        if scan.high:  # one more bit of each coefficient, all of which are nonzero already; for AC after an end of block
            low = body & 1
            if scan.first == 0:
                value, width = low.ravel(), np.ones(low.size, np.int64)
            else:
                value = np.concatenate([np.full((len(low), 1), AC_TABLE.code[0]), low], axis=1).ravel()
                width = np.tile(np.append(AC_TABLE.size[0], np.ones(low.shape[1], np.int64)), len(low))
        else:
            value, table = body >> 1, AC_TABLE
            if scan.first == 0:
                table, flat = DC_TABLE, value[:, 0]
                comp = np.tile([0, 0, 0, 0, 1, 2], len(flat) // 6)
                value = np.zeros_like(flat)
                begins = np.zeros(len(flat), bool)
                for c in range(3):  # differences to the last of the same component in the interval
                    own = np.flatnonzero(comp == c)
                    diff = flat[own].copy()
                    diff[1:] -= flat[own[:-1]]
                    begins[:] = False
                    begins[lane_blocks[:-1] + (0, 4, 5)[c]] = True
                    diff[begins[own]] = flat[own[begins[own]]]
                    value[own] = diff
            value = value.ravel()
            bits = _bit_length(value)
            tail = np.where(value < 0, value + (1 << bits) - 1, value)
            value, width = (table.code[bits] << bits) | tail, table.size[bits] + bits
        per_block = len(value) // max(1, lane_blocks[-1])
        out, at = _stuff(*_write(value, width, lane_blocks * per_block), turn)
        ends = at[np.append(0, np.cumsum(lanes_each))]
        raw = out.tobytes()
        for own, a, b in zip(parts, ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            own += [head, raw[a:b]]
    return [b"".join([*own, b"\xff\xd9"]) for own in parts]


class Image(NamedTuple):
    frame: Frame
    steps: tuple[tuple[int, ...], ...]
    payload: int
    restart: int
    scans: tuple[tuple[Scan, tuple[tuple, ...]], ...]
    bodies: tuple[tuple[int, int], ...]


_NEXT = re.compile(rb"\xff[^\x00\xd0-\xd7\xff]", re.DOTALL)


def read(data: bytes) -> Image:
    """Markers of one image; the entropy-coded parts stay where they are."""
    if data[:2] != b"\xff\xd8":
        raise ValueError("no JPEG image")
    at, tables, steps, restart, payload, frame = 2, {}, {}, 0, -1, None
    scans, bodies = [], []
    while at < len(data):
        if data[at] != 0xFF:
            raise ValueError("a marker is missing")
        marker = data[at + 1]
        if marker == 0xD9:
            break
        size = int.from_bytes(data[at + 2 : at + 4], "big")
        body, at = data[at + 4 : at + 2 + size], at + 2 + size
        if marker == 0xC4:
            k = 0
            while k < len(body):
                counts = tuple(body[k + 1 : k + 17])
                n = sum(counts)
                tables[body[k]] = (counts, tuple(body[k + 17 : k + 17 + n]))
                k += 17 + n
        elif marker == 0xDB:
            k = 0
            while k < len(body):
                wide = body[k] >> 4
                raw = body[k + 1 : k + 1 + 64 * (1 + wide)]
                steps[body[k] & 15] = tuple(raw) if not wide else tuple(int.from_bytes(raw[j : j + 2], "big") for j in range(0, 128, 2))
                k += 1 + len(raw)
        elif marker == 0xDD:
            restart = int.from_bytes(body, "big")
        elif marker == 0xFE and body.startswith(b"payload "):
            payload = int(body[8:])
        elif marker == 0xC2:
            frame = Frame(int.from_bytes(body[3:5], "big"), int.from_bytes(body[1:3], "big"), tuple(Component(body[k], body[k + 1] >> 4, body[k + 1] & 15, body[k + 2]) for k in range(6, len(body), 3)))
        elif marker == 0xDA:
            if frame is None:
                raise ValueError("a scan before the frame")
            n = body[0]
            keys = [c.key for c in frame.components]
            parts = tuple(keys.index(body[1 + 2 * k]) for k in range(n))
            scan = Scan(parts, body[1 + 2 * n], body[2 + 2 * n], body[3 + 2 * n] >> 4, body[3 + 2 * n] & 15)
            chosen = tuple(tables.get(body[2 + 2 * k] >> 4 if scan.first == 0 else 0x10 | body[2 + 2 * k] & 15, ()) for k in range(n))
            end = _NEXT.search(data, at)
            stop = end.start() if end else len(data)
            scans.append((scan, chosen))
            bodies.append((at, stop))
            at = stop
        elif 0xC0 <= marker <= 0xCF:
            raise ValueError("not a progressive Huffman image")
    else:
        raise ValueError("the image ends early")
    if frame is None or any(c.across > 4 or c.down > 4 for c in frame.components):
        raise ValueError("no frame")
    return Image(frame, tuple(steps.get(c.table, (1,) * 64) for c in frame.components), payload, restart, tuple(scans), tuple(bodies))


class Bits:
    """Bits of joined lanes, read at many places at a time."""

    def __init__(self, data: np.ndarray):
        wide = np.append(data, np.zeros(8, np.uint8)).astype(np.int64)
        self.words = wide[:-3] << 24 | wide[1:-2] << 16 | wide[2:-1] << 8 | wide[3:]

    def peek(self, at: np.ndarray) -> np.ndarray:
        return self.words[at >> 3] >> (16 - (at & 7)) & 0xFFFF

    def take(self, at: np.ndarray, n: np.ndarray) -> np.ndarray:
        return (self.words[at >> 3] << (at & 7) & 0xFFFFFFFF) >> (32 - n)


def _unstuff(data: np.ndarray, segments: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes without stuffing and restart markers, where each lane begins, lanes of each segment)."""
    full = data == 255
    nexts = np.append(data[1:], 0)
    marker = full & (nexts >= 0xD0) & (nexts <= 0xD7)
    drop = marker.copy()
    drop[1:] |= marker[:-1] | (full[:-1] & (data[1:] == 0))
    kept = np.append(0, np.cumsum(~drop))
    cuts = np.flatnonzero(marker)
    begins = np.sort(np.concatenate([segments[:-1], cuts + 2]))
    lanes = np.searchsorted(begins, segments)
    return data[~drop], kept[begins], np.diff(lanes)


def _dc_scan(bits: Bits, at: np.ndarray, first: np.ndarray, stop: np.ndarray, comp: np.ndarray, place: np.ndarray, flat: np.ndarray, scan: Scan, tables: list) -> None:
    if scan.high:
        n = stop - first
        lane = np.repeat(np.arange(len(at)), n)
        k = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        flat[place[first[lane] + k]] |= bits.take(at[lane] + k, np.ones(len(lane), np.int64)) << scan.low
        return
    at, unit = at.copy(), first.copy()
    last = np.zeros((len(at), int(comp.max()) + 1), np.int64)
    live = np.flatnonzero(unit < stop)
    while len(live):
        c = comp[unit[live]]
        window = bits.peek(at[live])
        s, n = np.zeros(len(live), np.int64), np.zeros(len(live), np.int64)
        for k, t in tables:
            own = c == k
            s[own], n[own] = t.next_symbol[window[own]], t.next_size[window[own]]
        where = at[live] + n
        extra = bits.take(where, s)
        at[live] = where + s
        last[live, c] += np.where(extra < (1 << s >> 1), extra - (1 << s) + 1, extra)
        flat[place[unit[live]]] = last[live, c] << scan.low
        unit[live] += 1
        live = live[unit[live] < stop[live]]


def _ac_first(bits: Bits, at: np.ndarray, unit: np.ndarray, stop: np.ndarray, place: np.ndarray, flat: np.ndarray, scan: Scan, table: Table) -> None:
    k = np.full(len(at), scan.first)
    while True:
        live = unit < stop
        if not live.all():
            at, unit, stop, k = at[live], unit[live], stop[live], k[live]
        if not len(at):
            return
        window = bits.peek(at)
        symbol = table.next_symbol[window].astype(np.int64)
        at = at + table.next_size[window]
        run, s = symbol >> 4, symbol & 15
        k = k + run
        if s.all():
            extra = bits.take(at, s)
            at = at + s
            flat[place[unit] + ZIGZAG[np.minimum(k, 63)]] = np.where(extra < (1 << (s - 1)), extra - (1 << s) + 1, extra) << scan.low
            k = k + 1
            skip = 0
        else:
            end = (s == 0) & (run < 15)
            n = np.where(end, run, s)
            extra = bits.take(at, n)
            at = at + n
            own = np.flatnonzero(s)
            flat[place[unit[own]] + ZIGZAG[np.minimum(k[own], 63)]] = np.where(extra[own] < (1 << (s[own] - 1)), extra[own] - (1 << s[own]) + 1, extra[own]) << scan.low
            k = np.where(end, scan.last + 1, k + 1)
            skip = np.where(end, (1 << run) + extra - 1, 0)
        over = k > scan.last
        unit = unit + np.where(over, 1 + skip, 0)
        k = np.where(over, scan.first, k)


def _ac_refine(bits: Bits, at: np.ndarray, unit: np.ndarray, stop: np.ndarray, place: np.ndarray, flat: np.ndarray, scan: Scan, table: Table) -> None:
    """A symbol at a time: its corrections are of the nonzero coefficients up to the zero at which its run ends."""
    spots = ZIGZAG[scan.first : scan.last + 1]
    step = 1 << scan.low
    k, left = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
    while True:
        live = unit < stop
        if not live.all():
            at, unit, stop, k, left = at[live], unit[live], stop[live], k[live], left[live]
        if not len(at):
            return
        fresh = left == 0
        window = bits.peek(at)
        symbol = np.where(fresh, table.next_symbol[window], 0).astype(np.int64)
        at = at + np.where(fresh, table.next_size[window], 0)
        run, s = symbol >> 4, symbol & 15
        n = np.where(fresh, np.where((s == 0) & (run < 15), run, (s > 0).astype(np.int64)), 0)
        extra = bits.take(at, n)
        at = at + n
        ending = ~fresh | ((s == 0) & (run < 15))
        left = np.where(fresh & ending, (1 << run) + extra, left)
        index = place[unit][:, None] + spots
        held = flat[index]
        nonzero = held != 0
        ahead = np.arange(len(spots)) >= k[:, None]
        if ending.all():
            until = np.full(len(at), len(spots))
        else:
            until = ((~nonzero & ahead).cumsum(1) <= run[:, None]).sum(1)  # the place of zero number run + 1, or the end
            until = np.where(ending, len(spots), until)
        fix = nonzero & ahead & (np.arange(len(spots)) < until[:, None])
        number = fix.cumsum(1)
        rows, columns = np.nonzero(fix)
        where = at[rows] + number[rows, columns] - 1
        bit = bits.words[where >> 3] >> (31 - (where & 7)) & 1
        spot = index[rows, columns]
        old = held[rows, columns]
        flat[spot] = old + np.where((bit > 0) & (np.abs(old) & step == 0), np.sign(old) * step, 0)
        at = at + number[:, -1]
        new = np.flatnonzero(~ending & (s > 0) & (until < len(spots)))
        flat[index[new, until[new]]] = np.where(extra[new] > 0, step, -step)
        left = np.where(ending, left - 1, left)
        k = np.where(ending, len(spots), until + 1)
        over = k >= len(spots)
        unit = unit + over
        k = np.where(over, 0, k)


def decode(files: list[bytes]) -> list[tuple[Image, list[np.ndarray]]]:
    """Each image with the coefficients of its components: a row of 64 for each block of the grid, in natural order. Bytes that end early or contradict themselves raise ValueError."""
    try:
        return _decode(files)
    except (IndexError, KeyError, TypeError, AttributeError) as broken:
        raise ValueError("the image is cut off or damaged") from broken


def _decode(files: list[bytes]) -> list[tuple[Image, list[np.ndarray]]]:
    images = [read(f) for f in files]
    kinds: dict[tuple, list[int]] = {}
    for k, i in enumerate(images):
        kinds.setdefault((tuple((c.across, c.down) for c in i.frame.components), i.scans, i.restart > 0), []).append(k)
    out: list = [None] * len(files)
    for (shape, scans, _), members in kinds.items():
        own = [images[k] for k in members]
        grid = np.array([[np.prod(i.frame.grid(c)) for c in range(len(shape))] for i in own], np.int64)
        base = np.concatenate([[0], np.cumsum(grid.T.ravel())])[:-1].reshape(len(shape), -1)  # component after component
        flat = np.zeros(64 * int(grid.sum()), np.int64)
        orders: dict[tuple, tuple] = {}
        for n, (scan, chosen) in enumerate(scans):
            raw = b"".join(files[k][slice(*images[k].bodies[n])] for k in members)
            segments = np.append(0, np.cumsum([i.bodies[n][1] - i.bodies[n][0] for i in own]))
            data, begins, lanes = _unstuff(np.frombuffer(raw, np.uint8), segments)
            comp, place, first, stop, at = [], [], [], [], 0
            for j, i in enumerate(own):
                key = (i.frame, scan.components)
                if key not in orders:
                    orders[key] = i.frame.order(scan.components)
                kind, block, each = orders[key]
                comp.append(kind)
                place.append((base[kind, j] + block) * 64)
                size = (i.restart or len(kind)) * each
                cuts = np.arange(0, len(kind), size)
                if len(cuts) != lanes[j]:
                    raise ValueError("restart intervals are missing")
                first.append(at + cuts)
                stop.append(at + np.minimum(cuts + size, len(kind)))
                at += len(kind)
            comp, place, first, stop = map(np.concatenate, (comp, place, first, stop))
            bits, at = Bits(data), begins * 8
            tables = [huffman_cached(*t) if t else None for t in chosen]
            if scan.first == 0:
                _dc_scan(bits, at, first, stop, comp, place, flat, scan, list(zip(scan.components, tables, strict=True)))
            elif scan.high:
                _ac_refine(bits, at, first, stop, place, flat, scan, tables[0])
            else:
                _ac_first(bits, at, first, stop, place, flat, scan, tables[0])
        table = flat.reshape(-1, 64)
        for j, k in enumerate(members):
            out[k] = (images[k], [table[base[c, j] : base[c, j] + grid[j, c]] for c in range(len(shape))])
    return out


_CACHE: dict[tuple, Table] = {}


def huffman_cached(counts: tuple[int, ...], symbols: tuple[int, ...]) -> Table:
    if (counts, symbols) not in _CACHE:
        _CACHE[counts, symbols] = huffman(counts, symbols)
    return _CACHE[counts, symbols]


def _basis() -> np.ndarray:
    k, x = np.arange(8)[:, None], np.arange(8)[None, :]
    one = np.cos((2 * x + 1) * k * np.pi / 16) * np.where(k == 0, np.sqrt(1 / 8), 0.5)
    return np.rint(np.kron(one, one) * (1 << 20))


#: Inverse transform of a whole block, in whole numbers of 2^-20; sums stay exact in double precision.
BASIS = _basis()


def samples(coefficients: np.ndarray) -> np.ndarray:
    """Samples 0 to 255 of blocks: (n, 8, 8)."""
    raw = np.floor((coefficients.astype(np.float64) @ BASIS) / (1 << 20) + 0.5) + 128
    return np.clip(raw, 0, 255).astype(np.uint8).reshape(-1, 8, 8)


def tensor(frame: Frame, steps: tuple, coefficients: list[np.ndarray]) -> np.ndarray:
    """The image as height x width x 3 (RGB), chroma upsampled to full resolution."""
    planes = []
    h, v = max(c.across for c in frame.components), max(c.down for c in frame.components)
    for k, (c, table, own) in enumerate(zip(frame.components, steps, coefficients, strict=True)):
        natural = np.ones(64, np.int64)
        natural[ZIGZAG] = table
        wide, high = frame.grid(k)
        plane = samples(own * natural if (natural != 1).any() else own).reshape(high, wide, 8, 8).swapaxes(1, 2).reshape(high * 8, wide * 8)
        planes.append(plane.repeat(v // c.down, 0).repeat(h // c.across, 1)[: frame.height, : frame.width].astype(np.int32))
    if len(planes) == 1:
        return np.stack(planes * 3, -1).astype(np.uint8)
    y, blue, red = planes[0] << 16, planes[1] - 128, planes[2] - 128
    rgb = np.stack([y + 91_881 * red, y - 22_554 * blue - 46_802 * red, y + 116_130 * blue], -1)
    return np.clip((rgb + 32_768) >> 16, 0, 255).astype(np.uint8)


def payload(image: Image, coefficients: list[np.ndarray]) -> bytes:
    """The bytes that one of our images stores."""
    kind, block, _ = image.frame.order((0, 1, 2))
    luma, blue, red = (c[:, ZIGZAG] - LIFT for c in coefficients)
    rows = np.empty((len(kind), 64), np.int64)
    for k, own in enumerate((luma, blue, red)):
        rows[kind == k] = own[block[kind == k]]
    return rows.ravel()[: image.payload].astype(np.uint8).tobytes()


def padded(data: np.ndarray, where: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each text's bytes and 255s up to a positive multiple of UNIT, end to end."""
    size = np.diff(where)
    whole = np.maximum(1, -(-size // UNIT)) * UNIT
    begins = np.append(0, np.cumsum(whole))
    out = np.full(begins[-1], PAD, np.uint8)
    out[np.arange(len(data)) + np.repeat(begins[:-1] - where[:-1], size)] = data
    return out, begins


#: Bytes of payload that a worker encodes and decodes at a time.
BATCH = 1 << 20


def store(texts: pa.Array) -> list[bytes]:
    return encode(*padded(*common.text_bytes(texts)))


def features(files: list[bytes]) -> list[tuple[bytes, np.ndarray]]:
    """Of each image: the payload read back (empty where it is not one of ours), and the RGB tensor. Ours that are one MCU wide stand on each other as one tall image."""
    decoded = decode(files)
    out: list = [None] * len(files)
    ours = [i.payload >= 0 and i.frame.components == YUV420 and all(s == (1,) * 64 for s in i.steps) for i, _ in decoded]
    strips = [k for k, (i, _) in enumerate(decoded) if ours[k] and i.frame.mcus[0] == 1]
    if strips:
        rows = np.array([decoded[k][0].frame.mcus[1] for k in strips])
        tall = [np.concatenate([decoded[k][1][c] for k in strips]) for c in range(3)]
        image = tensor(Frame(16, 16 * int(rows.sum()), YUV420), decoded[strips[0]][0].steps, tall)
        n = int(rows.sum())
        sent = np.concatenate([tall[0].reshape(n, 4, 64), tall[1][:, None], tall[2][:, None]], axis=1)[:, :, ZIGZAG].reshape(n, MCU)
        raw = (sent - LIFT).astype(np.uint8).tobytes()
        for k, a, m in zip(strips, (np.cumsum(rows) - rows).tolist(), rows.tolist(), strict=True):
            out[k] = (raw[a * MCU : a * MCU + decoded[k][0].payload], image[16 * a : 16 * (a + m)])
    for k, (i, c) in enumerate(decoded):
        if out[k] is None:
            out[k] = (payload(i, c) if ours[k] else b"", tensor(i.frame, i.steps, c))
    return out


def describe(rgb: np.ndarray) -> str:
    """Size, sums of red, green and blue, and CRC-32 of a tensor."""
    sums = rgb.reshape(-1, 3).sum(axis=0, dtype=np.int64)
    return f"{rgb.shape[1]}x{rgb.shape[0]};{sums[0]},{sums[1]},{sums[2]};{zlib.crc32(np.ascontiguousarray(rgb)):08x}"


def _tensors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in common.slices(batches, "media", BATCH):
        files = common.column(part, "media").to_pylist()
        found = iter([x for _, x in features([f for f in files if f is not None])])
        got = [None if f is None else next(found) for f in files]
        size = [pa.array([None if x is None else x.shape[k] for x in got], pa.int32()) for k in range(2)]
        yield pa.RecordBatch.from_arrays([common.column(part, "doc_id"), *size, pa.array([None if x is None else x.tobytes() for x in got], pa.binary())], ["doc_id", "height", "width", "rgb"])


def _stored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in common.slices(batches, "text", BATCH):
        yield pa.RecordBatch.from_arrays([common.column(part, "doc_id"), pa.array(store(common.column(part, "text")), pa.binary())], ["doc_id", "media"])


def stored(docs: DataFrame) -> DataFrame:
    """doc_id and media (the progressive image that stores the text) of each row of docs (doc_id, text)."""
    return docs.select("doc_id", "text").mapInArrow(_stored, "doc_id long, media binary")


def tensors(media: DataFrame) -> DataFrame:
    """doc_id, height, width, rgb (the full-resolution tensor's bytes) of each row of media (doc_id, media); null for null."""
    return media.select("doc_id", "media").mapInArrow(_tensors, "doc_id long, height int, width int, rgb binary")


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in common.slices(batches, "text", BATCH):
        size = np.diff(common.text_bytes(common.column(part, "text"))[1])
        files = store(common.column(part, "text"))
        rows = []
        for key, n, file, (raw, rgb) in zip(common.column(part, "doc_id").to_pylist(), size.tolist(), files, features(files), strict=True):
            rows.append((key, n, len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-32:]), len(file), hashlib.sha256(file).hexdigest(), describe(rgb)))
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return common.documents(spark, sf_dir).select("doc_id", "text").mapInArrow(_digest, schema)
