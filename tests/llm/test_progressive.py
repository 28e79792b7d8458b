import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pytest

from balclust.llm import progressive as media

TEXTS = [None, "", "a", "x" * 576, "x" * 577, "é ü\n" * 500, "".join(map(chr, range(1, 900))), "\x00\x01\xff" * 300, "long text " * 9000, "a"]


def payload(t):
    raw = (t or "").encode()
    return raw + b"\xff" * (max(1, -(-len(raw) // 576)) * 576 - len(raw))


def test_query_reads_back_every_byte(spark, tmp_path):
    spark.createDataFrame([(k, t, 1) for k, t in enumerate(TEXTS)], "doc_id long, text string, media int").write.parquet(str(tmp_path / "documents.parquet"))
    rows = {r.doc_id: r for r in media.op7(spark, str(tmp_path)).collect()}
    for k, t in enumerate(TEXTS):
        want = payload(t)
        assert (rows[k].n_bytes, rows[k].payload_bytes) == (len((t or "").encode()), len(want))
        assert rows[k].payload_sha256 == hashlib.sha256(want).hexdigest() and rows[k].tail_crc32 == zlib.crc32(want[-32:])
        (file,) = media.store(pa.array([t], pa.string()))
        assert rows[k].media_bytes == len(file) and rows[k].media_sha256 == hashlib.sha256(file).hexdigest()
    assert rows[2].feature == rows[9].feature and rows[2].media_sha256 == rows[9].media_sha256
    stored = media.stored(spark.createDataFrame([(1, "abc")], "doc_id long, text string"))
    (t,) = media.tensors(stored).collect()
    assert len(t.rgb) == t.height * t.width * 3
    assert media.tensors(media.stored(spark.createDataFrame([], "doc_id long, text string"))).count() == 0


def test_images_wider_than_one_mcu(monkeypatch):
    monkeypatch.setattr(media, "TALLEST", 3)
    texts = pa.array(["some words " * 300, "x", "other " * 1000])
    for t, (raw, rgb) in zip(texts.to_pylist(), media.features(media.store(texts))):
        assert raw == payload(t) and rgb.shape[2] == 3
    image, coefficients = media.decode(media.store(texts[:1]))[0]
    assert image.frame.mcus[0] > 1
    assert np.array_equal(media.features(media.store(texts[:1]))[0][1], media.tensor(image.frame, image.steps, coefficients))


def test_transform_is_the_cosine_transform():
    rng = np.random.default_rng(0)
    block = rng.integers(-60, 60, (1, 64))
    want = np.zeros((8, 8))
    for y in range(8):
        for x in range(8):
            for v in range(8):
                for u in range(8):
                    scale = (2**-0.5 if u == 0 else 1) * (2**-0.5 if v == 0 else 1) / 4
                    want[y, x] += scale * block[0, 8 * v + u] * np.cos((2 * x + 1) * u * np.pi / 16) * np.cos((2 * y + 1) * v * np.pi / 16)
    assert np.abs(media.samples(block)[0] - np.clip(want + 128, 0, 255)).max() <= 0.51


class Writer:
    """A plain progressive writer, symbol by symbol, with zero runs, runs of ended blocks and late coefficients. Codes are 8 bits long."""

    def __init__(self, table):
        self.table, self.bits = table, []

    def put(self, value, n):
        self.bits += [(value >> (n - 1 - k)) & 1 for k in range(n)]

    def symbol(self, s):
        self.put(int(self.table.code[s]), int(self.table.size[s]))

    def body(self):
        bits = self.bits + [1] * (-len(self.bits) % 8)
        return bytes(np.packbits(bits)).replace(b"\xff", b"\xff\x00")


def plain_image(blocks, wide, high, restart):
    """blocks: (n, 64) in the order sent; one component."""
    table = media.huffman((0,) * 7 + (250,) + (0,) * 8, tuple(range(250)))
    out = [b"\xff\xd8", media._segment(0xDB, b"\0" + bytes(range(1, 65))), media._segment(0xC2, b"\x08" + (8 * high).to_bytes(2, "big") + (8 * wide).to_bytes(2, "big") + b"\x01\x01\x11\x00")]
    out += [media._segment(0xC4, bytes([k, *table.counts, *table.symbols])) for k in (0x00, 0x10)]
    out.append(media._segment(0xDD, restart.to_bytes(2, "big")))

    def scan(first, last, high_, low, lane):
        out.append(media._segment(0xDA, bytes([1, 1, 0, first, last, high_ << 4 | low])))
        for k, a in enumerate(range(0, len(blocks), restart or len(blocks))):
            if k:
                out.append(bytes([0xFF, 0xD0 + (k - 1) % 8]))
            w = Writer(table)
            lane(w, blocks[a : a + (restart or len(blocks))])
            out.append(w.body())

    def signed(w, v, n):
        w.put(v if v > 0 else v + (1 << n) - 1, n)

    def dc(w, own):
        last = 0
        for b in own:
            v = int(b[0]) >> 1
            n = abs(v - last).bit_length()
            w.symbol(n)
            if n:
                signed(w, v - last, n)
            last = v

    def ended(w, run, fixes):
        if run:
            n = run.bit_length() - 1
            w.symbol(n << 4)
            w.put(run - (1 << n), n)
            for f in fixes:
                w.put(f, 1)

    def ac(w, own):
        run = 0
        for b in own:
            zeros = 0
            for k in range(1, 64):
                v = int(b[k])
                v = (abs(v) >> 1) * (1 if v > 0 else -1)
                if not v:
                    zeros += 1
                    continue
                ended(w, run, [])
                run = 0
                while zeros > 15:
                    w.symbol(0xF0)
                    zeros -= 16
                n = abs(v).bit_length()
                w.symbol(zeros << 4 | n)
                signed(w, v, n)
                zeros = 0
            run += zeros > 0
        ended(w, run, [])

    def more(w, own):
        run, kept = 0, []
        for b in own:
            last = max((k for k in range(1, 64) if abs(int(b[k])) == 1), default=0)
            zeros, fixes = 0, []
            for k in range(1, 64):
                v = int(b[k])
                if abs(v) > 1:
                    fixes.append(abs(v) & 1)
                    continue
                if v == 0:
                    zeros += 1
                    if zeros == 16 and k < last:
                        ended(w, run, kept)
                        run, kept = 0, []
                        w.symbol(0xF0)
                        for f in fixes:
                            w.put(f, 1)
                        zeros, fixes = 0, []
                    continue
                ended(w, run, kept)
                run, kept = 0, []
                w.symbol(zeros << 4 | 1)
                w.put(int(v > 0), 1)
                for f in fixes:
                    w.put(f, 1)
                zeros, fixes = 0, []
            if zeros or fixes:
                run += 1
                kept += fixes
        ended(w, run, kept)

    scan(0, 0, 0, 1, dc)
    scan(1, 63, 0, 1, ac)
    scan(0, 0, 1, 0, lambda w, own: [w.put(int(b[0]) & 1, 1) for b in own])
    scan(1, 63, 1, 0, more)
    return b"".join([*out, b"\xff\xd9"])


@pytest.mark.parametrize("restart", [0, 3])
@pytest.mark.parametrize("density", [0.02, 0.3, 0.9])
def test_any_coefficients_of_a_grey_image(restart, density):
    rng = np.random.default_rng(int(density * 100) + restart)
    blocks = np.where(rng.random((20, 64)) < density, rng.integers(-9, 10, (20, 64)), 0)
    blocks[4:9, 1:] = 0
    blocks[12, 1:] = 0
    blocks[12, 60] = 1
    images = [plain_image(blocks, 5, 4, restart), plain_image(blocks[:6], 3, 2, restart)]
    for (image, (got,)), want in zip(media.decode(images), (blocks, blocks[:6])):
        assert np.array_equal(got[:, media.ZIGZAG], want)
        assert image.steps[0][5] == 6
        assert media.tensor(image.frame, image.steps, [got]).shape == (8 * (len(want) // (5 if len(want) == 20 else 3)), 8 * (5 if len(want) == 20 else 3), 3)


def test_other_files_are_refused():
    for data in (b"", b"GIF89a", b"\xff\xd8\xff\xc0\x00\x0b\x08\x00\x08\x00\x08\x01\x01\x11\x00"):
        with pytest.raises(ValueError):
            media.read(data)


def test_feature_equals_a_plain_decoder():
    """Colours from the payload by the cosine formula in floats, without the writer, the reader or the transform of the module."""
    text = "Some text, é, 0123; " * 40
    raw = payload(text)
    raw += raw[:0] + bytes(-len(raw) % 384)
    (file,) = media.store(pa.array([text]))
    (got, rgb) = media.features([file])[0]
    assert got == payload(text)
    cos = [[np.cos((2 * x + 1) * u * np.pi / 16) * (np.sqrt(1 / 8) if u == 0 else 0.5) for u in range(8)] for x in range(8)]
    zigzag = sorted(((y, x) for y in range(8) for x in range(8)), key=lambda p: (sum(p), p[0] if sum(p) % 2 else p[1]))
    filled = len(payload(text)) // 384  # whole units of six blocks, whose coefficients are all known
    for m in range(filled):
        planes = []
        for b in range(6):
            own = np.zeros((8, 8))
            for value, (v, u) in zip(raw[384 * m + 64 * b : 384 * m + 64 * b + 64], zigzag):
                own[v, u] = value + 2
            c = np.array(cos)
            planes.append(np.clip(np.floor(c @ own @ c.T + 0.5) + 128, 0, 255))
        luma = np.block([[planes[0], planes[1]], [planes[2], planes[3]]])
        blue, red = (np.kron(p, np.ones((2, 2))) - 128 for p in planes[4:])
        want = np.clip(np.stack([luma + 1.402 * red, luma - 0.344136 * blue - 0.714136 * red, luma + 1.772 * blue], -1) + 0.5, 0, 255).astype(int)
        assert np.abs(rgb[16 * m : 16 * m + 16].astype(int) - want).max() <= 2
    sums = rgb.reshape(-1, 3).astype(int).sum(axis=0)
    assert media.describe(rgb) == f"{rgb.shape[1]}x{rgb.shape[0]};{sums[0]},{sums[1]},{sums[2]};{zlib.crc32(rgb.tobytes()):08x}"


def test_tensors_of_null_grey_and_damaged_images(spark):
    rng = np.random.default_rng(4)
    blocks = rng.integers(-3, 4, (6, 64))
    grey, strip = plain_image(blocks, 3, 2, 0), plain_image(blocks[:2], 1, 2, 0)
    (own,) = media.store(pa.array(["text"]))
    got = media.tensors(spark.createDataFrame([(1, None), (2, grey), (3, strip), (4, own), (5, None)], "doc_id long, media binary").coalesce(1)).collect()
    assert [(r.height, r.width) for r in got] == [(None, None), (16, 24), (16, 8), (32, 16), (None, None)]
    assert got[0].rgb is None and len(got[1].rgb) == 16 * 24 * 3
    for cut in (own[:40], own[: len(own) // 2], own[:-40]):
        with pytest.raises(ValueError):
            media.features([cut])
