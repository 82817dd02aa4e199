import hashlib
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from linefault.llm import media as M
from linefault.llm import progressive_jpeg as J


@pytest.mark.parametrize("groups", [1, 2, 7, 8, 9, 130, 8200])
def test_payload_round_trip(groups):
    payload = np.random.default_rng(groups).integers(0, 256, groups * 192, dtype=np.uint8).tobytes()
    assert J.read_payload(J.decode_coefficients(J.encode_payload(payload))) == payload


def test_symbol_by_symbol_agrees(monkeypatch):
    payload = np.random.default_rng(0).integers(0, 256, 9 * 192, dtype=np.uint8).tobytes()
    fast = J.decode_coefficients(J.encode_payload(payload))
    monkeypatch.setattr(J, "_uniform", lambda *a: False)
    slow = J.decode_coefficients(J.encode_payload(payload))
    assert all((a.coefs == b.coefs).all() for a, b in zip(fast.components, slow.components, strict=True))


class Writer:
    """A plain progressive encoder: all tables hold every symbol with eight-bit codes."""

    def __init__(self):
        self.bits = []

    def put(self, value, n):
        self.bits += [value >> i & 1 for i in range(n - 1, -1, -1)]

    def symbol(self, s, table):
        self.put(table.index(s), 8)

    def signed(self, v, size):
        self.put(v if v > 0 else v + (1 << size) - 1, size)

    def done(self):
        out = np.packbits(np.array(self.bits + [1] * (-len(self.bits) % 8), np.uint8)).tobytes()
        self.bits = []
        return out.replace(b"\xff", b"\xff\x00")


DC, AC = list(range(12)), [r << 4 | s for r in range(16) for s in range(11)][:200]


def dht(kind, table):
    return J._segment(0xC4, bytes([kind << 4] + [0] * 7 + [len(table)] + [0] * 8 + table))


def shift(v, low):
    return (abs(v) >> low) * (1 if v > 0 else -1)


def encode_420(coefs, width, height):
    """coefs: three arrays (down, across, 64); luma is sampled twice as densely. Al 1 and a refining pass on all bands."""
    w, out = Writer(), [b"\xff\xd8", J._segment(0xDB, bytes([0] + [3] * 64)), J._segment(0xC2, struct.pack(">BHHB", 8, height, width, 3) + bytes([1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])), dht(0, DC), dht(1, AC)]
    y, cb, cr = coefs
    order = [(c, i) for my in range(cb.shape[0]) for mx in range(cb.shape[1]) for c, i in ((0, (2 * my, 2 * mx)), (0, (2 * my, 2 * mx + 1)), (0, (2 * my + 1, 2 * mx)), (0, (2 * my + 1, 2 * mx + 1)), (1, (my, mx)), (2, (my, mx)))]
    for high, low in ((0, 1), (1, 0)):
        last = [0, 0, 0]
        for c, i in order:
            v = int(coefs[c][i][0])
            if high:
                w.put(v & 1, 1)
                continue
            d = (v >> 1) - last[c]
            last[c] = v >> 1
            w.symbol(abs(d).bit_length(), DC)
            if d:
                w.signed(d, abs(d).bit_length())
        out += [J._start([(1, 0), (2, 0), (3, 0)], 0, 0, high, low), w.done()]
    for c in range(3):
        hmax = 2 if c == 0 else 1
        wide, tall = -(-(-(-width * hmax // 2)) // 8), -(-(-(-height * hmax // 2)) // 8)
        for i in np.ndindex(tall, wide):
            run = 0
            for k in range(1, 64):
                v = shift(int(coefs[c][i][k]), 1)
                if not v:
                    run += 1
                    continue
                while run > 15:
                    w.symbol(0xF0, AC)
                    run -= 16
                size = abs(v).bit_length()
                w.symbol(run << 4 | size, AC)
                w.signed(v, size)
                run = 0
            if run:
                w.symbol(0, AC)
        out += [J._start([(c + 1, 0)], 1, 63, 0, 1), w.done()]
        for i in np.ndindex(tall, wide):
            block = [int(x) for x in coefs[c][i]]
            fresh = [k for k in range(1, 64) if abs(block[k]) == 1]
            k, run, held = 1, 0, []
            for k in range(1, 64):
                if fresh and k <= fresh[-1]:
                    if abs(block[k]) > 1:
                        held.append(abs(block[k]) & 1)
                    elif block[k] == 0:
                        run += 1
                        if run == 16:
                            w.symbol(0xF0, AC)
                            for b in held:
                                w.put(b, 1)
                            run, held = 0, []
                    else:
                        w.symbol(run << 4 | 1, AC)
                        w.put(int(block[k] > 0), 1)
                        for b in held:
                            w.put(b, 1)
                        run, held = 0, []
                elif k == (fresh[-1] + 1 if fresh else 1):
                    w.symbol(0, AC)
                    for j in range(k, 64):
                        if abs(block[j]) > 1:
                            w.put(abs(block[j]) & 1, 1)
        out += [J._start([(c + 1, 0)], 1, 63, 1, 0), w.done()]
    return b"".join(out) + b"\xff\xd9"


def test_subsampled_image_with_refinement():
    rng = np.random.default_rng(3)
    coefs = [np.where(rng.random((d, a, 64)) < 0.25, rng.integers(-9, 10, (d, a, 64)), 0) for d, a in ((4, 6), (2, 3), (2, 3))]
    coefs[0][:, 5:, 1:] = 0  # beyond the component's own width only the first coefficients are coded
    coefs[0][3:, :, 1:] = 0
    image = J.decode_coefficients(encode_420(coefs, 39, 24))
    for c, want in zip(image.components, coefs, strict=True):
        assert (c.coefs == want).all()
    rgb = J.to_rgb(image)
    assert rgb.shape == (24, 39, 3)
    # By the definition of the transform, at a few samples.
    for yy, xx in ((0, 0), (7, 20), (17, 38)):
        def sample(c, r, q):
            block = np.zeros(64)
            block[J.ZIGZAG] = c[r // 8, q // 8] * 3
            b = block.reshape(8, 8)
            f = [np.sqrt(1 / 8) if u == 0 else 0.5 for u in range(8)]
            return 128 + sum(f[u] * f[v] * b[u, v] * np.cos((2 * (r % 8) + 1) * u * np.pi / 16) * np.cos((2 * (q % 8) + 1) * v * np.pi / 16) for u in range(8) for v in range(8))

        lum, blue, red = sample(coefs[0], yy, xx), sample(coefs[1], yy // 2, xx // 2) - 128, sample(coefs[2], yy // 2, xx // 2) - 128
        want = np.clip(np.rint([lum + 1.402 * red, lum - 0.344136 * blue - 0.714136 * red, lum + 1.772 * blue]), 0, 255)
        assert np.abs(rgb[yy, xx] - want).max() <= 1


def test_report(docs_of, odd):
    rows = {(r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in M.media_report(M.store_texts(docs_of(odd))).collect()}
    want = {(i, len((t or "").encode()), len(p := M.payload_of((t or "").encode())), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:])) for i, t, _ in odd}
    assert rows == want
    assert M.media_report(M.store_texts(docs_of([]))).count() == 0


def test_tensors(docs_of, tmp_path):
    text = bytes(range(32, 127)) * 9
    stored = M.store_texts(docs_of([(1, "abc", "a"), (2, None, "a"), (3, text.decode(), "a")])).withColumn("media", F.expr("CASE WHEN doc_id <> 2 THEN media END"))
    got = {r.doc_id: (r.width, r.height, None if r.rgb is None else len(r.rgb)) for r in M.decode_media(stored).collect()}
    assert got == {1: (16, 16, 768), 2: (None, None, None), 3: (48, 16, 48 * 16 * 3)}
    kept = {r.doc_id: r for r in M.write_tensors(stored, str(tmp_path / "tensors")).collect()}
    want = J.to_rgb(J.decode_coefficients(J.encode_payload(M.payload_of(text))))
    assert (M.as_array(kept[3].width, kept[3].height, kept[3].rgb) == want).all() and kept[2].rgb is None


def test_clashing_columns_stay(docs_of):
    stored = M.store_texts(docs_of([(1, "abc", "a")])).selectExpr("*", "7 AS width", "'x' AS decoded_media", "'y' AS RGB")
    out = M.decode_media(stored)
    assert out.columns == [*stored.columns, "_width", "height", "_rgb"]
    row = out.first()
    assert (row["width"], row["decoded_media"], row["RGB"], row["_width"], row["height"]) == (7, "x", "y", 16, 16)
    assert M.decode_media(stored.where("false")).count() == 0


def test_chroma_is_upsampled():
    """The stored form has chroma at half the resolution both ways: its samples come in squares of four."""
    image = J.decode_coefficients(J.encode_payload(np.random.default_rng(5).integers(0, 256, 40 * 192, dtype=np.uint8).tobytes()))
    assert [(c.h, c.v) for c in image.components] == [(2, 2), (1, 1), (1, 1)]
    assert image.components[0].coefs.shape[:2] == (2, 40) and image.components[1].coefs.shape[:2] == (1, 20)
    assert J.to_rgb(image).shape == (16, 320, 3)


def test_broken_media():
    with pytest.raises(ValueError):
        J.decode_coefficients(b"no image")
