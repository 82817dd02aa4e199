"""Progressive JPEG in numpy: scans accumulated into coefficient arrays, inverse transform, chroma upsampling.

decode_coefficients reads any Huffman-coded sequential or progressive file of 8-bit samples: spectral selection,
successive approximation, runs of ended bands, restart intervals and any sampling factors. A scan whose
table holds a single symbol has fields of one width, and is read as one bit matrix; every other scan goes
symbol by symbol.

encode_payload stores bytes without loss as coefficients, which are the format's unit: the 256 values of
magnitude class 8 stand for the 256 bytes, and their class-8 bits are the byte itself. Chroma has half the resolution both
ways, so 384 bytes fill one unit of 16x16 samples: four 8x8 blocks of luma and one of each chroma component.
"""

from __future__ import annotations

import re
import struct
from dataclasses import dataclass, field

import numpy as np

BLOCK, GROUP = 64, 192
#: Blocks of one unit: two rows of two of luma, and one of each chroma component.
UNIT = 6
#: Units along a row of the stored image; the format allows 65535 samples.
MOST_ACROSS = 4095
#: Groups coded at once, a multiple of 8 so that every chunk ends on a byte: bounds memory on long payloads.
CHUNK = 8192
LOW_BAND = (1, 5)
HIGH_BAND = (6, 63)


def _zigzag() -> np.ndarray:
    """Natural index (row * 8 + column) of each zigzag position, by walking the diagonals."""
    order = sorted(((r, c) for r in range(8) for c in range(8)), key=lambda p: (p[0] + p[1], p[0] if (p[0] + p[1]) % 2 else p[1]))
    return np.array([r * 8 + c for r, c in order])


ZIGZAG = _zigzag()


def _basis() -> np.ndarray:
    """Row k: the 64 samples of a unit coefficient at zigzag position k."""
    x = np.arange(8)
    cosine = np.cos((2 * x[None, :] + 1) * x[:, None] * np.pi / 16) * np.where(x == 0, np.sqrt(1 / 8), 0.5)[:, None]
    return np.einsum("ux,vy->uvxy", cosine, cosine).reshape(64, 64)[ZIGZAG].astype(np.float32)


BASIS = _basis()


@dataclass
class Component:
    ident: int
    h: int
    v: int
    table: int
    across: int = 0
    down: int = 0
    coefs: np.ndarray = field(default_factory=lambda: np.zeros((0, 0, 64), np.int32))


@dataclass
class Decoded:
    width: int
    height: int
    components: list[Component]
    quant: dict[int, np.ndarray]
    comment: bytes = b""


# Writing


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _lone_table(kind: int, symbol: int) -> bytes:
    """A Huffman table with one symbol, whose code is a single 0 bit."""
    return _segment(0xC4, bytes([kind << 4, 1] + [0] * 15 + [symbol]))


def _start(components: list[tuple[int, int]], first: int, last: int, high: int, low: int) -> bytes:
    return _segment(0xDA, bytes([len(components), *[x for c in components for x in c], first, last, high << 4 | low]))


def _stuffed(data: bytes) -> bytes:
    return data.replace(b"\xff", b"\xff\x00")


def _ended(bits: np.ndarray) -> bytes:
    """Bits as bytes, the last one filled with 1s."""
    return np.packbits(np.concatenate([bits, np.ones(-len(bits) % 8, np.uint8)])).tobytes()


def _fields(values: np.ndarray) -> np.ndarray:
    """Each byte behind the one-bit code 0, as bits."""
    out = np.zeros((values.size, 9), np.uint8)
    out[:, 1:] = np.unpackbits(values.reshape(-1, 1), axis=1)
    return out.ravel()


def _chunks(n: int):
    return ((i, min(n, i + CHUNK)) for i in range(0, n, CHUNK))


def _planes(units: np.ndarray, down: int, across: int) -> list[np.ndarray]:
    """The blocks of each component, row by row, from units in order."""
    luma = units[:, :4].reshape(down, across, 2, 2, BLOCK).swapaxes(1, 2).reshape(-1, BLOCK)
    return [luma, units[:, 4], units[:, 5]]


def _units(planes: list[np.ndarray], down: int, across: int) -> np.ndarray:
    """The inverse of _planes."""
    luma = planes[0].reshape(down, 2, across, 2, BLOCK).swapaxes(1, 2).reshape(-1, 4, BLOCK)
    return np.concatenate([luma, planes[1].reshape(-1, 1, BLOCK), planes[2].reshape(-1, 1, BLOCK)], axis=1)


def encode_payload(payload: bytes) -> bytes:
    """A progressive 4:2:0 file whose coefficients hold the payload; its length must be a positive multiple of 192."""
    if not payload or len(payload) % GROUP:
        raise ValueError("a payload is a positive multiple of 192 bytes")
    n = -(-len(payload) // (UNIT * BLOCK))
    across = min(n, MOST_ACROSS)
    down = -(-n // across)
    data = np.full(across * down * UNIT * BLOCK, 128, np.uint8)
    data[: len(payload)] = np.frombuffer(payload, np.uint8)
    planes = _planes(data.reshape(-1, UNIT, BLOCK), down, across)
    out = [b"\xff\xd8", _segment(0xFE, str(len(payload)).encode()), _segment(0xDB, bytes([0] + [1] * 64))]
    out += [_segment(0xC2, struct.pack(">BHHB", 8, down * 16, across * 16, 3) + bytes(x for c, size in ((1, 0x22), (2, 0x11), (3, 0x11)) for x in (c, size, 0)))]
    # First coefficients: restarted at every block, so that no prediction is carried.
    out += [_lone_table(0, 8), _segment(0xDD, struct.pack(">H", 1))]
    for c, plane in enumerate(planes):
        out += [_start([(c + 1, 0)], 0, 0, 0, 0)]
        for a, b in _chunks(len(plane)):
            bits = np.ones((b - a, 16), np.uint8)
            bits[:, :9] = _fields(plane[a:b, 0]).reshape(-1, 9)
            groups = np.packbits(bits, axis=1)  # the code's 0 comes first and 1s fill up, so only the second byte can be 255
            marks = np.stack([np.full(b - a, 0xFF), 0xD0 + np.arange(a, b) % 8], axis=1).astype(np.uint8)
            row = np.zeros((b - a, 5), np.uint8)
            row[:, :2], row[:, 3:] = groups, marks
            keep = np.ones(row.shape, bool)
            keep[:, 2] = groups[:, 1] == 255
            out += [row[keep].tobytes()[: -2 if b == len(plane) else None]]
    out += [_segment(0xDD, struct.pack(">H", 0))]
    low, high = slice(LOW_BAND[0], LOW_BAND[1] + 1), slice(HIGH_BAND[0], HIGH_BAND[1] + 1)
    out += [_lone_table(1, 7)]
    for c, plane in enumerate(planes):  # the low band without its last bit: a byte's upper seven bits behind the code
        out += [_start([(c + 1, 0)], *LOW_BAND, 0, 1), _stuffed((plane[:, low] >> 1).tobytes())]
    out += [_lone_table(1, 8)]
    for c, plane in enumerate(planes):
        out += [_start([(c + 1, 0)], *HIGH_BAND, 0, 0), *[_stuffed(_ended(_fields(plane[a:b, high]))) for a, b in _chunks(len(plane))]]
    out += [_lone_table(1, 0)]
    for c, plane in enumerate(planes):  # the last bit of the low band's magnitudes, behind an end-of-band code for each block
        part = plane[:, low]
        bits = np.zeros((len(plane), part.shape[1] + 1), np.uint8)
        bits[:, 1:] = (part & 1) ^ (part < 128)
        out += [_start([(c + 1, 0)], *LOW_BAND, 1, 0), _stuffed(_ended(bits.ravel()))]
    return b"".join(out) + b"\xff\xd9"


# Reading


class _Bits:
    """Bits of one restart segment, most significant first; past the end come 0s."""

    def __init__(self, data: bytes):
        self.data, self.at, self.hold, self.have = data, 0, 0, 0

    def take(self, n: int) -> int:
        while self.have < n:
            self.hold = self.hold << 8 | (self.data[self.at] if self.at < len(self.data) else 0)
            self.at += 1
            self.have += 8
        self.have -= n
        out = self.hold >> self.have & ((1 << n) - 1)
        self.hold &= (1 << self.have) - 1
        return out

    def symbol(self, codes: dict) -> int:
        code = 0
        for length in range(1, 17):
            code = code << 1 | self.take(1)
            if (length, code) in codes:
                return codes[length, code]
        raise ValueError("no such Huffman code")

    def signed(self, size: int) -> int:
        x = self.take(size) if size else 0
        return x if not size or x >> (size - 1) else x - (1 << size) + 1


def _codes(body: bytes) -> dict:
    """(length, code) -> symbol: codes count up, and double at each further bit."""
    out, code, at = {}, 0, 16
    for length in range(1, 17):
        for _ in range(body[length - 1]):
            out[length, code] = body[at]
            code += 1
            at += 1
        code <<= 1
    return out


_RESTART = re.compile(rb"\xff[\xd0-\xd7]")
_NEXT_MARKER = re.compile(rb"\xff[^\x00\xd0-\xd7]")


def _entropy(data: bytes, at: int) -> tuple[list[bytes], int]:
    """The restart segments from `at`, unstuffed, and where the next marker stands."""
    found = _NEXT_MARKER.search(data, at)
    end = found.start() if found else len(data)
    body = data[at:end]
    segments = _RESTART.split(body)
    return [x.replace(b"\xff\x00", b"\xff") for x in segments] if b"\xff\x00" in body else segments, end


def _extended(values: np.ndarray, size: int) -> np.ndarray:
    values = values.astype(np.int32)
    return np.where(values >> (size - 1) > 0, values, values - (1 << size) + 1)


def _numbers(bits: np.ndarray) -> np.ndarray:
    """The rightmost axis of at most 16 bits as numbers."""
    width = bits.shape[-1]
    if width == 8:
        return np.packbits(bits, axis=-1)[..., 0].astype(np.int32)
    return bits @ (1 << np.arange(width - 1, -1, -1, dtype=np.int32))


def _uniform(scan, segments: list[bytes], interval: int) -> bool:
    """Read a scan whose tables hold one symbol each; False if this way doesn't fit it."""
    parts, first, last, high, low = scan
    component, dc, ac = parts[0]
    codes = dc if first == 0 else ac
    if any(len(p[1] if first == 0 else p[2]) != 1 for p in parts) or (first == 0 and last > 0):
        return False
    (length, _), symbol = next(iter(codes.items()))
    if first == 0:
        if high or interval != 1 or any((p[1] != codes) or len(parts) > 1 and p[0].h * p[0].v != 1 for p in parts) or not 0 < symbol <= 11:
            return False
        width = (length + symbol) * len(parts)
        size = -(-width // 8)
        blocks = component.across * component.down
        if len(segments) != blocks or any(len(s) != size for s in segments):
            return False
        for a, b in _chunks(blocks):
            bits = np.unpackbits(np.frombuffer(b"".join(segments[a:b]), np.uint8).reshape(-1, size), axis=1)[:, :width].reshape(-1, len(parts), length + symbol)
            found = _extended(_numbers(bits[:, :, length:]), symbol) << low
            for i, p in enumerate(parts):
                p[0].coefs.reshape(-1, 64)[a:b, 0] = found[:, i]
        return True
    if interval or component.coefs.shape[:2] != (component.down, component.across):
        return False
    flat, band, data = component.coefs.reshape(-1, 64), last - first + 1, np.frombuffer(segments[0], np.uint8)
    if high == 0:
        if symbol >> 4 or not symbol or symbol > 10:
            return False
        width = band * (length + symbol)
    else:
        if symbol or not (flat[:, first : last + 1] != 0).all():
            return False
        width = length + band
    if len(data) * 8 < width * len(flat):
        return False
    for a, b in _chunks(len(flat)):
        bits = np.unpackbits(data[a * width // 8 :], count=(b - a) * width).reshape(b - a, -1)
        if high == 0:
            flat[a:b, first : last + 1] = _extended(_numbers(bits.reshape(b - a, band, -1)[:, :, length:]), symbol) * (1 << low)
        else:
            flat[a:b, first : last + 1] += np.sign(flat[a:b, first : last + 1]) * (bits[:, length:].astype(np.int32) << low)
    return True


def _refine(bits: _Bits, block: np.ndarray, first: int, last: int, codes: dict, low: int, run: int) -> int:
    """One block of a refining scan of a band; returns how many blocks of ended bands are left."""
    step, k = 1 << low, first

    def correct(at: int) -> None:
        if bits.take(1):
            block[at] += step if block[at] > 0 else -step

    while k <= last and not run:
        skip, size = divmod(bits.symbol(codes), 16)
        value = 0
        if size:
            value = step if bits.take(1) else -step
        elif skip < 15:
            run = (1 << skip) + (bits.take(skip) if skip else 0)
            break
        while k <= last:
            if block[k]:
                correct(k)
            elif skip == 0:
                if value:
                    block[k] = value
                k += 1
                break
            else:
                skip -= 1
            k += 1
    if run:
        for at in range(k, last + 1):
            if block[at]:
                correct(at)
        run -= 1
    return run


def _read_scan(image: Decoded, scan, segments: list[bytes], interval: int) -> None:
    """Any scan, symbol by symbol."""
    parts, first, last, high, low = scan
    hmax, vmax = max(c.h for c in image.components), max(c.v for c in image.components)
    if len(parts) == 1:  # not interleaved: only the blocks that the component's own size needs
        c = parts[0][0]
        wide = -(-(-(-image.width * c.h // hmax)) // 8)
        tall = -(-(-(-image.height * c.v // vmax)) // 8)
        units = [[(parts[0], y, x)] for y in range(tall) for x in range(wide)]
    else:
        wide, tall = -(-image.width // (8 * hmax)), -(-image.height // (8 * vmax))
        units = [[(p, my * p[0].v + y, mx * p[0].h + x) for p in parts for y in range(p[0].v) for x in range(p[0].h)] for my in range(tall) for mx in range(wide)]
    for at, unit in enumerate(units):
        if at == 0 or interval and at % interval == 0:
            bits = _Bits(segments[at // interval if interval else 0])
            predicted, run = dict.fromkeys(range(256), 0), 0
        for (c, dc, ac), y, x in unit:
            block, k = c.coefs[y, x], first
            if first == 0:
                if high:
                    block[0] |= bits.take(1) << low
                else:
                    predicted[c.ident] += bits.signed(bits.symbol(dc))
                    block[0] = predicted[c.ident] << low
                k = 1
            if last == 0:
                continue
            if high:
                run = _refine(bits, block, k, last, ac, low, run)
                continue
            if run:
                run -= 1
                continue
            while k <= last:
                skip, size = divmod(bits.symbol(ac), 16)
                if size:
                    k += skip
                    block[k] = bits.signed(size) * (1 << low)
                    k += 1
                elif skip == 15:
                    k += 16
                else:
                    run = (1 << skip) - 1 + (bits.take(skip) if skip else 0)
                    break


def decode_coefficients(data: bytes) -> Decoded:
    """The coefficients of all components, accumulated over all scans, in zigzag order."""
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG file")
    image, tables, quant, interval, at, comment = None, {}, {}, 0, 2, b""
    while at + 4 <= len(data) and data[at + 1] != 0xD9:
        if data[at] != 0xFF:
            raise ValueError("marker expected")
        code = data[at + 1]
        if code == 0xFF:
            at += 1
            continue
        size = struct.unpack_from(">H", data, at + 2)[0]
        body = data[at + 4 : at + 2 + size]
        at += 2 + size
        if code == 0xFE:
            comment = body
        elif code == 0xDB:
            while body:
                wide, length = body[0] >> 4, 1 + 64 * (1 + (body[0] >> 4))
                quant[body[0] & 15] = np.frombuffer(body[1:length], ">u2" if wide else np.uint8).astype(np.int32)
                body = body[length:]
        elif code == 0xC4:
            while body:
                length = 17 + sum(body[1:17])
                tables[body[0]] = _codes(body[1:length])
                body = body[length:]
        elif code == 0xDD:
            interval = struct.unpack(">H", body)[0]
        elif code in (0xC0, 0xC1, 0xC2):
            depth, tall, wide, count = struct.unpack_from(">BHHB", body)
            if depth != 8:
                raise ValueError("samples of 8 bits only")
            parts = [Component(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(count)]
            hmax, vmax = max(c.h for c in parts), max(c.v for c in parts)
            for c in parts:
                c.across, c.down = -(-wide // (8 * hmax)) * c.h, -(-tall // (8 * vmax)) * c.v
                c.coefs = np.zeros((c.down, c.across, 64), np.int32)
            image = Decoded(wide, tall, parts, quant)
        elif code == 0xDA:
            by = {c.ident: c for c in image.components}
            n = body[0]
            parts = [(by[body[1 + 2 * i]], tables.get(body[2 + 2 * i] >> 4, {}), tables.get(16 | body[2 + 2 * i] & 15, {})) for i in range(n)]
            first, last, approx = body[1 + 2 * n], body[2 + 2 * n], body[3 + 2 * n]
            segments, at = _entropy(data, at)
            scan = (parts, first, last, approx >> 4, approx & 15)
            if not _uniform(scan, segments, interval):
                _read_scan(image, scan, segments, interval)
        elif 0xC3 <= code <= 0xCF and code not in (0xC8, 0xCC):
            raise ValueError("not a sequential or progressive Huffman-coded file")
    if image is None:
        raise ValueError("no frame")
    image.comment = comment
    return image


def to_rgb(image: Decoded) -> np.ndarray:
    """Full-resolution samples (height, width, 3): dequantised, inverse-transformed, chroma repeated to full size."""
    hmax, vmax = max(c.h for c in image.components), max(c.v for c in image.components)
    planes = []
    for c in image.components:
        flat = c.coefs.reshape(-1, 64)
        samples = np.empty(flat.shape, np.float32)
        for a, b in _chunks(len(flat)):
            samples[a:b] = (flat[a:b] * image.quant[c.table]).astype(np.float32) @ BASIS
        plane = samples.reshape(c.down, c.across, 8, 8).swapaxes(1, 2).reshape(c.down * 8, c.across * 8)
        if (c.h, c.v) != (hmax, vmax):
            plane = plane.repeat(vmax // c.v, axis=0).repeat(hmax // c.h, axis=1)
        planes.append(plane[: image.height, : image.width] + np.float32(128))
    if len(planes) == 1:
        planes = [planes[0], np.full_like(planes[0], 128), np.full_like(planes[0], 128)]
    y, cb, cr = planes[0], planes[1] - 128, planes[2] - 128
    out = np.empty((image.height, image.width, 3), np.uint8)
    for i, plane in enumerate((y + np.float32(1.402) * cr, y - np.float32(0.344136) * cb - np.float32(0.714136) * cr, y + np.float32(1.772) * cb)):
        out[:, :, i] = np.clip(np.rint(plane), 0, 255)
    return out


def read_payload(image: Decoded) -> bytes:
    """The bytes that encode_payload put into the coefficients."""
    chroma = image.components[1]
    stacked = _units([c.coefs.reshape(-1, BLOCK) for c in image.components], chroma.down, chroma.across)
    return np.where(stacked > 0, stacked, stacked + 255).astype(np.uint8).tobytes()[: int(image.comment)]
