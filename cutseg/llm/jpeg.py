"""Baseline JPEG in numpy: a decoder of DC-only luminance thumbnails, and an
encoder for images whose 8 x 8 blocks are flat.

The decoder reads any baseline file (8 bits, Huffman, one interleaved scan of
up to four components, with or without restart markers).  Segments between
restart markers do not depend on each other, so all segments of all images
that share tables and layout are decoded in step, one array lane for each.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np


class JpegError(ValueError):
    """The bytes are no baseline JPEG that this decoder reads."""


@dataclass
class Header:
    width: int = 0
    height: int = 0
    #: (id, horizontal, vertical sampling, quantisation table) in frame order
    components: list = field(default_factory=list)
    quant: dict = field(default_factory=dict)
    huffman: dict = field(default_factory=dict)
    restart: int = 0
    #: component index -> (DC table, AC table)
    tables: dict = field(default_factory=dict)
    data: tuple[int, int] = (0, 0)
    end: int = 0


def parse(raw: bytes, at: int = 0) -> Header:
    """Read all markers of the image that starts at ``at``."""
    if raw[at:at + 2] != b"\xff\xd8":
        raise JpegError("no SOI")
    h, p = Header(), at + 2
    while True:
        while raw[p:p + 2] == b"\xff\xff":
            p += 1
        if len(raw) < p + 4 or raw[p] != 0xFF:
            raise JpegError("marker expected")
        kind, size = raw[p + 1], struct.unpack(">H", raw[p + 2:p + 4])[0]
        body = raw[p + 4:p + 2 + size]
        if len(body) != size - 2:
            raise JpegError("cut short")
        p += 2 + size
        if kind == 0xDB:
            while body:
                wide, name = body[0] >> 4, body[0] & 15
                h.quant[name] = struct.unpack(">H", body[1:3])[0] if wide else body[1]
                body = body[1 + 64 * (1 + wide):]
        elif kind == 0xC4:
            while body:
                lengths = body[1:17]
                n = sum(lengths)
                h.huffman[body[0] >> 4, body[0] & 15] = (bytes(lengths), bytes(body[17:17 + n]))
                body = body[17 + n:]
        elif kind == 0xC0 or kind == 0xC1:
            if body[0] != 8:
                raise JpegError("only 8-bit samples")
            h.height, h.width = struct.unpack(">HH", body[1:5])
            h.components = [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(body[5])]
        elif 0xC2 <= kind <= 0xCF and kind != 0xC8 and kind != 0xCC:
            raise JpegError("not baseline")
        elif kind == 0xDD:
            h.restart = struct.unpack(">H", body)[0]
        elif kind == 0xDA:
            names = [c[0] for c in h.components]
            for i in range(body[0]):
                h.tables[names.index(body[1 + 2 * i])] = (body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15)
            if len(h.tables) != len(h.components):
                raise JpegError("only one interleaved scan")
            break
    start = q = p
    while True:  # the scan ends at the first marker that is no restart
        q = raw.find(b"\xff", q)
        if q < 0 or q + 1 >= len(raw):
            raise JpegError("no EOI")
        if raw[q + 1] == 0 or 0xD0 <= raw[q + 1] <= 0xD7:
            q += 2
            continue
        break
    h.data = (start, q)
    h.end = q + 2
    return h


def _lookup(spec: tuple[bytes, bytes]) -> np.ndarray:
    """16 bits -> code length * 256 + symbol; 0 where no code fits."""
    lengths, symbols = spec
    table, code, k = np.zeros(1 << 16, np.int32), 0, 0
    for n in range(1, 17):
        for _ in range(lengths[n - 1]):
            table[code << (16 - n):(code + 1) << (16 - n)] = n * 256 + symbols[k]
            code, k = code + 1, k + 1
        code <<= 1
    return table


@lru_cache(16)
def _flat_lookup(dc_spec: tuple[bytes, bytes], ac_spec: tuple[bytes, bytes]) -> np.ndarray:
    """16 bits -> (difference + 4096) * 32 + length, where they hold a whole
    block without AC coefficients; else 0."""
    bits = np.arange(1 << 16)
    dc = _lookup(dc_spec)
    size, used = dc & 255, (dc >> 8) + (dc & 255)
    fits = (dc > 0) & (used < 16) & (size < 12)
    left = np.where(fits, 16 - used, 0)
    value = _signed((bits >> left) & ((1 << np.where(fits, size, 0)) - 1), np.where(fits, size, 0))
    ac = _lookup(ac_spec)[(bits << (16 - left)) & 0xFFFF]
    fits &= (ac > 0) & ((ac & 255) == 0) & ((ac >> 8) <= left)
    return np.where(fits, (value + 4096) * 32 + used + (ac >> 8), 0).astype(np.int64)


def _segments(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entropy-coded bytes without stuffing and markers; start of each segment."""
    marks = np.flatnonzero(raw[:-1] == 0xFF)
    restart = marks[(raw[marks + 1] >= 0xD0) & (raw[marks + 1] <= 0xD7)]
    stuffed = marks[raw[marks + 1] == 0] + 1
    keep = np.ones(len(raw), bool)
    keep[stuffed] = keep[restart] = keep[restart + 1] = False
    before = np.cumsum(keep)
    return raw[keep], np.concatenate(([0], before[restart]))


class _Bits:
    def __init__(self, data: np.ndarray):
        d = np.concatenate((data, np.zeros(8, np.uint8))).astype(np.uint32)
        self.words = (d[:-3] << 24) | (d[1:-2] << 16) | (d[2:-1] << 8) | d[3:]

    def peek(self, at: np.ndarray, n) -> np.ndarray:
        """The next n (at most 16) bits of each lane."""
        return (self.words.take(at >> 3, mode="clip").astype(np.int64) >> (32 - (at & 7) - n)) & ((1 << n) - 1)


def _signed(bits: np.ndarray, size: np.ndarray) -> np.ndarray:
    return np.where((size > 0) & (bits < (1 << np.maximum(size, 1) - 1)), bits - (1 << size) + 1, bits)


def _same_layout(h: Header) -> tuple:
    return (h.width, tuple(h.components), tuple(sorted(h.quant.items())), tuple(sorted(h.huffman.items())), h.restart, tuple(sorted(h.tables.items())))


def thumbnails(images: list[bytes], headers: list[Header]) -> list[np.ndarray]:
    """For each image its luminance at one sample a block, uint8 (rows, columns)."""
    out: list = [None] * len(images)
    groups: dict[tuple, list[int]] = {}
    for i, h in enumerate(headers):
        groups.setdefault(_same_layout(h), []).append(i)
    for members in groups.values():
        _decode_group(images, headers, members, out)
    return out


def _decode_group(images: list[bytes], headers: list[Header], members: list[int], out: list) -> None:
    h0 = headers[members[0]]
    hmax, vmax = max(c[1] for c in h0.components), max(c[2] for c in h0.components)
    if len(h0.components) == 1:  # a lone component is never interleaved
        hmax = vmax = 1
    sampling = [(1, 1)] if len(h0.components) == 1 else [(c[1], c[2]) for c in h0.components]
    across = -(-h0.width // (8 * hmax))
    chunks, starts, units, base, first = [], [], [], [], []
    offset = grid = 0
    for i in members:
        h = headers[i]
        data, begin = _segments(np.frombuffer(images[i], np.uint8, h.data[1] - h.data[0], h.data[0]))
        mcus = across * -(-h.height // (8 * vmax))
        each = h.restart or mcus
        if 2 * mcus * sum(a * b for a, b in sampling) > 8 * len(data):  # a block takes two bits at least
            raise JpegError("fewer bits than blocks")
        if len(begin) != -(-mcus // each):
            raise JpegError("restart markers are missing")
        units.append(np.minimum(each, mcus - each * np.arange(len(begin))))
        starts.append((begin + offset) * 8)
        base.append(grid + each * np.arange(len(begin)))
        first.append(grid)
        chunks += [data, np.zeros(4, np.uint8)]
        offset, grid = offset + len(data) + 4, grid + mcus
    bits, pos = _Bits(np.concatenate(chunks)), np.concatenate(starts).astype(np.int64)
    units, base = np.concatenate(units), np.concatenate(base)
    luma_blocks = sampling[0][0] * sampling[0][1]
    dc = np.zeros((grid, luma_blocks), np.int32)
    codes = {k: _lookup(v) for k, v in h0.huffman.items()}
    flat = [_flat_lookup(h0.huffman[0, d], h0.huffman[1, a]) for d, a in (h0.tables[c] for c in range(len(h0.components)))]
    pred = np.zeros((len(h0.components), len(pos)), np.int64)
    for t in range(int(units.max())):
        lanes = np.flatnonzero(units > t)
        whole = len(lanes) == len(units)
        p = pos if whole else pos[lanes]
        for c, (hs, vs) in enumerate(sampling):
            dc_code, ac_code = codes[0, h0.tables[c][0]], codes[1, h0.tables[c][1]]
            for b in range(hs * vs):
                ahead = bits.peek(p, 16)
                hit = flat[c][ahead]
                if hit.all():  # the usual case of flat blocks, in one step
                    value = (pred[c] if whole else pred[c, lanes]) + (hit >> 5) - 4096
                    pred[c, slice(None) if whole else lanes] = value
                    p = p + (hit & 31)
                    if c == 0:
                        dc[base + t if whole else base[lanes] + t, b] = value
                    continue
                hit = dc_code[ahead]
                if not hit.all():
                    raise JpegError("no such code")
                p = p + (hit >> 8)
                size = (hit & 255).astype(np.int64)
                value = pred[c, lanes] + _signed(bits.peek(p, size), size)
                pred[c, lanes] = value
                p = p + size
                if c == 0:
                    dc[base[lanes] + t, b] = value
                p = _skip_ac(bits, ac_code, p)
        pos = p if whole else _put(pos, lanes, p)
    step = h0.quant[h0.components[0][3]]
    level = np.clip(np.floor(dc * (step / 8) + 128.5), 0, 255).astype(np.uint8)
    hs, vs = sampling[0]
    for i, start in zip(members, first):
        h = headers[i]
        down = -(-h.height // (8 * vmax))
        whole = level[start:start + across * down].reshape(down, across, vs, hs).transpose(0, 2, 1, 3).reshape(down * vs, across * hs)
        scale_x, scale_y = (8 * hmax // hs, 8 * vmax // vs)
        out[i] = whole[:-(-h.height // scale_y), :-(-h.width // scale_x)]


def _put(pos: np.ndarray, lanes: np.ndarray, p: np.ndarray) -> np.ndarray:
    pos = pos.copy()
    pos[lanes] = p
    return pos


def _skip_ac(bits: _Bits, code: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Move each lane behind the AC coefficients of its block."""
    hit = code[bits.peek(p, 16)]
    p = p + (hit >> 8) + (hit & 15)
    symbol = hit & 255
    open_ = np.flatnonzero(symbol != 0)
    k = np.where(symbol == 0xF0, 17, (symbol >> 4) + 2)[open_]
    while len(open_):
        live = k < 64
        open_, k = open_[live], k[live]
        if not len(open_):
            break
        q = p[open_]
        hit = code[bits.peek(q, 16)]
        if not hit.all():
            raise JpegError("no such code")
        symbol = hit & 255
        p[open_] = q + (hit >> 8) + (symbol & 15)
        k = k + np.where(symbol == 0xF0, 16, (symbol >> 4) + 1)
        go = symbol != 0
        open_, k = open_[go], k[go]
    return p


# --- flat-block images -------------------------------------------------------

#: Blocks in a row, payload bytes in a unit of 24 rows, and units in an image (its height has 16 bits).
ACROSS, UNIT, UNITS = 24, 576, 341
#: All nine DC sizes of 8-bit samples have 4-bit codes; the only AC code, one bit, ends the block.
_DC_SPEC = (bytes([0, 0, 0, 9, *[0] * 12]), bytes(range(9)))
_AC_SPEC = (bytes([1, *[0] * 15]), b"\x00")
_DC_STEP = 8
#: Bits of a magnitude from 0 to 255.
_SIZES = np.array([n.bit_length() for n in range(256)], np.int32)


def _segment(kind: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, kind, len(body) + 2) + body


def _head(rows: int) -> bytes:
    return b"".join((
        b"\xff\xd8", _segment(0xE0, b"JFIF\x00\x01\x01\x00\x00\x01\x00\x01\x00\x00"), _segment(0xDB, b"\x00" + bytes([_DC_STEP, *[16] * 63])),
        _segment(0xC0, struct.pack(">BHHB", 8, 8 * rows, 8 * ACROSS, 1) + b"\x01\x11\x00"),
        _segment(0xC4, b"\x00" + _DC_SPEC[0] + _DC_SPEC[1]), _segment(0xC4, b"\x10" + _AC_SPEC[0] + _AC_SPEC[1]),
        _segment(0xDD, struct.pack(">H", ACROSS)), _segment(0xDA, b"\x01\x01\x00\x00\x3f\x00")))


def encode_flat(payloads: list[np.ndarray]) -> list[bytes]:
    """Each payload (uint8, a positive multiple of 576 long) as a run of JPEG
    images with one flat block for each byte, a restart after each row."""
    frames = [p[i:i + UNIT * UNITS] for p in payloads for i in range(0, len(p), UNIT * UNITS)]
    owner = [k for k, p in enumerate(payloads) for _ in range(0, len(p), UNIT * UNITS)]
    samples = np.concatenate(frames).reshape(-1, ACROSS).astype(np.int32) - 128
    diff = np.diff(samples, axis=1, prepend=0)
    size = _SIZES.take(np.abs(diff))
    extra = np.where(diff < 0, diff + (1 << size) - 1, diff)
    width = size + 5
    value = ((size << size) | extra) << 1
    ends = np.cumsum(width, axis=1)
    row_bits = ends[:, -1]
    row_bytes = (row_bits + 7) >> 3
    row_start = np.cumsum(row_bytes) - row_bytes
    at = (ends - width + 8 * row_start[:, None]).ravel()
    # a code has at most 13 bits, so it touches two 16-bit units; units add up as no bits overlap
    word = value.ravel().astype(np.int64) << (32 - (at & 15) - width.ravel())
    total, unit = int(row_bytes.sum()), at >> 4
    data = np.bincount(unit, word >> 16, total // 2 + 2) + np.bincount(unit + 1, word & 0xFFFF, total // 2 + 2)
    data = data.astype(">u2").view(np.uint8)[:total].copy()
    data[row_start + row_bytes - 1] |= ((1 << (8 * row_bytes - row_bits)) - 1).astype(np.uint8)  # padding is ones
    # stuffing behind 255, a restart marker behind each row but an image's last
    rows_of = np.array([len(f) // ACROSS for f in frames])
    last_row = np.cumsum(rows_of) - 1
    in_frame = np.arange(len(samples)) - np.repeat(last_row + 1 - rows_of, rows_of)
    marked = np.ones(len(samples), bool)
    marked[last_row] = False
    full = data == 255
    row_of = np.repeat(np.arange(len(samples)), row_bytes)
    marks_before = np.cumsum(marked) - marked
    place = np.arange(total) + np.cumsum(full) - full + 2 * marks_before[row_of]
    out = np.zeros(total + int(full.sum()) + 2 * int(marked.sum()), np.uint8)
    out[place] = data
    tail = row_start + row_bytes - 1
    mark_at = (place[tail] + 1 + full[tail])[marked]
    out[mark_at] = 0xFF
    out[mark_at + 1] = 0xD0 + in_frame[marked] % 8
    stop = place[tail[last_row]] + 1 + full[tail[last_row]]
    images: list[list[bytes]] = [[] for _ in payloads]
    begin = 0
    for k, rows, end in zip(owner, rows_of, stop):
        images[k] += [_head(int(rows)), out[begin:end].tobytes(), b"\xff\xd9"]
        begin = end
    return [b"".join(parts) for parts in images]


def split_images(raw: bytes) -> list[Header]:
    """Headers of all images in a run of JPEG images."""
    found, at = [], 0
    while at < len(raw):
        found.append(parse(raw, at))
        at = found[-1].end
    return found
