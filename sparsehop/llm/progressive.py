"""Progressive JPEG in numpy: many images' scans decoded side by side.

A scan is cut at its restart markers into segments, and all segments of all
images of a batch that share a scan's parameters and tables are decoded in
lockstep: each step reads one symbol (or one refinement bit) of every segment.
Spectral-selection and successive-approximation scans gather in one coefficient
array; the inverse transform is an exact integer product in float64, so equal
images give equal samples in any batch; components are replicated to full resolution
and all of them are mixed: gray, YCbCr, RGB, CMYK and YCCK.

The encoder stores a payload losslessly: each byte plus 256 is one quantised
coefficient, 64 to a block in zigzag order. The blocks fill the luma plane of a
colour image, then its two chroma planes of half the width and height, each split
over six scans.
"""

from __future__ import annotations

import functools
import struct
from bisect import bisect_left
from dataclasses import dataclass, field

import numpy as np


def _zigzag() -> np.ndarray:
    """Natural index of each zigzag position, by walking the anti-diagonals."""
    cells = sorted(((r, c) for r in range(8) for c in range(8)), key=lambda x: (x[0] + x[1], x[0] if (x[0] + x[1]) % 2 else x[1]))
    return np.array([8 * r + c for r, c in cells])


ZIGZAG = _zigzag()
BIAS = 256
#: Units (2 x 2 luma blocks and one of each chroma) in a row of a payload's image, and how many a side can have.
ROW_UNITS, MOST_UNITS = 512, 65535 // 16
#: Blocks of a unit by component, and the sampling factors.
PLANES, FACTORS = (4, 1, 1), (0x22, 0x11, 0x11)
#: (first, last coefficient, high bit, low bit) of the payload's scans, each for every component.
SCRIPT = [(0, 0, 0, 1), (1, 5, 0, 1), (6, 63, 0, 1), (0, 0, 1, 0), (1, 5, 1, 0), (6, 63, 1, 0)]
FIRST_DC, FIRST_AC, MORE_AC = 0x08, 0x08, 0x00


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def _table(kind: int, number: int, symbol: int) -> bytes:
    """A Huffman table of one symbol, whose code is a single nought bit."""
    return _segment(0xC4, bytes([kind << 4 | number, 1, *[0] * 15, symbol]))


def _head(n_bytes: int, wide: int, high: int) -> bytes:
    frame = struct.pack(">BHHB", 8, high * 16, wide * 16, len(PLANES)) + bytes(x for k, f in enumerate(FACTORS) for x in (k + 1, f, 0))
    parts = [b"\xff\xd8", _segment(0xFE, b"payload %d" % n_bytes), _segment(0xDB, bytes([0, *[1] * 64])), _segment(0xC2, frame)]
    return b"".join([*parts, _table(0, 0, FIRST_DC), _table(1, 0, FIRST_AC), _table(1, 1, MORE_AC), _segment(0xDD, struct.pack(">H", 1))])


def _scan_bits(zz: np.ndarray, ss: int, se: int, ah: int, al: int) -> np.ndarray:
    """Bits of one scan, a row for each block: every block's record is equally long."""
    n, band = len(zz), zz[:, ss : se + 1].astype(np.uint16) + BIAS
    if ah:
        bits = ((band >> al) & 1).astype(np.uint8)
        return bits if ss == 0 else np.concatenate([np.zeros((n, 1), np.uint8), bits], axis=1)
    value = np.unpackbits((band >> al).astype(np.uint8)[:, :, None], axis=2)
    return np.concatenate([np.zeros((n, se - ss + 1, 1), np.uint8), value], axis=2).reshape(n, -1)


def encode_payloads(payloads: list[bytes]) -> list[bytes]:
    """A progressive JPEG for each payload, whose length is a positive multiple of 64."""
    shapes, blocks = [], []
    for p in payloads:
        n = len(p) // 64
        units = -(-n // sum(PLANES))
        wide = max(min(units, ROW_UNITS), -(-units // MOST_UNITS))
        high = -(-units // wide)
        shapes.append((len(p), wide, high))
        blocks.append(np.frombuffer(p + bytes(64 * (sum(PLANES) * wide * high - n)), np.uint8))
    if not payloads:
        return []
    zz = np.concatenate(blocks).reshape(-1, 64)
    # a component's blocks lie together, so each is coded like an image of its own
    counts = np.array([w * h * n for _, w, h in shapes for n in PLANES])
    ends = np.cumsum(counts)
    within = np.arange(len(zz)) - np.repeat(ends - counts, counts)
    last = np.zeros(len(zz), bool)
    last[ends - 1] = True
    files = [[_head(*s)] for s in shapes]
    for ss, se, ah, al in SCRIPT:
        bits = _scan_bits(zz, ss, se, ah, al)
        bits = np.concatenate([bits, np.ones((len(zz), -bits.shape[1] % 8), np.uint8)], axis=1)
        packed = np.packbits(bits, axis=1)
        data = np.concatenate([packed, np.full((len(zz), 1), 255, np.uint8), (0xD0 + within % 8).astype(np.uint8)[:, None]], axis=1)
        kept = np.ones(data.shape, bool)
        kept[last, -2:] = False
        stuffed = (data == 255) & (np.arange(data.shape[1]) < packed.shape[1])
        size = kept.astype(np.int64) + stuffed
        place = np.cumsum(size.ravel()) - size.ravel()
        total = int(size.sum())
        out = np.zeros(total, np.uint8)
        out[place[kept.ravel()]] = data.ravel()[kept.ravel()]
        after = np.concatenate([place.reshape(data.shape)[ends[:-1], 0], [total]])
        heads = [_segment(0xDA, bytes([1, k + 1, (1 if ah else 0) if ss else 0, ss, se, ah << 4 | al])) for k in range(len(PLANES))]
        start = 0
        for k, end in enumerate(after.tolist()):
            files[k // len(PLANES)] += [heads[k % len(PLANES)], out[start:end].tobytes()]
            start = end
    return [b"".join([*file, b"\xff\xd9"]) for file in files]


@functools.lru_cache(64)
def _lookup(lengths: bytes, symbols: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Symbol and code length for every 16 bits that may come next; length 0 where no code fits."""
    symbol, length = np.zeros(1 << 16, np.int32), np.zeros(1 << 16, np.int64)
    code = at = 0
    for bits, n in enumerate(lengths, 1):
        for _ in range(n):
            low, high = code << (16 - bits), (code + 1) << (16 - bits)
            symbol[low:high], length[low:high] = symbols[at], bits
            code, at = code + 1, at + 1
        code <<= 1
    return symbol, length


@dataclass
class Component:
    number: int
    across: int
    down: int
    quant: int
    blocks: tuple[int, int] = (0, 0)
    padded: tuple[int, int] = (0, 0)
    base: int = 0


@dataclass
class Scan:
    parts: list[int]
    tables: list[tuple[int, int]]
    band: tuple[int, int, int, int]
    luts: dict[tuple[int, int], tuple[bytes, bytes]]
    restart: int
    data: np.ndarray
    #: What scans share that are decoded in lockstep.
    alike: tuple = ()


@dataclass
class Image:
    width: int = 0
    height: int = 0
    components: list[Component] = field(default_factory=list)
    quants: dict[int, np.ndarray] = field(default_factory=dict)
    scans: list[Scan] = field(default_factory=list)
    comment: bytes = b""
    jfif: bool = False
    #: The colour transform that an Adobe marker names.
    transform: int | None = None
    orders: dict[tuple[int, ...], tuple[np.ndarray, np.ndarray, int]] = field(default_factory=dict)


def parse(raw: bytes) -> Image:
    image, restart, at = Image(), 0, 2
    luts: dict[tuple[int, int], tuple[bytes, bytes]] = {}
    keyed: tuple = ()
    array = np.frombuffer(raw, np.uint8)
    markers = np.flatnonzero((array[:-1] == 255) & (array[1:] != 0) & ((array[1:] < 0xD0) | (array[1:] > 0xD7))).tolist()
    while at < len(raw) - 1:
        marker = raw[at + 1]
        if marker == 0xD9:
            break
        n = raw[at + 2] << 8 | raw[at + 3]
        body, at = raw[at + 4 : at + 2 + n], at + 2 + n
        if marker == 0xC2:
            image.height, image.width = body[1] << 8 | body[2], body[3] << 8 | body[4]
            image.components = [Component(body[i], body[i + 1] >> 4, body[i + 1] & 15, body[i + 2]) for i in range(6, 6 + 3 * body[5], 3)]
            most_x, most_y = max(c.across for c in image.components), max(c.down for c in image.components)
            for c in image.components:
                c.blocks = (-(-(-(-image.width * c.across // most_x)) // 8), -(-(-(-image.height * c.down // most_y)) // 8))
                c.padded = (-(-image.width // (8 * most_x)) * c.across, -(-image.height // (8 * most_y)) * c.down)
        elif marker in (0xC0, 0xC1, *range(0xC3, 0xC4), *range(0xC5, 0xC8), *range(0xC9, 0xCC)):
            raise ValueError("only progressive Huffman-coded JPEG is read here")
        elif marker == 0xC4:
            while body:
                many = sum(body[1:17])
                luts = luts | {(body[0] >> 4, body[0] & 15): (body[1:17], body[17 : 17 + many])}
                body = body[17 + many :]
            keyed = tuple(sorted(luts.items()))
        elif marker == 0xDB:
            while body:
                wide = 128 if body[0] >> 4 else 64
                image.quants[body[0] & 15] = np.frombuffer(body[1 : 1 + wide], ">u2" if wide == 128 else np.uint8).astype(np.int64)
                body = body[1 + wide :]
        elif marker == 0xDD:
            restart = body[0] << 8 | body[1]
        elif marker == 0xFE:
            image.comment = body
        elif marker == 0xE0 and body[:5] == b"JFIF\0":
            image.jfif = True
        elif marker == 0xEE and body[:5] == b"Adobe" and len(body) >= 12:
            image.transform = body[11]
        elif marker == 0xDA:
            ids = [c.number for c in image.components]
            parts = [ids.index(body[1 + 2 * i]) for i in range(body[0])]
            tables = [(body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15) for i in range(body[0])]
            ss, se, a = body[-3:]
            following = bisect_left(markers, at)
            end = markers[following] if following < len(markers) else len(raw)
            band = (ss, se, a >> 4, a & 15)
            image.scans.append(Scan(parts, tables, band, luts, restart, array[at:end], (band, len(parts), tuple(tables), keyed)))
            at = end
    return image


def _order(image: Image, scan: Scan) -> tuple[np.ndarray, np.ndarray, int]:
    """Blocks of a scan in coded order, the scan's component of each, and the blocks of one unit; the same for all scans of the same components."""
    if (parts := tuple(scan.parts)) not in image.orders:
        image.orders[parts] = _coded_order(image, scan)
    return image.orders[parts]


def _coded_order(image: Image, scan: Scan) -> tuple[np.ndarray, np.ndarray, int]:
    if len(scan.parts) == 1:
        c = image.components[scan.parts[0]]
        (wide, high), stride = c.blocks, c.padded[0]
        return (c.base + np.arange(high)[:, None] * stride + np.arange(wide)).ravel(), np.zeros(wide * high, np.int64), 1
    first = image.components[0]
    units_x, units_y = first.padded[0] // first.across, first.padded[1] // first.down
    y, x = (a.ravel()[:, None] for a in np.mgrid[:units_y, :units_x])
    blocks, owner = [], []
    for k, part in enumerate(scan.parts):
        c = image.components[part]
        dy, dx = (a.ravel()[None, :] for a in np.mgrid[: c.down, : c.across])
        blocks.append(c.base + (y * c.down + dy) * c.padded[0] + x * c.across + dx)
        owner.append(np.full(c.down * c.across, k))
    own = np.concatenate(owner)
    return np.concatenate(blocks, axis=1).ravel(), np.tile(own, units_x * units_y), len(own)


class _Bits:
    """Bit positions of all segments over one buffer."""

    def __init__(self, data: np.ndarray) -> None:
        b = np.concatenate([data, np.zeros(8, np.uint8)]).astype(np.uint32)
        self.words = b[:-3] << 24 | b[1:-2] << 16 | b[2:-1] << 8 | b[3:]

    def peek(self, at: np.ndarray) -> np.ndarray:
        return (self.words[np.minimum(at >> 3, len(self.words) - 1)] >> (16 - (at & 7)).astype(np.uint32) & 0xFFFF).astype(np.int64)


def _extend(value: np.ndarray, size: np.ndarray) -> np.ndarray:
    return np.where(value < (1 << np.maximum(size - 1, 0)), value - (1 << size) + 1, value)


def _dc_scan(bits: _Bits, at, order, owner, first, count, coefs, scan: Scan) -> None:
    al = scan.band[3]
    luts = [_lookup(*scan.luts[0, dc]) for dc, _ in scan.tables] if not scan.band[2] else []
    seen = np.zeros((len(scan.parts), len(at)), np.int64)
    lane, done = np.arange(len(at)), 0
    while lane.size:
        block, part = order[first[lane] + done], owner[first[lane] + done]
        if scan.band[2]:
            coefs[block, 0] |= (bits.peek(at) >> 15) << al
            at = at + 1
        else:
            code, size = bits.peek(at), np.zeros(len(at), np.int64)
            for k, (symbol, length) in enumerate(luts):
                mine = part == k
                size = np.where(mine, symbol[code], size)
                at = np.where(mine, at + length[code], at)
            diff = _extend(bits.peek(at) >> (16 - size), size)
            at = at + size
            seen[part, lane] += diff
            coefs[block, 0] = seen[part, lane] << al
        done += 1
        if (ended := count[lane] <= done).any():
            lane, at = lane[~ended], at[~ended]


def _ac_first(bits: _Bits, at, order, first, count, coefs, scan: Scan) -> None:
    ss, se, _, al = scan.band
    symbol, length = _lookup(*scan.luts[1, scan.tables[0][1]])
    end = first + count
    k = np.full(len(at), ss)
    while at.size:
        code = bits.peek(at)
        sym = symbol[code]
        run, size = sym >> 4, sym & 15
        at = at + length[code]
        more = bits.peek(at)
        value = _extend(more >> (16 - size), size)
        put = size > 0
        k = k + np.where(put | (run == 15), run, 0)
        if put.all():
            coefs[order[first], ZIGZAG[np.minimum(k, 63)]] = value << al
            at, k, skip = at + size, k + 1, 0
        else:
            coefs[order[first[put]], ZIGZAG[np.minimum(k[put], 63)]] = value[put] << al
            ended = ~put & (run < 15)
            skip = np.where(ended, (1 << run) - 1 + np.where(run > 0, more >> (16 - np.maximum(run, 1)), 0), 0)
            at = at + np.where(ended, run, size)
            k = np.where(ended, 64, k + 1)
        over = k > se
        if over.any():
            first = first + np.where(over, 1 + skip, 0)
            k = np.where(over, ss, k)
            if (gone := first >= end).any():
                stay = ~gone
                at, k, first, end = at[stay], k[stay], first[stay], end[stay]


def _ac_more(bits: _Bits, at, order, first, count, coefs, scan: Scan) -> None:
    ss, se, _, al = scan.band
    symbol, length = _lookup(*scan.luts[1, scan.tables[0][1]])
    end = first + count
    k = np.full(len(at), ss)
    #: zeros still to pass (-1: no symbol in hand), value to place then, blocks left in a run of ended blocks
    run, value, ended = np.full(len(at), -1), np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
    while at.size:
        if (need := (run < 0) & (ended == 0)).any():
            i = np.flatnonzero(need)
            code = bits.peek(at[i])
            sym, at[i] = symbol[code], at[i] + length[code]
            r, s, more = sym >> 4, sym & 15, bits.peek(at[i])
            stop = (s == 0) & (r < 15)
            ended[i] = np.where(stop, (1 << r) + np.where(r > 0, more >> (16 - np.maximum(r, 1)), 0), 0)
            run[i] = np.where(stop, -1, r)
            value[i] = np.where(s > 0, np.where(more >> 15 > 0, 1, -1) << al, 0)
            at[i] += np.where(stop, r, s)
        block, place = order[first], ZIGZAG[k]
        now = coefs[block, place]
        old = now != 0
        bit = bits.peek(at) >> 15
        now = now + np.where(old, np.where(now > 0, bit, -bit) << al, 0)
        fill = ~old & (run == 0)
        coefs[block, place] = np.where(fill, value, now)
        at = at + old
        run = np.where(~old & (run >= 0), run - 1, run)
        k = k + 1
        over = k > se
        if over.any():
            ended = np.where(over, np.maximum(ended - 1, 0), ended)
            first, k = first + over, np.where(over, ss, k)
            if (gone := first >= end).any():
                stay = ~gone
                at, k, first, end, run, value, ended = (a[stay] for a in (at, k, first, end, run, value, ended))


def coefficients(files: list[bytes]) -> tuple[list[Image], np.ndarray]:
    """Quantised coefficients of all images, a row of 64 (natural order) for each block."""
    images, total = [parse(f) for f in files], 0
    for image in images:
        for c in image.components:
            c.base = total
            total += c.padded[0] * c.padded[1]
    coefs = np.zeros((total, 64), np.int32)
    left = [i.scans[::-1] for i in images]
    while any(left):
        alike: dict[tuple, list[tuple[Image, Scan]]] = {}
        for image, scans in zip(images, left, strict=True):
            if not scans:
                continue
            key, taken = scans[-1].alike, set()
            group = alike.setdefault(key, [])
            # scans that follow each other on other components do not touch each other's blocks
            while scans and scans[-1].alike == key and taken.isdisjoint(scans[-1].parts):
                scan = scans.pop()
                taken.update(scan.parts)
                group.append((image, scan))
        for group in alike.values():
            _scan_group(group, coefs)
    return images, coefs


def _scan_group(group: list[tuple[Image, Scan]], coefs: np.ndarray) -> None:
    raw = np.concatenate([s.data for _, s in group])
    ends = np.cumsum([len(s.data) for _, s in group])
    starts = ends - [len(s.data) for _, s in group]
    before = np.concatenate([[0], raw[:-1]])
    before[starts[starts < len(raw)]] = 0
    marker = (before == 255) & (raw >= 0xD0) & (raw <= 0xD7)
    drop = marker | ((before == 255) & (raw == 0))
    drop[:-1] |= marker[1:]
    place = np.concatenate([[0], np.cumsum(~drop)])
    cuts = np.flatnonzero(marker) + 1
    found = [_order(image, scan) for image, scan in group]
    sizes = np.array([len(order) for order, _, _ in found])
    steps = np.array([scan.restart * unit or len(order) for (_, scan), (order, _, unit) in zip(group, found, strict=True)])
    # a scan's segments: its start, then its cuts, and no more than its blocks need
    upto = np.searchsorted(cuts, ends, side="left")
    have = np.diff(upto, prepend=0) + 1
    heads = np.cumsum(have) - have
    lanes, head = np.empty(have.sum(), np.int64), np.zeros(have.sum(), bool)
    head[heads] = True
    lanes[head], lanes[~head] = starts, cuts[: upto[-1]]
    done = (np.arange(len(lanes)) - np.repeat(heads, have)) * np.repeat(steps, have)
    kept = done < np.repeat(sizes, have)
    first = (np.repeat(np.cumsum(sizes) - sizes, have) + done)[kept]
    count = np.minimum(np.repeat(steps, have), np.repeat(sizes, have) - done)[kept]
    order, owners = (np.concatenate([f[k] for f in found]) for k in (0, 1))
    bits, at, scan = _Bits(raw[~drop]), place[lanes[kept]].astype(np.int64) * 8, group[0][1]
    if scan.band[0] == 0:
        _dc_scan(bits, at, order, owners, first, count, coefs, scan)
    elif scan.band[2] == 0:
        _ac_first(bits, at, order, first, count, coefs, scan)
    else:
        _ac_more(bits, at, order, first, count, coefs, scan)


def _basis() -> np.ndarray:
    """Inverse transform of all 64 coefficients at once, scaled by 2**26 and rounded: products stay exact in float64."""
    u = np.arange(8)
    one = np.cos((2 * u[:, None] + 1) * u * np.pi / 16) * np.where(u == 0, np.sqrt(1 / 8), 0.5)
    whole = np.rint(one * 2**13)
    return np.kron(whole, whole).T


BASIS = _basis()


def _plane(image: Image, c: Component, coefs: np.ndarray) -> np.ndarray:
    """One component's samples at full resolution, replicated by whatever ratio its factors have to the largest ones."""
    wide, high = c.padded
    quant = np.ones(64, np.int64)
    quant[ZIGZAG] = image.quants[c.quant]
    samples = (coefs[c.base : c.base + wide * high] * quant).astype(np.float64) @ BASIS
    samples = np.clip(np.floor(samples / 2**26 + 128.5), 0, 255)
    plane = samples.reshape(high, wide, 8, 8).swapaxes(1, 2).reshape(high * 8, wide * 8)
    most_x, most_y = max(x.across for x in image.components), max(x.down for x in image.components)
    if c.down < most_y:
        plane = plane.take(np.arange(image.height) * c.down // most_y, 0)
    if c.across < most_x:
        plane = plane.take(np.arange(image.width) * c.across // most_x, 1)
    return plane[: image.height, : image.width]


def _mixed(image: Image) -> bool:
    """Whether the first three components are luma and chroma: a file marker says so, else the components' names."""
    if len(image.components) == 4:
        return image.transform == 2
    if image.jfif or image.transform is None:
        return image.jfif or [c.number for c in image.components] != [*b"RGB"]
    return image.transform != 0


def rgb(image: Image, coefs: np.ndarray) -> np.ndarray:
    """Full-resolution samples (height, width, 3) of one image, from all its components."""
    if len(image.components) not in (1, 3, 4):
        raise ValueError(f"no colours are known for {len(image.components)} components")
    planes = [_plane(image, c, coefs) for c in image.components]
    out = np.empty((image.height, image.width, 3), np.uint8)
    if len(planes) == 1:
        out[:] = planes[0][:, :, None]
        return out
    if _mixed(image):
        y, cb, cr = planes[0], planes[1] - 128, planes[2] - 128
        # fixed values: the full-range colour matrix of the JPEG file format
        colours = (y + 1.402 * cr, y - 0.344136 * cb - 0.714136 * cr, y + 1.772 * cb)
        planes[:3] = [np.clip(np.rint(x), 0, 255) for x in colours]
        if len(planes) == 4:
            planes[:3] = [255 - x for x in planes[:3]]
    if len(planes) == 4:
        # ink: what is left of the light; files with an Adobe marker store that itself
        light = planes if image.transform is not None else [255 - x for x in planes]
        planes = [np.rint(x * light[3] / 255) for x in light[:3]]
    for k, x in enumerate(planes):
        out[:, :, k] = x
    return out


def stored_payload(image: Image, coefs: np.ndarray) -> bytes:
    """The bytes that ``encode_payloads`` stored, read from decoded coefficients."""
    c = image.components[0]  # the other components' blocks follow its own
    n = int(image.comment.split()[1])
    values = coefs[c.base : c.base + n // 64][:, ZIGZAG] - BIAS
    if ((values < 0) | (values > 255)).any():
        raise ValueError("not a stored payload")
    return values.astype(np.uint8).tobytes()
