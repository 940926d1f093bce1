"""Progressive JPEG for media columns.

`decode_batch` reads progressive images: every scan adds a spectral band or one more bit of precision to the
coefficient arrays of its component; at the end the coefficients are inverse-transformed by a matrix product, chroma is
upsampled to full resolution and converted, and the RGB tensor is returned. Entropy decoding runs in lockstep: the
restart intervals of all images of a batch are independent bit strings, and one numpy step advances each by a symbol.

`encode_payload` stores bytes losslessly in an image's own unit, its quantised coefficients: byte b becomes the
coefficient b + 2 of a 4:2:0 image with unit quantisers, in four scans per component (DC and AC, each once without
its lowest bit and once with it) and a restart marker every RESTART blocks. No coefficient becomes 0 without its lowest bit, so the
encoder has no runs to code; the decoder takes any baseline Huffman tables, runs, bands, bit positions and restart intervals, in
non-interleaved scans of one component and interleaved DC scans. It reads 8-bit images of one or three components.

Results for odd input: a null or empty text is a payload of one block row of padding; a null doc_id stays null; rows that
repeat give equal values; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, IntegerType, StructField, StructType

from .shared import prepare_workers

UNIT = 576  # payloads are padded to a multiple of this
BLOCK = 64
RESTART = 12  # blocks between restart markers
BATCH = 2 << 20  # payload bytes coded at a time
# Fixed values of the format: place of each coefficient of a block in coded order.
ZIGZAG = np.array([
    0, 1, 8, 16, 9, 2, 3, 10, 17, 24, 32, 25, 18, 11, 4, 5, 12, 19, 26, 33, 40, 48, 41, 34, 27, 20, 13, 6, 7, 14, 21, 28,
    35, 42, 49, 56, 57, 50, 43, 36, 29, 22, 15, 23, 30, 37, 44, 51, 58, 59, 52, 45, 38, 31, 39, 46, 53, 60, 61, 54, 47, 55, 62, 63,
])


# ---------------------------------------------------------------- Huffman tables


def huffman_codes(bits: list[int], values: list[int]) -> dict[int, tuple[int, int]]:
    """symbol -> (code, length) of a table given as numbers of codes by length and symbols in order."""
    out, code, at = {}, 0, 0
    for length, n in enumerate(bits, 1):
        for _ in range(n):
            out[values[at]] = (code, length)
            code, at = code + 1, at + 1
        code <<= 1
    return out


def lookup(bits: list[int], values: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """(symbol, length) for the next 16 bits; length 0 where no code fits."""
    symbol, size = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64)
    for s, (code, length) in huffman_codes(bits, values).items():
        a = code << (16 - length)
        symbol[a : a + (1 << (16 - length))], size[a : a + (1 << (16 - length))] = s, length
    return symbol, size


# Symbols of the encoder: DC difference sizes, and AC sizes after no run, commonest first; 0x00 ends a band, 0xE0 many.
DC_TABLE = ([0, 2, 3, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0, 0, 0], [5, 6, 4, 3, 7, 2, 8, 1, 0])
AC_TABLE = ([1, 0, 1, 1, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0], [6, 5, 4, 8, 7, 3, 1, 2, 0])
REFINE_TABLE = ([0, 2, 2, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0], [0x20, 0x10, 0x00, 0x30])


# ---------------------------------------------------------------- bit strings


def join_codes(codes: np.ndarray, lengths: np.ndarray, owner: np.ndarray, n: int) -> list[bytes]:
    """Bytes of each of n bit strings from codes of up to 32 bits in order; rest bits are 1, and 0xFF is followed by 0."""
    per = np.bincount(owner, lengths, n).astype(np.int64)
    size = -(-per // 8)
    base = np.concatenate([[0], np.cumsum(size)])
    ends = np.cumsum(lengths)
    before = np.concatenate([[0], np.cumsum(per)])[owner]
    at = (ends - lengths) - before + 8 * base[owner]
    total = int(base[-1])
    words = np.zeros(total // 8 + 2, np.uint64)
    if len(at):
        word, over = at >> 6, (at & 63) + lengths - 64
        shift = np.abs(over).astype(np.uint64)
        top = np.where(over > 0, codes >> shift, codes << shift)
        first = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
        words[word[first]] = np.bitwise_or.reduceat(top, first)
        split = np.flatnonzero(over > 0)
        words[word[split] + 1] |= codes[split] << (np.uint64(64) - shift[split])
    raw = words.astype(">u8").view(np.uint8)[:total].copy()
    rest = 8 * size - per
    some = size > 0
    raw[base[1:][some] - 1] |= ((1 << rest[some]) - 1).astype(np.uint8)
    marks = np.flatnonzero(raw == 255)
    data = np.insert(raw, marks + 1, 0).tobytes()
    cuts = base + np.searchsorted(marks, base)
    return [data[a:b] for a, b in zip(cuts, cuts[1:], strict=False)]


class Bits:
    """Many bit strings side by side, each with its own place."""

    def __init__(self, strings: list[bytes]):
        plain = [s.replace(b"\xff\x00", b"\xff") for s in strings]
        size = np.array([len(s) + 12 for s in plain])
        self.base = (np.cumsum(size) - size) * 8
        self.data = np.frombuffer(b"".join(s + b"\xff" * 12 for s in plain), np.uint8)
        padded = np.concatenate([self.data, np.full(-len(self.data) % 8 + 8, 255, np.uint8)])
        self.words = padded.view(">u8").astype(np.uint64)
        self.at = self.base.copy()

    def peek(self, who: np.ndarray, n: int) -> np.ndarray:
        at = self.at[who]
        word, bit = at >> 6, (at & 63).astype(np.uint64)
        window = (self.words[word] << bit) | ((self.words[word + 1] >> np.uint64(1)) >> (np.uint64(63) - bit))
        return (window >> np.uint64(64 - n)).astype(np.int64)

    def take(self, who: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Values of the next `lengths` (0 to 16) bits."""
        out = self.peek(who, 16) >> (16 - lengths)
        self.at[who] += lengths
        return out

    def symbol(self, who: np.ndarray, tables: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
        """tables: (symbols, lengths), each one row per string or a single shared row."""
        code = self.peek(who, 16)
        symbols, lengths = tables
        self.at[who] += lengths[code]
        return symbols[code]


def extend(value: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Signed value of `size` extra bits."""
    return np.where(value < (1 << size >> 1), value - (1 << size) + 1, value)


# ---------------------------------------------------------------- container


@dataclass
class Component:
    number: int
    h: int
    v: int
    table: int
    wide: int = 0  # blocks of the component itself
    high: int = 0
    coefficients: np.ndarray | None = None  # (blocks of whole MCUs high, wide, 64), coded order


@dataclass
class Image:
    width: int = 0
    height: int = 0
    components: list[Component] = field(default_factory=list)
    quantisers: dict[int, np.ndarray] = field(default_factory=dict)
    huffman: dict[int, tuple] = field(default_factory=dict)
    interval: int = 0
    comment: bytes = b""
    scans: list[tuple] = field(default_factory=list)  # (component numbers, table ids, start, end, high, low, interval, tables, strings)


def segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 255, marker, len(body) + 2) + body


def parse(data: bytes) -> Image:
    """Headers and the bit strings of all scans."""
    image, at = Image(), 2
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG image")
    while at < len(data):
        marker = data[at + 1]
        if marker == 0xD9:
            break
        size = struct.unpack(">H", data[at + 2 : at + 4])[0]
        body, at = data[at + 4 : at + 2 + size], at + 2 + size
        if marker in (0xC0, 0xC1, 0xC3, *range(0xC5, 0xC8), *range(0xC9, 0xCC), *range(0xCD, 0xD0)):
            raise ValueError("only progressive images with Huffman codes are read")
        if marker == 0xC2:
            precision, image.height, image.width, n = struct.unpack(">BHHB", body[:6])
            if precision != 8:
                raise ValueError("only 8-bit images are read")
            image.components = [Component(c, hv >> 4, hv & 15, t) for c, hv, t in (body[6 + 3 * i : 9 + 3 * i] for i in range(n))]
            hm, vm = max(c.h for c in image.components), max(c.v for c in image.components)
            if any(hm % c.h or vm % c.v for c in image.components):
                raise ValueError("only whole sampling ratios are read")
            mx, my = -(-image.width // (8 * hm)), -(-image.height // (8 * vm))
            for c in image.components:
                c.wide, c.high = -(-(-(-image.width * c.h // hm)) // 8), -(-(-(-image.height * c.v // vm)) // 8)
                c.coefficients = np.zeros((my * c.v, mx * c.h, BLOCK), np.int32)
        elif marker == 0xDB:
            while body:
                wide, number = body[0] >> 4, body[0] & 15
                values = np.frombuffer(body[1 : 1 + 64 * (1 + wide)], ">u2" if wide else np.uint8).astype(np.int64)
                image.quantisers[number], body = values, body[1 + 64 * (1 + wide) :]
        elif marker == 0xC4:
            while body:
                n = sum(body[1:17])
                image.huffman[body[0]], body = (tuple(body[1:17]), tuple(body[17 : 17 + n])), body[17 + n :]
        elif marker == 0xDD:
            image.interval = struct.unpack(">H", body)[0]
        elif marker == 0xFE:
            image.comment = body
        elif marker == 0xDA:
            n = body[0]
            parts = [(body[1 + 2 * i], body[2 + 2 * i]) for i in range(n)]
            start, end, precision = body[1 + 2 * n : 4 + 2 * n]
            stop, strings, a = at, [], at
            while True:
                stop = data.index(b"\xff", stop)
                follows = data[stop + 1]
                if follows == 0 or follows == 255:
                    stop += 2 if follows == 0 else 1
                    continue
                strings.append(data[a:stop])
                if not 0xD0 <= follows <= 0xD7:
                    break
                stop = a = stop + 2
            at = stop
            image.scans.append((parts, start, end, precision >> 4, precision & 15, image.interval, dict(image.huffman), strings))
    return image


# ---------------------------------------------------------------- entropy decoding


@dataclass
class Interval:
    """A restart interval: where its blocks go, in order, and the component of each for interleaved scans."""

    target: np.ndarray  # row numbers in the flat coefficient array of the batch
    part: np.ndarray


def _block_order(image: Image, parts, offsets: dict[int, int]) -> tuple[np.ndarray, np.ndarray, int]:
    """(coefficient rows, part numbers, blocks per MCU) of a scan's blocks in coded order."""
    own = [next(c for c in image.components if c.number == number) for number, _ in parts]
    if len(own) == 1:
        c = own[0]
        stride = c.coefficients.shape[1]
        rows = offsets[c.number] + (np.arange(c.high)[:, None] * stride + np.arange(c.wide)).ravel()
        return rows, np.zeros(len(rows), np.int64), 1
    my, mx = own[0].coefficients.shape[0] // own[0].v, own[0].coefficients.shape[1] // own[0].h
    y, x = np.divmod(np.arange(my * mx), mx)
    rows, part = [], []
    for i, c in enumerate(own):
        for v in range(c.v):
            for h in range(c.h):
                rows.append(offsets[c.number] + (y * c.v + v) * c.coefficients.shape[1] + x * c.h + h)
                part.append(np.full(len(x), i))
    return np.stack(rows, 1).ravel(), np.stack(part, 1).ravel(), len(rows)


def decode_scans(images: list[Image]) -> np.ndarray:
    """All scans of all images, in lockstep over restart intervals; returns the batch's coefficients (blocks, 64)."""
    offsets, total = [], 0
    for image in images:
        own = {}
        for c in image.components:
            own[c.number] = total
            total += c.coefficients.shape[0] * c.coefficients.shape[1]
        offsets.append(own)
    flat = np.zeros((total, BLOCK), np.int32)
    for nth in range(max((len(i.scans) for i in images), default=0)):
        groups: dict[tuple, tuple[list, list, list]] = {}
        for image, own in zip(images, offsets, strict=True):
            if nth >= len(image.scans):
                continue
            parts, start, end, high, low, interval, tables, strings = image.scans[nth]
            rows, part, per = _block_order(image, parts, own)
            used = tuple(tables.get(t >> 4 if start == 0 else 16 + (t & 15)) for _, t in parts)
            step = (interval or len(rows)) * per if interval else len(rows)
            group = groups.setdefault((start, end, high, low, used), ([], [], []))
            for i, string in enumerate(strings):
                group[0].append(string)
                group[1].append(rows[i * step : (i + 1) * step])
                group[2].append(part[i * step : (i + 1) * step])
        for (start, end, high, low, used), (strings, rows, part) in groups.items():
            counts = np.array([len(r) for r in rows])
            grid = np.full((len(rows), counts.max(initial=0)), -1, np.int64)
            kind = np.zeros_like(grid)
            mask = np.arange(grid.shape[1]) < counts[:, None]
            grid[mask], kind[mask] = np.concatenate(rows), np.concatenate(part)
            bits = Bits(strings)
            if start == 0 and high == 0:
                _dc_first(flat, bits, grid, kind, low, [lookup(*t) for t in used])
            elif start == 0:
                _dc_more(flat, bits, grid, low)
            elif high == 0:
                _ac_first(flat, bits, grid, counts, start, end, low, lookup(*used[0]))
            else:
                _ac_more(flat, bits, grid, counts, start, end, low, lookup(*used[0]))
    return flat


def _dc_first(flat, bits, grid, kind, low, tables):
    last = np.zeros((len(grid), len(tables)), np.int64)
    for column in range(grid.shape[1]):
        live = np.flatnonzero(grid[:, column] >= 0)
        for p, table in enumerate(tables):
            who = live[kind[live, column] == p] if len(tables) > 1 else live
            if not len(who):
                continue
            size = bits.symbol(who, table)
            last[who, p] += extend(bits.take(who, size), size)
            flat[grid[who, column], 0] = last[who, p] << low


def _dc_more(flat, bits, grid, low):
    for column in range(grid.shape[1]):
        who = np.flatnonzero(grid[:, column] >= 0)
        flat[grid[who, column], 0] |= (bits.take(who, np.ones(len(who), np.int64)) << low).astype(np.int32)


def _ac_first(flat, bits, grid, counts, start, end, low, table):
    block, k = np.zeros(len(grid), np.int64), np.full(len(grid), start, np.int64)
    cells = flat.reshape(-1)
    who = np.flatnonzero(counts > 0)
    while len(who):
        code = bits.symbol(who, table)
        run, size = code >> 4, code & 15
        value = bits.take(who, np.where(size > 0, size, np.where(run < 15, run, 0)))
        coded = size > 0
        at = k[who] + run
        c = who[coded]
        cells[grid[c, block[c]] * BLOCK + at[coded]] = extend(value[coded], size[coded]) << low
        k[who] = at + 1  # also right for sixteen zeros, code 15/0
        done = ~coded & (run < 15)
        if done.any():
            block[who[done]] += (1 << run[done]) + value[done]
            k[who[done]] = start
        over = coded & (k[who] > end)
        if over.any():
            block[who[over]] += 1
            k[who[over]] = start
        if done.any() or over.any():
            who = who[block[who] < counts[who]]


def _ac_more(flat, bits, grid, counts, start, end, low, table):
    """A further bit of a band: corrections of known coefficients, and new ones placed among the zeros."""
    step = np.int32(1 << low)
    block, k = np.zeros(len(grid), np.int64), np.full(len(grid), start, np.int64)
    to_skip = np.zeros(len(grid), np.int64)  # blocks left in an end-of-band run
    zeros = np.full(len(grid), -1, np.int64)  # zeros to pass before the pending coefficient; -1: none pending
    pending = np.zeros(len(grid), np.int32)
    who = np.flatnonzero(counts > 0)
    cells = flat.reshape(-1)
    while len(who):
        # whole blocks of a run whose coefficients are all known: their corrections are consecutive bits
        idle = who[(to_skip[who] > 0) & (k[who] == start)]
        if len(idle):
            rows = grid[idle, block[idle]]
            own = flat[rows, start : end + 1]
            known = own != 0
            n = known.sum(1)
            place = np.cumsum(known, 1) - 1
            at = bits.at[idle][:, None] + np.where(known, place, 0)
            bit = (bits.data[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1
            flat[rows, start : end + 1] = own + np.sign(own) * (step * (bit.astype(np.int32) & known))
            bits.at[idle] += n
            to_skip[idle] -= 1
            block[idle] += 1
            who = who[block[who] < counts[who]]
            continue
        fresh = who[(zeros[who] < 0) & (to_skip[who] == 0)]
        if len(fresh):
            code = bits.symbol(fresh, table)
            run, size = code >> 4, code & 15
            ends = (size == 0) & (run < 15)
            value = bits.take(fresh, np.where(size > 0, 1, np.where(ends, run, 0)))
            e = fresh[ends]
            to_skip[e] = (1 << run[ends]) + value[ends]
            g = fresh[~ends]
            zeros[g] = run[~ends]
            pending[g] = np.where(size[~ends] > 0, np.where(value[~ends] > 0, step, -step), 0)
        # one coefficient of every string that has something pending or is inside a block of a run
        cell = grid[who, block[who]] * BLOCK + k[who]
        now = cells[cell]
        known = now != 0
        fix = who[known]
        if len(fix):
            bit = bits.take(fix, np.ones(len(fix), np.int64)).astype(np.int32)
            cells[cell[known]] = now[known] + np.sign(now[known]) * step * bit
        empty = ~known
        waiting = empty & (zeros[who] >= 0)
        land = waiting & (zeros[who] == 0)
        put = who[land]
        cells[cell[land]] = pending[put]
        zeros[who[waiting]] -= 1
        k[who] += 1
        over = who[k[who] > end]
        if len(over):
            block[over] += 1
            k[over] = start
            zeros[over] = -1
            to_skip[over] = np.maximum(to_skip[over] - 1, 0)
            who = who[block[who] < counts[who]]


# ---------------------------------------------------------------- pixels


def _basis() -> np.ndarray:
    """64 x 64: coefficients in coded order to samples of a block."""
    x, u = np.meshgrid(np.arange(8), np.arange(8), indexing="ij")
    one = np.cos((2 * x + 1) * u * np.pi / 16) * np.where(u == 0, np.sqrt(0.125), 0.5)
    return np.einsum("yv,xu->vuyx", one, one).reshape(64, 64)[ZIGZAG].astype(np.float32)


def to_rgb(image: Image, basis: np.ndarray) -> np.ndarray:
    """Full-resolution uint8 tensor (height, width, 3)."""
    hm, vm = max(c.h for c in image.components), max(c.v for c in image.components)
    planes = []
    for c in image.components:
        rows, cols, _ = c.coefficients.shape
        scaled = c.coefficients.reshape(-1, BLOCK).astype(np.float32) * image.quantisers[c.table].astype(np.float32)
        samples = (scaled @ basis).reshape(rows, cols, 8, 8).transpose(0, 2, 1, 3).reshape(rows * 8, cols * 8) + np.float32(128)
        if c.h < hm:
            samples = samples.repeat(hm // c.h, 1)
        if c.v < vm:
            samples = samples.repeat(vm // c.v, 0)
        planes.append(samples[: image.height, : image.width])
    if len(planes) == 1:
        planes = planes * 3
    else:
        y, b, r = planes[0], planes[1] - 128, planes[2] - 128
        # fixed values of the colour transform
        planes = [y + np.float32(1.402) * r, y - np.float32(0.344136) * b - np.float32(0.714136) * r, y + np.float32(1.772) * b]
    return np.clip(np.rint(np.stack(planes, 2)), 0, 255).astype(np.uint8)


def decode_batch(files: list[bytes]) -> list[Image]:
    images = [parse(f) for f in files]
    flat, at = decode_scans(images), 0
    for image in images:
        for c in image.components:
            n = c.coefficients.shape[0] * c.coefficients.shape[1]
            c.coefficients = flat[at : at + n].reshape(c.coefficients.shape)
            at += n
    return images


# ---------------------------------------------------------------- payloads


def padded(text: bytes) -> bytes:
    return text + b"\xff" * (-len(text) % UNIT if text else UNIT)


def _shape(blocks: int) -> tuple[int, int]:
    """MCUs across and down of a 4:2:0 image for so many blocks."""
    mcus = -(-blocks // 6)
    across = -(-mcus // 4095)
    return across, -(-mcus // across)


def _dht(kind: int, table) -> bytes:
    return segment(0xC4, bytes([kind, *table[0], *table[1]]))


def encode_payloads(payloads: list[bytes]) -> list[bytes]:
    """A progressive JPEG for each payload of whole blocks."""
    shapes = [_shape(len(p) // BLOCK) for p in payloads]
    dc = np.array([huffman_codes(*DC_TABLE).get(s, (0, 0)) for s in range(12)], np.int64)
    ac = np.array([huffman_codes(*AC_TABLE).get(s, (0, 0)) for s in range(12)], np.int64)
    sizes = np.array([int(v).bit_length() for v in range(1024)])
    rows, owner, scans = [], [], []
    blocks = [6 * a * b for a, b in shapes]
    data = b"".join(p + b"\x00" * (BLOCK * n - len(p)) for p, n in zip(payloads, blocks, strict=True))
    values = np.frombuffer(data, np.uint8).reshape(-1, BLOCK).astype(np.int64) + 2
    first = np.concatenate([[0], np.cumsum(blocks)])
    # restart intervals: every component of every image in pieces of RESTART blocks
    for i, n in enumerate(blocks):
        third = n // 6
        for a, b in ((0, 4 * third), (4 * third, 5 * third), (5 * third, n)):
            for s in range(a, b, RESTART):
                rows.append((first[i] + s, first[i] + min(s + RESTART, b)))
                owner.append((i, (0, 4 * third, 5 * third).index(a)))
    spans = np.array(rows)
    count = spans[:, 1] - spans[:, 0]
    string = np.repeat(np.arange(len(spans)), count)
    half, bit = values >> 1, (values & 1).astype(np.uint64)
    # DC without its lowest bit, as differences within an interval
    diff = half[:, 0].copy()
    diff[1:] -= half[:-1, 0]
    diff[spans[:, 0]] = half[spans[:, 0], 0]
    size = sizes[np.abs(diff)]
    extra = np.where(diff < 0, diff + (1 << size) - 1, diff)
    scans.append(join_codes((dc[size, 0] << size | extra).astype(np.uint64), dc[size, 1] + size, string, len(spans)))
    scans.append(join_codes(bit[:, 0], np.ones(len(string), np.int64), string, len(spans)))
    # AC without their lowest bits: no zeros, so each is one code
    size = sizes[half[:, 1:]]
    scans.append(join_codes((ac[size, 0] << size | half[:, 1:]).astype(np.uint64).ravel(), (ac[size, 1] + size).ravel(), np.repeat(string, 63), len(spans)))
    # their lowest bits: one end-of-band run over the interval, then a correction for each
    run = np.array([int(c).bit_length() - 1 for c in count])
    symbols = {r: huffman_codes(*REFINE_TABLE)[r << 4] for r in range(RESTART.bit_length())}
    head = np.array([symbols[r][0] for r in run]) << run | (count - (1 << run))
    head_size = np.array([symbols[r][1] for r in run]) + run
    low = bit[:, 1:]
    weights = np.uint64(1) << np.arange(20, -1, -1, dtype=np.uint64)
    packed = (low.reshape(-1, 3, 21) * weights).sum(2, dtype=np.uint64)  # 63 bits as three codes of 21
    codes = np.insert(packed.ravel(), 3 * (np.cumsum(count) - count), head.astype(np.uint64))
    lengths = np.insert(np.full(3 * len(string), 21), 3 * (np.cumsum(count) - count), head_size)
    strings = np.insert(np.repeat(string, 3), 3 * (np.cumsum(count) - count), np.arange(len(spans)))
    scans.append(join_codes(codes, lengths, strings, len(spans)))
    parts: dict[tuple[int, int], list[int]] = {}
    for n, key in enumerate(owner):
        parts.setdefault(key, []).append(n)
    out = []
    fixed = segment(0xDB, bytes([0]) + bytes([1] * 64)) + _dht(0x00, DC_TABLE) + _dht(0x10, AC_TABLE) + _dht(0x11, REFINE_TABLE) + segment(0xDD, struct.pack(">H", RESTART))
    for i, (p, (across, down)) in enumerate(zip(payloads, shapes, strict=True)):
        frame = struct.pack(">BHHB", 8, 16 * down, 16 * across, 3) + bytes([1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])
        file = [b"\xff\xd8", segment(0xFE, struct.pack(">Q", len(p))), segment(0xC2, frame), fixed]
        for start, end, precision, table, strings_ in ((0, 0, 0x01, 0x00, scans[0]), (0, 0, 0x10, 0x00, scans[1]), (1, 63, 0x01, 0x00, scans[2]), (1, 63, 0x10, 0x01, scans[3])):
            for c in range(3):
                file.append(segment(0xDA, bytes([1, c + 1, table, start, end, precision])))
                for n, s in enumerate(parts[i, c]):
                    if n:
                        file.append(bytes([255, 0xD0 + (n - 1) % 8]))
                    file.append(strings_[s])
        out.append(b"".join(file) + b"\xff\xd9")
    return out


def payload_of(image: Image) -> bytes:
    """The bytes that encode_payloads put into an image."""
    n = struct.unpack(">Q", image.comment)[0]
    values = np.concatenate([c.coefficients.reshape(-1) for c in image.components])[:n]
    return (values - 2).astype(np.uint8).tobytes()


def features(rgb: np.ndarray) -> str:
    """Mean colour of the image's quarters and its spread, as hexadecimal digits."""
    h, w = rgb.shape[0] // 2, rgb.shape[1] // 2
    quarters = [rgb[:h, :w], rgb[:h, w:], rgb[h:, :w], rgb[h:, w:]]
    means = [q.reshape(-1, 3).mean(0) for q in quarters] + [rgb.reshape(-1, 3).std(0)]
    return bytes(np.rint(np.concatenate(means)).astype(np.uint8)).hex()


SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _store(batches):
    basis = _basis()
    for batch in batches:
        ids = batch.column("doc_id").cast(pa.int64()).to_pylist()
        texts = batch.column("text").cast(pa.large_binary()).to_pylist()
        at = 0
        while at < len(texts):
            stop, size = at, 0
            while stop < len(texts) and (stop == at or size + len(texts[stop] or b"") < BATCH):
                size += len(texts[stop] or b"")
                stop += 1
            own = [t or b"" for t in texts[at:stop]]
            files = encode_payloads([padded(t) for t in own])
            rows = []
            for doc_id, text, file, image in zip(ids[at:stop], own, files, decode_batch(files), strict=True):
                back = payload_of(image)
                rows.append((doc_id, len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(file), hashlib.sha256(file).hexdigest(), features(to_rgb(image, basis))))
            names = [c.split()[0] for c in SCHEMA.split(", ")]
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)
            at = stop


def store_texts(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) -> digests of the payload read back from a progressive JPEG, and image features."""
    prepare_workers(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_store, SCHEMA)


TENSORS = 64 << 20  # bytes of decoded pixels after which rows are handed on


def tensors(files: list[bytes | None]) -> Iterator[tuple[int, np.ndarray | None]]:
    """(row, RGB tensor) in order; None for no file and for one that can't be read. Files decode together up to TENSORS bytes."""
    basis = _basis()
    held: list[tuple[int, bytes | None]] = []
    size = 0

    def decoded(group: list[bytes]) -> list[np.ndarray | None]:
        try:
            return [to_rgb(image, basis) for image in decode_batch(group)]
        except (ValueError, IndexError, KeyError, struct.error):
            return [None] if len(group) == 1 else [x for f in group for x in decoded([f])]

    def pixels(file: bytes | None) -> int:
        if not file:
            return 0
        try:
            image = parse(file)
        except (ValueError, IndexError, KeyError, struct.error):
            return -1
        return 3 * image.height * image.width if image.components else -1

    def close():
        found = iter(decoded([f for _, f in held if f is not None]))
        yield from ((row, None if f is None else next(found)) for row, f in held)

    for row, file in enumerate(files):
        n = pixels(file)
        if size + n > TENSORS and held:
            yield from close()
            held, size = [], 0
        held.append((row, file if n > 0 else None))
        size += max(n, 0)
    if held:
        yield from close()


def decode_column(media: DataFrame, column: str = "media") -> DataFrame:
    """media plus height, width and rgb (the tensor's bytes in row order) of a column of progressive JPEG files.

    They are null for a null or empty file and for one that isn't a readable progressive image; columns of media with these
    names are replaced. An empty table gives an empty result.
    """
    prepare_workers(media.sparkSession)
    own = [f for f in media.schema if f.name not in ("height", "width", "rgb")]
    schema = StructType([*own, StructField("height", IntegerType()), StructField("width", IntegerType()), StructField("rgb", BinaryType())])
    names = [f.name for f in own]

    def handed_on(batch, rows):
        at, found = zip(*rows, strict=True)
        kept = batch.select(names).slice(at[0], len(at))
        extra = [pa.array([None if t is None else t.shape[i] for t in found], pa.int32()) for i in (0, 1)]
        return pa.RecordBatch.from_arrays([*kept.columns, *extra, pa.array([None if t is None else t.tobytes() for t in found], pa.binary())], [*names, "height", "width", "rgb"])

    def run(batches):
        for batch in batches:
            rows, size = [], 0
            for row, t in tensors(batch.column(column).to_pylist()):
                rows.append((row, t))
                size += 0 if t is None else t.nbytes
                if size > TENSORS:
                    yield handed_on(batch, rows)
                    rows, size = [], 0
            if rows:
                yield handed_on(batch, rows)

    return media.mapInArrow(run, schema)
