"""Baseline JPEG as a store of bytes, with a Huffman decoder that runs all restart intervals in step.

A payload byte is a quantised coefficient (byte - 128), 192 of them one MCU of three 8 x 8 blocks, in
zigzag order, under a quantisation table of ones; so the stored form is lossless and an ordinary
baseline file. Every MCU is a restart interval: intervals start at a byte, so numpy decodes one symbol
of every interval at a time. The decoder reads other baseline files as well (sampling factors, any
tables, any restart interval, none). The thumbnail is the luminance of the DC coefficients alone.
"""

from __future__ import annotations

import hashlib
import math
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shards as sh

MCU = 192
STEP_BYTES = 2 << 20
RESULT = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, width long, height long, thumbnail binary"


def _canonical(lengths: list[tuple[int, list[int]]]) -> tuple[np.ndarray, np.ndarray]:
    """Code and length of each of 256 symbols, from symbols by ascending length."""
    code, last = 0, 0
    codes, sizes = np.zeros(256, np.uint64), np.zeros(256, np.uint64)
    for size, symbols in lengths:
        code <<= size - last
        last = size
        for s in symbols:
            codes[s], sizes[s] = code, size
            code += 1
    return codes, sizes


#: Tables by rule: short codes for direct coefficients and the end of a block, one length for the rest.
DC_TABLE = [(4, list(range(12)))]
_SHORT = [0x00, *range(0x01, 0x0A), 0x11, 0x12, 0x13, 0xF0]
AC_TABLE = [(4, _SHORT), (12, [r << 4 | s for r in range(16) for s in range(1, 11) if (r << 4 | s) not in _SHORT])]


def _segment(marker: int, data: bytes) -> bytes:
    return bytes([0xFF, marker]) + (len(data) + 2).to_bytes(2, "big") + data


def _dht(kind: int, table: list[tuple[int, list[int]]]) -> bytes:
    counts = dict((size, len(s)) for size, s in table)
    return bytes([kind]) + bytes(counts.get(i, 0) for i in range(1, 17)) + bytes(s for _, symbols in table for s in symbols)


def shape_of(mcus: int) -> tuple[int, int]:
    """Columns and rows of MCUs, nearly square."""
    cols = math.isqrt(mcus - 1) + 1
    return cols, -(-mcus // cols)


def header(n_bytes: int, mcus: int) -> bytes:
    cols, rows = shape_of(mcus)
    if cols * 8 > 65535:
        raise ValueError("a payload of over 12 GB")
    frame = bytes([8]) + (rows * 8).to_bytes(2, "big") + (cols * 8).to_bytes(2, "big") + bytes([3, 1, 0x11, 0, 2, 0x11, 0, 3, 0x11, 0])
    return b"\xff\xd8" + _segment(0xFE, n_bytes.to_bytes(8, "big") + mcus.to_bytes(8, "big")) + _segment(0xDB, bytes([0]) + bytes([1] * 64)) + _segment(0xC0, frame) + _segment(0xC4, _dht(0x00, DC_TABLE) + _dht(0x10, AC_TABLE)) + _segment(0xDD, (1).to_bytes(2, "big")) + _segment(0xDA, bytes([3, 1, 0, 2, 0, 3, 0, 0, 63, 0]))


def _tokens(coefficients: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bits, their number and the block of every code of the blocks (n, 64)."""
    dc_code, dc_size = _canonical(DC_TABLE)
    ac_code, ac_size = _canonical(AC_TABLE)
    flat = coefficients.ravel()
    some = flat != 0
    some[::64] = True
    at = np.flatnonzero(some)
    value = flat[at].astype(np.int64)
    place = at & 63
    run = np.diff(at, prepend=-1) - 1
    run[place == 0] = 0
    size = np.frexp(np.abs(value).astype(np.float32))[1].astype(np.int64)
    bits = np.where(value < 0, value + (1 << size) - 1, value).astype(np.uint64)
    symbol = (run & 15) << 4 | size
    code = np.where(place == 0, dc_code[size], ac_code[symbol])
    length = np.where(place == 0, dc_size[size], ac_size[symbol])
    code = code << size.astype(np.uint64) | bits
    length = length + size.astype(np.uint64)
    block = at >> 6
    last = np.ones(len(at), dtype=bool)
    last[:-1] = block[1:] != block[:-1]
    zeros, ends = run >> 4, last & (place < 63)
    if not zeros.any() and not ends.any():
        return code, length, block
    count = 1 + zeros + ends
    own = np.cumsum(count) - 1 - ends
    out, sizes = np.full(int(count.sum()), ac_code[0xF0]), np.full(int(count.sum()), ac_size[0xF0])
    out[own], sizes[own] = code, length
    out[own[ends] + 1], sizes[own[ends] + 1] = ac_code[0], ac_size[0]
    return out, sizes, np.repeat(block, count)


def _direct() -> tuple[np.ndarray, np.ndarray]:
    """Code and length for each byte as a DC (row 0) or an AC coefficient without zeros before it (row 1)."""
    dc, ac = _canonical(DC_TABLE), _canonical(AC_TABLE)
    value = np.arange(256, dtype=np.int64) - 128
    size = np.frexp(np.abs(value).astype(np.float32))[1].astype(np.int64)
    bits = np.where(value < 0, value + (1 << size) - 1, value).astype(np.uint64)
    code = np.stack([t[0][size] << size.astype(np.uint64) | bits for t in (dc, ac)])
    return code, np.stack([t[1][size] + size.astype(np.uint64) for t in (dc, ac)])


def _spread(word: np.ndarray, first: np.ndarray, data: np.ndarray, planes: int) -> None:
    """ORs the leading bytes of 64-bit words into the data from `first` on; no two words of a plane start at one byte."""
    for i in range(planes):
        data[first + i] |= (word >> np.uint64(56 - 8 * i)).astype(np.uint8)


def _pack_direct(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For MCUs without zero AC coefficients: words of four codes each, their bit offsets in the MCU, and the MCUs' bits."""
    code, length = _direct()
    column = np.ones(MCU, dtype=np.intp)
    column[::64] = 0
    at = rows.astype(np.intp) + 256 * column
    bits, size = code.ravel()[at], length.ravel()[at]
    for _ in range(2):  # two codes to one, twice: at most 4 * 13 bits
        bits = bits[:, ::2] << size[:, 1::2] | bits[:, 1::2]
        size = size[:, ::2] + size[:, 1::2]
    ends = np.cumsum(size, axis=1)
    return bits << (np.uint64(64) - size), (ends - size).astype(np.int64), ends[:, -1].astype(np.int64)


def encode_mcus(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all intervals, one after another, and the size of each; rows: payload bytes, 192 an MCU."""
    n = len(rows)
    zero = rows == 128
    zero[:, ::64] = False
    hard = zero.any(axis=1)
    total = np.zeros(n, np.int64)
    word, offset, total[~hard] = _pack_direct(rows[~hard])
    some = np.flatnonzero(hard)
    if len(some):
        bits, length, block = _tokens((rows[some].astype(np.int16) - 128).reshape(-1, 64))
        mcu = block // 3
        head = np.flatnonzero(sh.first_of_runs(mcu))
        ends = np.cumsum(length).astype(np.int64)
        starts = ends - length.astype(np.int64)
        total[some] = np.diff(np.append(starts[head], ends[-1]))
    size = (total + 7) >> 3
    begin = np.cumsum(size) - size
    data = np.zeros(int(size.sum()) + 8, dtype=np.uint8)
    place = offset + 8 * begin[~hard][:, None]
    _spread(word >> (place & 7).astype(np.uint64), place >> 3, data, 8)
    if len(some):
        place = starts - np.repeat(starts[head], np.diff(head, append=len(mcu))) + 8 * begin[some][mcu]
        word = bits << (np.uint64(64) - length - (place & 7).astype(np.uint64))
        first = place >> 3
        group = np.flatnonzero(sh.first_of_runs(first))  # codes that start in one byte share no bit: their sum is their union
        _spread(np.add.reduceat(word, group), first[group], data, 4)
    data[begin + size - 1] |= ((1 << (8 * size - total).astype(np.uint8)) - 1).astype(np.uint8)
    return data[:-8], size


def encode_all(flat: np.ndarray, sizes: list[int]) -> list[bytes]:
    """The stored form of each payload; sizes: the unpadded bytes of each of the texts in `flat`."""
    mcus = [max(1, -(-n // MCU)) for n in sizes]
    grid = [c * r for c, r in map(shape_of, mcus)]
    rows = np.full((sum(grid), MCU), 128, dtype=np.uint8)  # 128 is coefficient 0
    at, row = 0, 0
    for n, m, g in zip(sizes, mcus, grid, strict=True):
        payload = rows[row : row + m].reshape(-1)
        payload[:n] = flat[at : at + n]
        payload[n:] = 32
        at, row = at + n, row + g
    data, size = encode_mcus(rows)
    ends = np.cumsum(size)
    index = np.concatenate([np.arange(g) for g in grid])
    last = np.zeros(len(size), dtype=bool)
    last[np.cumsum(grid) - 1] = True  # no marker after the last interval of an image
    stuffed = np.flatnonzero(data == 0xFF) + 1
    marked = ends[~last]
    where = np.concatenate([stuffed, np.repeat(marked, 2)])
    what = np.zeros(len(where), dtype=np.uint8)
    what[len(stuffed) :: 2] = 0xFF
    what[len(stuffed) + 1 :: 2] = 0xD0 + (index[~last] & 7)
    order = np.argsort(where, kind="stable")  # after a byte FF at an interval's end, its zero stands first
    out = np.insert(data, where[order], what[order])
    bounds = np.concatenate([[0], ends[last]])
    # Stuffing after an image's last byte still belongs to it.
    cuts = bounds + np.searchsorted(stuffed, bounds, side="right") + 2 * np.searchsorted(marked, bounds)
    return [header(n, m) + out[a:b].tobytes() + b"\xff\xd9" for n, m, a, b in zip(sizes, mcus, cuts[:-1], cuts[1:], strict=True)]


@dataclass
class Image:
    """What the markers of one baseline file say, and where its scan lies."""

    width: int = 0
    height: int = 0
    components: list[tuple[int, int, int, int]] = field(default_factory=list)  # id, h, v, quantisation
    quantisation: dict[int, np.ndarray] = field(default_factory=dict)
    huffman: dict[int, bytes] = field(default_factory=dict)
    tables: dict[int, tuple[int, int]] = field(default_factory=dict)
    restart: int = 0
    comments: list[bytes] = field(default_factory=list)
    scan: slice = slice(0, 0)


def parse(data: bytes) -> Image:
    """Walks the markers; raises ValueError for what baseline files can't hold."""
    image, i = Image(), 2
    if data[:2] != b"\xff\xd8":
        raise ValueError("no start of image")
    while True:
        while data[i] == 0xFF and data[i + 1] == 0xFF:
            i += 1
        if data[i] != 0xFF:
            raise ValueError("no marker where one is due")
        marker, size = data[i + 1], int.from_bytes(data[i + 2 : i + 4], "big")
        body = data[i + 4 : i + 2 + size]
        i += 2 + size
        if marker == 0xDB:
            while body:
                wide = body[0] >> 4
                n = 64 << wide
                image.quantisation[body[0] & 15] = np.frombuffer(body[1 : 1 + n], ">u2" if wide else "u1").astype(np.int64)
                body = body[1 + n :]
        elif marker == 0xC4:
            while body:
                n = 17 + sum(body[1:17])
                image.huffman[body[0]] = body[1:n]
                body = body[n:]
        elif marker == 0xC0:
            image.height, image.width = int.from_bytes(body[1:3], "big"), int.from_bytes(body[3:5], "big")
            image.components = [(body[6 + 3 * c], body[7 + 3 * c] >> 4, body[7 + 3 * c] & 15, body[8 + 3 * c]) for c in range(body[5])]
        elif 0xC1 <= marker <= 0xCF and marker != 0xC8 and marker != 0xCC:
            raise ValueError("not a baseline image")
        elif marker == 0xDD:
            image.restart = int.from_bytes(body[:2], "big")
        elif marker == 0xFE:
            image.comments.append(body)
        elif marker == 0xDA:
            image.tables = {body[1 + 2 * c]: (body[2 + 2 * c] >> 4, body[2 + 2 * c] & 15) for c in range(body[0])}
            end = data.rfind(b"\xff\xd9")
            image.scan = slice(i, end if end >= i else len(data))
            return image


def _lookup(table: bytes) -> np.ndarray:
    """For every 16 bits, length << 8 | symbol of the code they start with; 0: none."""
    out, code, at = np.zeros(1 << 16, dtype=np.int32), 0, 16
    for size in range(1, 17):
        for _ in range(table[size - 1]):
            out[code << (16 - size) : (code + 1) << (16 - size)] = size << 8 | table[at]
            code, at = code + 1, at + 1
        code <<= 1
    return out


def intervals(scan: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The scan's bytes without stuffing and restart markers, and where each interval starts."""
    mark = np.flatnonzero(scan[:-1] == 0xFF)
    after = scan[mark + 1]
    restart = mark[(after >= 0xD0) & (after <= 0xD7)]
    drop = np.sort(np.concatenate([restart, restart + 1, mark[after == 0] + 1]))
    left = np.ones(len(scan), dtype=bool)
    left[drop] = False
    return scan[left], np.concatenate([[0], restart - np.searchsorted(drop, restart)]).astype(np.int64)


def _whole_symbols(lookup: np.ndarray, ac: np.ndarray) -> np.ndarray:
    """For every 16 bits, the value and the length of a coefficient without zeros before it that they hold whole; else 0.

    ac: the places of AC tables, in which size 0 is no coefficient.
    """
    peek = np.arange(1 << 16, dtype=np.int64)
    out = []
    for i, table in enumerate(lookup.reshape(-1, 1 << 16).astype(np.int64)):
        length, size = table >> 8, table & 15
        bits = peek >> np.maximum(16 - length - size, 0) & ((1 << size) - 1)
        value = np.where(bits >> np.maximum(size - 1, 0) == 0, bits - (1 << size) + 1, bits)
        fits = (length > 0) & (length + size <= 16) & (table & 0xF0 == 0)
        if (i << 16) in ac:
            fits &= size > 0
        out.append(np.where(fits, np.where(size > 0, value, 0) << 8 | length + size, 0))
    return np.concatenate(out).astype(np.int32)


def decode_intervals(data: np.ndarray, start: np.ndarray, blocks: np.ndarray, lookup: np.ndarray, pattern: np.ndarray) -> np.ndarray:
    """Coefficients (interval, block, 64), differences still in place of DC values.

    blocks: how many blocks each interval has; lookup: all tables in one array; pattern: the places
    of the DC and the AC table of each block of an MCU.
    """
    padded = np.concatenate([data, np.zeros(16, np.uint8)])
    n = len(data) + 8
    most, per_mcu = int(blocks.max(initial=0)), len(pattern)
    lane, bit, k, stop = np.arange(len(start)), start * 8, np.zeros(len(start), np.int64), blocks * 64
    limit = len(data) * 8 + 64

    # While intervals are at the same coefficient, one lookup gives its value. Those that meet a run
    # of zeros, an end of block or a long code leave for the general loop below.
    narrow = (padded[:n].astype(np.int32) << 16) | (padded[1 : n + 1].astype(np.int32) << 8) | padded[2 : n + 2]
    symbols, left = _whole_symbols(lookup, pattern[:, 1]), []
    turned = np.zeros((most * 64, len(start)), dtype=np.int16)  # a row for each coefficient: lanes lie side by side
    for step in range(most * 64):
        if len(lane) < 64:
            break
        table = int(pattern[(step >> 6) % per_mcu, 0 if step & 63 == 0 else 1])
        entry = symbols[table + ((narrow[bit >> 3] >> (8 - (bit & 7))) & 0xFFFF)]
        done = step > 0 and step & 63 == 0 and int(stop[lane].min()) <= step
        if done or not entry.all():
            over = stop[lane] <= step
            gone = (entry == 0) & ~over
            left.append((lane[gone], bit[gone], np.full(int(gone.sum()), step)))
            stay = ~gone & ~over
            lane, bit, entry = lane[stay], bit[stay], entry[stay]
        if len(lane) == len(start):
            turned[step] = entry >> 8
        else:
            turned[step, lane] = entry >> 8
        bit = bit + (entry & 255)
    else:
        lane = lane[:0]
    out = np.ascontiguousarray(turned.T)
    k = np.concatenate([*(x[2] for x in left), np.full(len(lane), step if len(lane) else 0)]).astype(np.int64)
    bit = np.concatenate([*(x[1] for x in left), bit[: len(lane)]]).astype(np.int64)
    lane = np.concatenate([*(x[0] for x in left), lane]).astype(np.int64)
    out, stop = out.reshape(-1), stop[lane]
    lane, bit, k, stop = (x[k < stop] for x in (lane, bit, k, stop))
    window = np.zeros(n if len(lane) else 0, np.uint64)
    for i in range(8 if len(lane) else 0):
        window |= padded[i : i + n].astype(np.uint64) << np.uint64(56 - 8 * i)
    while len(lane):
        dc = (k & 63) == 0
        table = pattern[(k >> 6) % per_mcu, np.where(dc, 0, 1)]
        bits = window[bit >> 3] << (bit & 7).astype(np.uint64)
        entry = lookup[table + (bits >> np.uint64(48)).astype(np.int64)]
        length, size = entry >> 8, entry & 15
        if not length.all():
            raise ValueError("bits that start no code")
        run = np.where(dc, 0, entry >> 4 & 15)
        extra = (bits << length.astype(np.uint64)) >> np.uint64(1) >> (63 - size).astype(np.uint64)
        value = extra.astype(np.int64)
        value = np.where((value >> np.maximum(size - 1, 0)) == 0, value - (1 << size) + 1, value)
        put = dc | (size > 0)
        k = k + run
        if ((k >= stop) & put).any():
            raise ValueError("coefficients beyond a block")
        out[(lane * (most * 64) + k)[put]] = np.where(size > 0, value, 0)[put]
        k = np.where(put | (run == 15), k + 1, (k - run | 63) + 1)
        bit = bit + length + size
        if (bit > limit).any():
            raise ValueError("the scan ends too early")
        if (k >= stop).any():
            go = k < stop
            lane, bit, k, stop = lane[go], bit[go], k[go], stop[go]
    return out.reshape(len(start), most, 64)


def decode(files: list[bytes]) -> Iterator[tuple[Image, np.ndarray]]:
    """(image, coefficients by MCU and block) of each file; files with the same tables are decoded in step."""
    images = [parse(f) for f in files]
    keys = [(str(i.huffman), str(i.tables), str(i.components), i.restart) for i in images]
    lo = 0
    while lo < len(files):
        hi = lo
        while hi < len(files) and keys[hi] == keys[lo]:
            hi += 1
        first = images[lo]
        names = sorted(first.huffman)
        lookup = np.concatenate([_lookup(first.huffman[x]) for x in names])
        place = {x: i << 16 for i, x in enumerate(names)}
        alone = len(first.components) == 1
        pattern, owner = [], []
        for c, (name, h, v, _) in enumerate(first.components):
            dc, ac = first.tables[name]
            for _ in range(1 if alone else h * v):
                pattern.append((place[dc], place[0x10 | ac]))
                owner.append(c)
        mcus, parts, starts, blocks, base = [], [], [], [], 0
        for f, image in zip(files[lo:hi], images[lo:hi], strict=True):
            wide = 8 * (1 if alone else max(h for _, h, _, _ in image.components))
            high = 8 * (1 if alone else max(v for _, _, v, _ in image.components))
            mcus.append(-(-image.width // wide) * -(-image.height // high))
            data, start = intervals(np.frombuffer(f, np.uint8)[image.scan])
            each = image.restart or mcus[-1]
            if len(start) != -(-mcus[-1] // each):
                raise ValueError("restart intervals are missing")
            parts.append(data)
            starts.append(start + base)
            blocks.append(np.minimum(each, mcus[-1] - each * np.arange(len(start))) * len(pattern))
            base += len(data)
        found = decode_intervals(np.concatenate(parts), np.concatenate(starts), np.concatenate(blocks), lookup, np.array(pattern))
        found = found.reshape(len(found), -1, len(pattern), 64)
        for c in range(len(first.components)):  # DC values are differences within their interval
            at = [i for i, o in enumerate(owner) if o == c]
            dc = found[:, :, at, 0]
            found[:, :, at, 0] = np.cumsum(dc.reshape(len(found), -1), axis=1, dtype=np.int64).reshape(dc.shape)
        row = 0
        for image, m, s in zip(images[lo:hi], mcus, starts, strict=True):
            yield image, found[row : row + len(s)].reshape(-1, len(pattern), 64)[:m]
            row += len(s)
        lo = hi


def thumbnail(image: Image, coefficients: np.ndarray) -> np.ndarray:
    """One luminance sample per 8 x 8 block, from DC coefficients alone."""
    _, h, v, q = image.components[0]
    if len(image.components) == 1:
        h = v = 1
    most_h, most_v = (max(c[i] for c in image.components) if len(image.components) > 1 else 1 for i in (1, 2))
    cols, rows = -(-image.width // (8 * most_h)), -(-image.height // (8 * most_v))
    dc = coefficients[:, : h * v, 0].astype(np.int64) * int(image.quantisation[q][0])
    grid = dc.reshape(rows, cols, v, h).transpose(0, 2, 1, 3).reshape(rows * v, cols * h)
    grid = grid[: -(-image.height * v // (8 * most_v)), : -(-image.width * h // (8 * most_h))]
    return np.clip((grid + 4 >> 3) + 128, 0, 255).astype(np.uint8)


def average_hash(thumb: np.ndarray, side: int = 8) -> str:
    """64 bits: cells of an 8 x 8 reduction that are brighter than their mean."""
    sums = np.zeros((thumb.shape[0] + 1, thumb.shape[1] + 1), dtype=np.int64)
    sums[1:, 1:] = thumb.astype(np.int64).cumsum(0).cumsum(1)
    edge = [(np.arange(side) * n // side, np.maximum((np.arange(1, side + 1) * n + side - 1) // side, np.arange(side) * n // side + 1)) for n in thumb.shape]
    (a, b), (c, d) = edge
    total = sums[np.ix_(b, d)] - sums[np.ix_(a, d)] - sums[np.ix_(b, c)] + sums[np.ix_(a, c)]
    cells = total / ((b - a)[:, None] * (d - c)[None, :])
    return np.packbits((cells > cells.mean()).ravel()).tobytes().hex()


def media_columns(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Stores each text as a baseline JPEG, reads it back, and returns dimensions, thumbnail and digests.

    The payload is the text in UTF-8 with bytes 32 appended up to a positive multiple of 192; its size
    and that of the text stand in a comment segment. Null and empty texts are one MCU of blanks. Rows
    are independent: repeated rows give repeated results, a null id stays null, an empty table gives
    no rows. Other columns are ignored. A long text is one image, stored and decoded in parts.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, offsets = sh.utf8(batch.column(1))
            keys, lo = batch.column(0).to_pylist(), 0
            while lo < len(keys):
                hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + STEP_BYTES, side="right")) - 1)
                sizes = np.diff(offsets[lo : hi + 1]).tolist()
                files = encode_all(flat[offsets[lo] : offsets[hi]], sizes)
                rows = []
                for key, stored, (image, found) in zip(keys[lo:hi], files, decode(files), strict=True):
                    n_bytes, mcus = (int.from_bytes(image.comments[0][i : i + 8], "big") for i in (0, 8))
                    payload = (found[:mcus].reshape(-1) + 128).astype(np.uint8).tobytes()
                    thumb = thumbnail(image, found)
                    feature = f"{image.width}x{image.height}:{average_hash(thumb)}"
                    rows.append((key, n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(stored), hashlib.sha256(stored).hexdigest(), feature, image.width, image.height, thumb.tobytes()))
                names = [x.split()[0] for x in RESULT.split(", ")]
                types = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names)
                lo = hi

    return docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text_col}`").cast("string").alias("text")).mapInArrow(work, RESULT).withColumnRenamed("doc_id", id_col)
