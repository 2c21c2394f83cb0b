"""Stored images against a decoder of one bit at a time, written from the format's public description."""

import hashlib
import zlib

import numpy as np

from optjoin.llm import jpeg


def plain_decode(data):
    """(width, height, comments, blocks of each component in zigzag order, quantisation of the first component)."""
    assert data[:2] == b"\xff\xd8"
    at, tables, quants, comments, restart = 2, {}, {}, [], 0
    while True:
        assert data[at] == 0xFF
        marker, size = data[at + 1], int.from_bytes(data[at + 2 : at + 4], "big")
        body = data[at + 4 : at + 2 + size]
        at += 2 + size
        if marker == 0xDB:
            while body:
                assert body[0] >> 4 == 0  # 8-bit entries
                quants[body[0] & 15], body = list(body[1:65]), body[65:]
        elif marker == 0xC4:
            while body:
                counts, code, i, found = body[1:17], 0, 17, {}
                for length, count in enumerate(counts, 1):
                    for _ in range(count):
                        found[length, code] = body[i]
                        code, i = code + 1, i + 1
                    code <<= 1
                tables[body[0]], body = found, body[i:]
        elif marker == 0xC0:
            assert body[0] == 8
            height, width = int.from_bytes(body[1:3], "big"), int.from_bytes(body[3:5], "big")
            shape = {body[6 + 3 * i]: (body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(body[5])}
        elif marker == 0xDD:
            restart = int.from_bytes(body, "big")
        elif marker == 0xFE:
            comments.append(body)
        elif marker == 0xDA:
            use = {body[1 + 2 * i]: (body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15) for i in range(body[0])}
            break
    pieces, held = [], bytearray()
    while True:
        byte, after = data[at], data[at + 1]
        if byte != 0xFF:
            held.append(byte)
            at += 1
            continue
        at += 2
        if after == 0:
            held.append(0xFF)
            continue
        pieces.append(bytes(held))
        held.clear()
        if after == 0xD9:
            break
        assert after == 0xD0 + (len(pieces) - 1) % 8
    assert at == len(data)
    one = len(shape) == 1
    most = [8 * (1 if one else max(s[i] for s in shape.values())) for i in (0, 1)]
    left = -(-width // most[0]) * -(-height // most[1])
    out = {c: [] for c in shape}
    for piece in pieces:
        bits, place = "".join(f"{b:08b}" for b in piece), 0

        def symbol(table):
            nonlocal place
            code = 0
            for length in range(1, 17):
                code = 2 * code + int(bits[place])
                place += 1
                if (length, code) in table:
                    return table[length, code]
            raise AssertionError("no code")

        def value(size):
            nonlocal place
            text, place = bits[place : place + size], place + size
            return 0 if not size else int(text, 2) if text[0] == "1" else int(text, 2) - (1 << size) + 1

        before = dict.fromkeys(shape, 0)
        for _ in range(min(restart or left, left)):
            left -= 1
            for c, (h, v, _) in shape.items():
                for _ in range(1 if one else h * v):
                    block, k = [0] * 64, 1
                    before[c] += value(symbol(tables[use[c][0]]))
                    block[0] = before[c]
                    while k < 64:
                        code = symbol(tables[0x10 | use[c][1]])
                        if code == 0:
                            break
                        k += code >> 4
                        if code & 15:
                            block[k] = value(code & 15)
                        k += 1
                    out[c].append(block)
        assert set(bits[place:]) <= {"1"} and len(bits) - place < 8
    assert left == 0
    first = next(iter(shape))
    return width, height, comments, list(out.values()), quants[shape[first][2]]


def texts():
    draw = np.random.default_rng(3)
    return [b"", b"a", b"\x80" * 500, draw.integers(0, 256, 3000, dtype=np.uint8).tobytes(), b"\xff\x00" * 200, "Ünï 中文 😀 ".encode() * 90, b"x" * 191, b"x" * 192, b"x" * 193]


def test_stored_bytes_by_a_plain_decoder():
    files = jpeg.encode_all(np.frombuffer(b"".join(texts()), np.uint8), [len(t) for t in texts()])
    for text, file, (image, found) in zip(texts(), files, jpeg.decode(files), strict=True):
        width, height, comments, blocks, quant = plain_decode(file)
        n, mcus = int.from_bytes(comments[0][:8], "big"), int.from_bytes(comments[0][8:16], "big")
        by_mcu = np.array(blocks).transpose(1, 0, 2)
        padded = text.ljust(max(192, -(-len(text) // 192) * 192))
        assert n == len(text) and bytes((by_mcu[:mcus].ravel() + 128).tolist()) == padded
        assert (width, height) == (image.width, image.height) and np.array_equal(by_mcu, found)
        dc = np.array(blocks[0])[:, 0].reshape(-(-height // 8), -(-width // 8)) * quant[0]
        thumb = jpeg.thumbnail(image, found)
        assert np.array_equal(thumb, np.clip(np.floor(dc / 8 + 0.5) + 128, 0, 255))
        rows, cols = thumb.shape
        span = lambda i, k: range(i * k // 8, max(-(-(i + 1) * k // 8), i * k // 8 + 1))
        cells = [[np.mean([int(thumb[y, x]) for y in span(i, rows) for x in span(j, cols)]) for j in range(8)] for i in range(8)]
        bits = "".join("1" if c > np.mean(cells) else "0" for row in cells for c in row)
        assert jpeg.average_hash(thumb) == f"{int(bits, 2):016x}"


def test_columns_by_a_plain_decoder(spark):
    rows = [(i, t.decode("utf-8", "replace")) for i, t in enumerate(texts())] + [(90, None), (None, "null id"), (1, "a")]
    got = jpeg.media_columns(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows)
    for r in got:
        (text,) = {(t or "") for d, t in rows if d == r.doc_id}
        raw = text.encode()
        padded = raw.ljust(max(192, -(-len(raw) // 192) * 192))
        (file,) = jpeg.encode_all(np.frombuffer(raw, np.uint8), [len(raw)])
        width, height, *_ = plain_decode(file)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest())
        assert (r.tail_crc32, r.media_bytes, r.media_sha256) == (zlib.crc32(padded[-16:]), len(file), hashlib.sha256(file).hexdigest())
        assert r.feature.startswith(f"{width}x{height}:")
