"""A decoder of baseline and lossless JPEG frames, for motion JPEG of any writer.

Baseline (process 1): any Huffman and quantisation tables, grey or three components at any
sampling, restart intervals; frames without Huffman tables use the standard's own, as
motion JPEG may leave them out. Lossless (process 14): one component, any table, the seven
predictors. The coefficients are read symbol by symbol; the inverse cosine transform,
scaling and colours are matrix products over all blocks of a frame.

What it gives: the frame's grey values, or the luma of frames in colour (``luma``), or all
components (``decode``). Broken frames, other processes and 12-bit samples raise ValueError.
"""

from __future__ import annotations

import struct

import numpy as np

# Fixed values of the JPEG standard (ITU T.81): the zigzag order follows a rule; the typical
# Huffman tables of annex K are counts of codes by length, then their symbols.


def _zigzag() -> np.ndarray:
    cells = sorted(((r, c) for r in range(8) for c in range(8)), key=lambda x: (sum(x), x[0] if sum(x) % 2 else x[1]))
    return np.array([8 * r + c for r, c in cells])


ZIGZAG = _zigzag()
_PLACES = ZIGZAG.tolist()
DC_LUMA = bytes([0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0, *range(12)])
DC_CHROMA = bytes([0, 3, 1, 1, 1, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, *range(12)])
AC_LUMA = bytes.fromhex(
    "0002010303020403050504040000017d"
    "01020300041105122131410613516107227114328191a1082342b1c11552d1f02433627282090a161718191a25262728292a3435363738393a43444546474849"
    "4a535455565758595a636465666768696a737475767778797a838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aab2b3b4b5b6b7b8b9bac2c3c4c5"
    "c6c7c8c9cad2d3d4d5d6d7d8d9dae1e2e3e4e5e6e7e8e9eaf1f2f3f4f5f6f7f8f9fa"
)
AC_CHROMA = bytes.fromhex(
    "00020102040403040705040400010277"
    "000102031104052131061241510761711322328108144291a1b1c109233352f0156272d10a162434e125f11718191a262728292a35363738393a434445464748"
    "494a535455565758595a636465666768696a737475767778797a82838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aab2b3b4b5b6b7b8b9bac2c3"
    "c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae2e3e4e5e6e7e8e9eaf2f3f4f5f6f7f8f9fa"
)


def lookup(table: bytes) -> list[int]:
    """For each 16 bits that may follow: 256 * length of the code they begin with + its symbol (0: none)."""
    counts, symbols = table[:16], table[16:]
    out = np.zeros(1 << 16, np.int32)
    code, at = 0, 0
    for length, n in enumerate(counts, 1):
        for _ in range(n):
            if code >= 1 << length or at >= len(symbols):
                raise ValueError("not a Huffman table")
            low = code << (16 - length)
            out[low : low + (1 << (16 - length))] = length << 8 | symbols[at]
            code, at = code + 1, at + 1
        code <<= 1
    return out.tolist()


def _standard() -> dict[tuple[int, int], list[int]]:
    return {(0, 0): lookup(DC_LUMA), (0, 1): lookup(DC_CHROMA), (1, 0): lookup(AC_LUMA), (1, 1): lookup(AC_CHROMA)}


class Bits:
    """The bits of one restart interval; reading past its end gives ones."""

    def __init__(self, data: bytes):
        self.data, self.at, self.held, self.n = data, 0, 0, 0

    def peek(self) -> int:
        """The next 16 bits."""
        while self.n < 16:
            part = self.data[self.at : self.at + 6]
            self.at += 6
            if len(part) < 6:
                part += b"\xff" * (6 - len(part))
                if self.at > len(self.data) + 4096:
                    raise ValueError("the frame's data end early")
            self.held = (self.held & ((1 << self.n) - 1)) << 48 | int.from_bytes(part, "big")
            self.n += 48
        return self.held >> (self.n - 16) & 0xFFFF

    def symbol(self, table: list[int]) -> int:
        x = table[self.peek()]
        if not x:
            raise ValueError("no such code")
        self.n -= x >> 8
        return x & 255

    def signed(self, size: int) -> int:
        """The number that ``size`` extra bits say."""
        if not size:
            return 0
        if size == 16:  # lossless only: no extra bits
            return 32768
        x = self.peek() >> (16 - size)
        self.n -= size
        return x if x >> (size - 1) else x - (1 << size) + 1


def segments(data: bytes):
    """(marker, body) of a frame, and for a scan (0xDA, header, its restart intervals without stuffing)."""
    if data[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG frame")
    at = 2
    while at + 4 <= len(data):
        if data[at] != 0xFF:
            raise ValueError("a marker is missing")
        marker = data[at + 1]
        if marker == 0xFF:
            at += 1
            continue
        if marker == 0xD9:
            return
        size = struct.unpack(">H", data[at + 2 : at + 4])[0]
        body = data[at + 4 : at + 2 + size]
        if size < 2 or len(body) != size - 2:
            raise ValueError("a segment is cut off")
        at += 2 + size
        if marker != 0xDA:
            yield marker, body, None
            continue
        intervals, begin, look = [], at, at
        while True:
            k = data.find(b"\xff", look)
            if k < 0 or k + 1 >= len(data):
                k, after = len(data), None
                break
            after = data[k + 1]
            if after == 0:
                look = k + 2
            elif 0xD0 <= after <= 0xD7:
                intervals.append(data[begin:k])
                begin = look = k + 2
            elif after == 0xFF:
                look = k + 1
            else:
                break
        intervals.append(data[begin:k])
        at = k
        yield 0xDA, body, [x.replace(b"\xff\x00", b"\xff") for x in intervals]


def _cosines() -> np.ndarray:
    k = np.arange(8)
    m = np.cos((2 * k[:, None] + 1) * k[None, :] * np.pi / 16) / 2
    m[:, 0] /= np.sqrt(2)
    return m


_COSINES = _cosines()


def decode(data: bytes) -> list[np.ndarray]:
    """The components of a frame, each scaled to the frame's size, as 8-bit samples."""
    try:
        return _decode(data)
    except (KeyError, IndexError, struct.error) as e:
        raise ValueError("a table is missing or data are cut off") from e


def _decode(data: bytes) -> list[np.ndarray]:
    quant: dict[int, np.ndarray] = {}
    huffman: dict[tuple[int, int], list[int]] = {}
    frame, every, planes = None, 0, {}
    for marker, body, intervals in segments(data):
        if marker == 0xDB:
            while body:
                wide, name = body[0] >> 4, body[0] & 15
                n = 128 if wide else 64
                if len(body) < n + 1:
                    raise ValueError("a table is cut off")
                values = np.zeros(64)
                values[ZIGZAG] = np.frombuffer(body[1 : n + 1], ">u2" if wide else np.uint8)
                quant[name] = values.reshape(8, 8)
                body = body[n + 1 :]
        elif marker == 0xC4:
            while body:
                n = 17 + sum(body[1:17])
                huffman[body[0] >> 4, body[0] & 15] = lookup(body[1:n])
                body = body[n:]
        elif marker == 0xDD:
            every = struct.unpack(">H", body[:2])[0]
        elif marker in (0xC0, 0xC1, 0xC3):
            precision, rows, columns, n = struct.unpack(">BHHB", body[:6])
            if precision != 8 or not rows or not columns or n not in (1, 3) or len(body) < 6 + 3 * n:
                raise ValueError("not a frame of 8-bit samples in one or three components")
            parts = [(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k]) for k in range(n)]
            if any(not (1 <= h <= 4 and 1 <= v <= 4) for _, h, v, _ in parts):
                raise ValueError("no such sampling")
            frame = (marker, rows, columns, parts)
        elif 0xC0 <= marker <= 0xCF and marker != 0xCC:
            raise ValueError("only baseline and lossless frames are decoded")
        elif marker == 0xDA:
            if frame is None:
                raise ValueError("a scan without a frame")
            n = body[0]
            chosen = [(body[1 + 2 * k], body[2 + 2 * k] >> 4, body[2 + 2 * k] & 15) for k in range(n)]
            tables = {**_standard(), **huffman} if len(huffman) < 2 and frame[0] != 0xC3 else huffman
            if frame[0] == 0xC3:
                planes[chosen[0][0]] = _lossless(frame, chosen, tables, intervals, every, body[1 + 2 * n], body[3 + 2 * n] & 15)
            else:
                planes |= _baseline(frame, chosen, tables, quant, intervals, every)
    if frame is None or len(planes) != len(frame[3]):
        raise ValueError("no picture")
    _, rows, columns, parts = frame
    high, wide = max(v for _, _, v, _ in parts), max(h for _, h, _, _ in parts)
    return [np.repeat(np.repeat(planes[c], high // v, axis=0), wide // h, axis=1)[:rows, :columns] for c, h, v, _ in parts]


def luma(data: bytes) -> np.ndarray:
    return decode(data)[0]


def _baseline(frame, chosen, tables, quant, intervals, every) -> dict[int, np.ndarray]:
    _, rows, columns, parts = frame
    high, wide = max(v for _, _, v, _ in parts), max(h for _, h, _, _ in parts)
    by_name = {c: (h, v, q) for c, h, v, q in parts}
    across, down = -(-columns // (8 * wide)), -(-rows // (8 * high))
    alone = len(chosen) == 1
    coefficients, plan = {}, []
    for c, dc, ac in chosen:
        h, v, _ = by_name[c]
        store = np.zeros((down * v, across * h, 64), np.float64)
        coefficients[c] = store
        plan.append((c, store, tables[0, dc], tables[1, ac], 1 if alone else h, 1 if alone else v))
    if alone:  # a scan of one component has its blocks in rows, without padding to whole units
        h, v, _ = by_name[chosen[0][0]]
        across, down = -(-(-(-columns * h // wide)) // 8), -(-(-(-rows * v // high)) // 8)
    total = across * down
    per = every or total
    for k, first in enumerate(range(0, total, per)):
        if k >= len(intervals):
            raise ValueError("an interval is missing")
        bits, last = Bits(intervals[k]), dict.fromkeys(coefficients, 0)
        for unit in range(first, min(first + per, total)):
            y, x = divmod(unit, across)
            for c, store, dc, ac, h, v in plan:
                for block in range(h * v):
                    cell = store[y * v + block // h, x * h + block % h]
                    last[c] += bits.signed(bits.symbol(dc))
                    cell[0] = last[c]
                    at = 1
                    while at < 64:
                        rs = bits.symbol(ac)
                        size = rs & 15
                        if size:
                            at += rs >> 4
                            cell[_PLACES[at]] = bits.signed(size)
                            at += 1
                        elif rs == 0xF0:
                            at += 16
                        else:
                            break
    out = {}
    for c, store in coefficients.items():
        block = store.reshape(*store.shape[:2], 8, 8) * quant[by_name[c][2]]
        samples = _COSINES @ block @ _COSINES.T + 128
        out[c] = np.clip(np.rint(samples), 0, 255).astype(np.uint8).transpose(0, 2, 1, 3).reshape(store.shape[0] * 8, store.shape[1] * 8)
    return out


def _lossless(frame, chosen, tables, intervals, every, predictor, shift) -> np.ndarray:
    _, rows, columns, parts = frame
    if len(chosen) != 1 or len(parts) != 1 or shift or not 1 <= predictor <= 7:
        raise ValueError("lossless frames have one component and a predictor")
    table = tables[0, chosen[0][1]]
    per = every // columns if every else rows
    if not per or (every and every % columns):
        raise ValueError("intervals are whole lines")
    d = np.zeros((rows, columns), np.int64)
    for k, first in enumerate(range(0, rows, per)):
        if k >= len(intervals):
            raise ValueError("an interval is missing")
        bits = Bits(intervals[k])
        for y in range(first, min(first + per, rows)):
            d[y] = [bits.signed(bits.symbol(table)) for _ in range(columns)]
    out = np.zeros((rows, columns), np.int64)
    for y in range(rows):
        if y % per == 0:
            out[y] = np.cumsum(d[y]) + 128
            continue
        up = out[y - 1]
        if predictor == 1:
            out[y] = np.cumsum(d[y]) + up[0]
        elif predictor == 2:
            out[y] = up + d[y]
        else:
            left = int(up[0] + d[y, 0])
            out[y, 0] = left
            for x in range(1, columns):
                b, c = int(up[x]), int(up[x - 1])
                guess = (None, None, None, c, left + b - c, left + ((b - c) >> 1), b + ((left - c) >> 1), (left + b) >> 1)[predictor]
                left = (guess + int(d[y, x])) & 0xFFFF
                out[y, x] = left
    return (out & 0xFFFF).astype(np.uint8)
