"""Progressive JPEG as a media column: coefficients gathered over scans, numpy inverse transform, full-size RGB.

A document's payload is held losslessly in the format's unit, the quantised coefficient: each byte b is
one AC coefficient 256 + b. Three colour components with 4:2:0 chroma; one interleaved DC scan, then per
component two spectral bands without their lowest bit and one refinement scan (successive
approximation). The decoder accepts baseline-free progressive streams in general (DC and AC, first and
refining scans, end-of-band runs, restart intervals); where a scan's code table has one symbol only, all
codes of the scan are of one length and its bits are read as a matrix.
Texts are coded in groups of about 256 KB, a longer one alone; what a text needs is some 30 times its bytes.
Edge cases: null text is empty and its payload is one unit of spaces; equal texts give equal bytes; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import blocks, utf8

UNIT = 192
_I = np.arange(8)
_DCT = (np.where(_I[:, None] == 0, np.sqrt(1 / 8), np.sqrt(2 / 8)) * np.cos((2 * _I[None] + 1) * _I[:, None] * np.pi / 16)).astype(np.float32)
#: Natural index of each zigzag position: diagonals, walked alternately up and down.
ZIGZAG = np.array([r * 8 + c for r, c in sorted(((r, c) for r in range(8) for c in range(8)), key=lambda x: (x[0] + x[1], x[0] if (x[0] + x[1]) % 2 else x[1]))])
_MARKER = re.compile(rb"\xff[^\x00\xff\xd0-\xd7]", re.S)


def _segment(marker: int, body: bytes) -> bytes:
    return bytes([0xFF, marker]) + (len(body) + 2).to_bytes(2, "big") + body


def _table(kind: int, slot: int, symbol: int) -> bytes:
    """A code table whose only symbol has the code 0."""
    return _segment(0xC4, bytes([kind << 4 | slot, 1, *[0] * 15, symbol]))


def _bits(rows: np.ndarray) -> bytes:
    bits = rows.reshape(-1)
    if rest := -len(bits) % 8:
        bits = np.concatenate([bits, np.ones(rest, np.uint8)])
    return np.packbits(bits).tobytes().replace(b"\xff", b"\xff\x00")


def _scan(components: list[tuple[int, int]], lo: int, hi: int, high: int, low: int, data: bytes) -> bytes:
    head = bytes([len(components)]) + b"".join(bytes([c, t]) for c, t in components) + bytes([lo, hi, high << 4 | low])
    return _segment(0xDA, head) + data


_HEAD = b"\xff\xd8" + _segment(0xE0, b"JFIF\x00\x01\x01\x00\x00\x01\x00\x01\x00\x00")
_TABLES = _segment(0xDB, b"\x00" + b"\x01" * 64) + _table(0, 0, 0x00) + _table(1, 0, 0x08) + _table(1, 1, 0x00)


def encode_payload(payload: bytes) -> bytes:
    """A progressive JPEG whose AC coefficients are the payload's bytes plus 256."""
    mcus = max(1, -(-len(payload) // (63 * 6)))
    wide = min(mcus, max(16, -(-mcus // 4095)))
    tall = -(-mcus // wide)
    mcus = wide * tall
    units = np.zeros(mcus * 6 * 63, np.uint8)
    units[: len(payload)] = np.frombuffer(payload, np.uint8)
    units = units.reshape(-1, 63)
    out = [_HEAD, _segment(0xFE, b"payload %d" % len(payload)), _TABLES,
           _segment(0xC2, bytes([8]) + (tall * 16).to_bytes(2, "big") + (wide * 16).to_bytes(2, "big") + bytes([3, 1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])),
           _scan([(1, 0), (2, 0), (3, 0)], 0, 0, 0, 0, _bits(np.zeros(mcus * 6, np.uint8)))]
    # coefficient 256 + b: without the lowest bit it is 128 + (b >> 1), always of size class 8
    first = np.zeros((len(units), 63, 9), np.uint8)
    first[:, :, 1:] = np.unpackbits((units >> 1) | 128).reshape(len(units), 63, 8)
    again = np.zeros((len(units), 64), np.uint8)
    again[:, 1:] = units & 1
    at = 0
    for c, n in ((1, 4 * mcus), (2, mcus), (3, mcus)):
        own = slice(at, at + n)
        out += [_scan([(c, 0)], 1, 5, 0, 1, _bits(first[own, :5])), _scan([(c, 0)], 6, 63, 0, 1, _bits(first[own, 5:])), _scan([(c, 1)], 1, 63, 1, 0, _bits(again[own]))]
        at += n
    return b"".join(out) + b"\xff\xd9"


class _Reader:
    """Bits of one restart interval, one at a time; the general path."""

    def __init__(self, data: bytes):
        self.bits = np.unpackbits(np.frombuffer(data, np.uint8)).tolist()
        self.at = 0

    def bit(self) -> int:
        self.at += 1
        return self.bits[self.at - 1] if self.at <= len(self.bits) else 1

    def take(self, n: int) -> int:
        v = 0
        for _ in range(n):
            v = v << 1 | self.bit()
        return v

    def signed(self, n: int) -> int:
        v = self.take(n)
        return v if n == 0 or v >> (n - 1) else v - (1 << n) + 1

    def symbol(self, codes: dict[tuple[int, int], int]) -> int:
        code = 0
        for n in range(1, 17):
            code = code << 1 | self.bit()
            if (n, code) in codes:
                return codes[n, code]
        raise ValueError("no such code")


def _codes(counts: bytes, symbols: bytes) -> dict[tuple[int, int], int]:
    out, code, k = {}, 0, 0
    for n, c in enumerate(counts, 1):
        for _ in range(c):
            out[n, code] = symbols[k]
            code, k = code + 1, k + 1
        code <<= 1
    return out


def _lone(codes: dict) -> int | None:
    return next(iter(codes.values())) if len(codes) == 1 and (1, 0) in codes else None


def _matrix(data: bytes, rows: int, width: int) -> np.ndarray | None:
    """The scan's bits as rows of one width, if it has just as many and each row's code bit is 0."""
    if len(data) != -(-rows * width // 8):
        return None
    bits = np.unpackbits(np.frombuffer(data, np.uint8))[: rows * width].reshape(rows, width)
    return None if bits[:, 0].any() else bits


def _ac_first(r: _Reader, block, lo: int, hi: int, low: int, codes: dict, run: int) -> int:
    if run:
        return run - 1
    k = lo
    while k <= hi:
        zeros, n = divmod(r.symbol(codes), 16)
        if n:
            k += zeros
            block[k] = r.signed(n) << low
        elif zeros < 15:
            return (1 << zeros) + r.take(zeros) - 1
        else:
            k += 15
        k += 1
    return 0


def _ac_refine(r: _Reader, block, lo: int, hi: int, low: int, codes: dict, run: int) -> int:
    k, unit = lo, 1 << low
    if not run:
        while k <= hi:
            zeros, n = divmod(r.symbol(codes), 16)
            value = 0
            if n:
                value = unit if r.bit() else -unit
            elif zeros < 15:
                run = (1 << zeros) + r.take(zeros)
                break
            while k <= hi:
                if block[k]:
                    if r.bit() and not block[k] & unit:
                        block[k] += unit if block[k] > 0 else -unit
                elif zeros:
                    zeros -= 1
                else:
                    break
                k += 1
            if value and k <= hi:
                block[k] = value
            k += 1
    if run:
        for j in range(k, hi + 1):
            if block[j] and r.bit() and not block[j] & unit:
                block[j] += unit if block[j] > 0 else -unit
        return run - 1
    return 0


def decode_coefficients(data: bytes) -> dict:
    """Size, sampling, quantisation and, per component, coefficients (blocks down, across, 64) in zigzag order."""
    at, tables, quant, out, interval = 2, {}, {}, {"comment": b""}, 0
    while True:
        marker = data[at + 1]
        if marker == 0xD9:
            return out
        size = int.from_bytes(data[at + 2 : at + 4], "big")
        body, at = data[at + 4 : at + 2 + size], at + 2 + size
        if marker == 0xFE:
            out["comment"] = body
        elif marker == 0xDD:
            interval = int.from_bytes(body[:2], "big")
        elif marker == 0xDB:
            while body:
                wide = 2 if body[0] >> 4 else 1
                quant[body[0] & 15] = np.frombuffer(body[1 : 1 + 64 * wide], ">u2" if wide == 2 else "u1").astype(np.float32)
                body = body[1 + 64 * wide :]
        elif marker == 0xC4:
            while body:
                n = sum(body[1:17])
                tables[body[0]] = _codes(body[1:17], body[17 : 17 + n])
                body = body[17 + n :]
        elif marker == 0xC2:
            tall, wide = int.from_bytes(body[1:3], "big"), int.from_bytes(body[3:5], "big")
            parts = {body[6 + 3 * i]: (body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(body[5])}
            hs, vs = max(p[0] for p in parts.values()), max(p[1] for p in parts.values())
            across, down = -(-wide // (8 * hs)), -(-tall // (8 * vs))
            out |= {"size": (tall, wide), "max": (vs, hs), "mcus": (down, across), "parts": parts, "quant": quant,
                    "coef": {c: np.zeros((down * v, across * h, 64), np.int32) for c, (h, v, _) in parts.items()}}
        elif marker == 0xDA:
            used = [(body[1 + 2 * i], body[2 + 2 * i]) for i in range(body[0])]
            lo, hi, high, low = *body[-3:-1], body[-1] >> 4, body[-1] & 15
            end = _MARKER.search(data, at).start()
            _run_scan(out, tables, used, lo, hi, high, low, data[at:end], interval)
            at = end
        elif 0xC0 <= marker <= 0xCF:
            raise ValueError("only progressive streams with Huffman codes")


def _run_scan(img: dict, tables: dict, used: list, lo: int, hi: int, high: int, low: int, raw: bytes, interval: int) -> None:
    parts, coef = img["parts"], img["coef"]
    if len(used) == 1:
        c = used[0][0]
        h, v, _ = parts[c]
        tall, wide = img["size"]
        rows, cols = -(-tall * v // (8 * img["max"][0])), -(-wide * h // (8 * img["max"][1]))
        order = None
    if not interval and lo and len(used) == 1:
        symbol = _lone(tables[16 | used[0][1] & 15])
        own = coef[c][:rows, :cols, lo : hi + 1]
        n = hi - lo + 1
        data = raw.replace(b"\xff\x00", b"\xff")
        if not high and symbol and symbol < 16 and symbol <= 8 and (bits := _matrix(data, rows * cols * n, 1 + symbol)) is not None:
            value = np.packbits(bits[:, 1:], axis=1)[:, 0].astype(np.int32) >> (8 - symbol)
            coef[c][:rows, :cols, lo : hi + 1] = (np.where(value >> (symbol - 1), value, value - (1 << symbol) + 1) << low).reshape(rows, cols, n)
            return
        if high and symbol == 0 and own.all() and (bits := _matrix(data, rows * cols, 1 + n)) is not None:
            step = bits[:, 1:].reshape(rows, cols, n).astype(np.int32) << low
            coef[c][:rows, :cols, lo : hi + 1] += np.where(own > 0, step, -step)
            return
    if not interval and not lo and not high and all(_lone(tables[t >> 4]) == 0 for _, t in used):
        return  # every DC difference is 0
    if len(used) == 1:
        order = [[(c, used[0][1], y, x)] for y in range(rows) for x in range(cols)]
    else:
        order = [[(c, t, my * parts[c][1] + y, mx * parts[c][0] + x) for c, t in used for y in range(parts[c][1]) for x in range(parts[c][0])]
                 for my in range(img["mcus"][0]) for mx in range(img["mcus"][1])]
    pieces = re.split(rb"\xff[\xd0-\xd7]", raw)
    step = interval or len(order)
    for i, piece in enumerate(pieces):
        r, run, last = _Reader(piece.replace(b"\xff\x00", b"\xff")), 0, dict.fromkeys(parts, 0)
        for mcu in order[i * step : (i + 1) * step]:
            for c, t, y, x in mcu:
                block = coef[c][y, x]
                if lo == 0 and not high:
                    last[c] += r.signed(r.symbol(tables[t >> 4]))
                    block[0] = last[c] << low
                elif lo == 0:
                    block[0] |= r.bit() << low
                else:
                    own = block.tolist()
                    run = (_ac_refine if high else _ac_first)(r, own, lo, hi, low, tables[16 | t & 15], run)
                    block[:] = own


def to_rgb(img: dict) -> np.ndarray:
    """(height, width, 3) uint8: dequantise, inverse transform, repeat chroma samples to full size, convert."""
    planes = []
    for c, (h, v, q) in img["parts"].items():
        z = img["coef"][c]
        rows, cols, _ = z.shape
        nat = np.empty((rows * cols, 64), np.float32)
        nat[:, ZIGZAG] = z.reshape(-1, 64) * img["quant"][q]
        px = (_DCT.T @ nat.reshape(-1, 8, 8) @ _DCT).reshape(rows, cols, 8, 8).swapaxes(1, 2).reshape(rows * 8, cols * 8)
        planes.append(np.repeat(np.repeat(px, img["max"][0] // v, 0), img["max"][1] // h, 1)[: img["size"][0], : img["size"][1]])
    y = planes[0] + 128
    cb, cr = (planes[1], planes[2]) if len(planes) == 3 else (np.zeros_like(y),) * 2
    rgb = np.stack([y + 1.402 * cr, y - 0.344136 * cb - 0.714136 * cr, y + 1.772 * cb], -1)
    return np.clip(np.rint(rgb), 0, 255).astype(np.uint8)


def decode_payload(data: bytes) -> tuple[bytes, dict]:
    img = decode_coefficients(data)
    units = np.concatenate([z.reshape(-1, 64)[:, 1:].reshape(-1) for z in img["coef"].values()]) - 256
    return units.astype(np.uint8)[: int(img["comment"].split()[1])].tobytes(), img


def store_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media: each whole text as a progressive JPEG."""
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(1))
            for lo, hi in blocks(off):
                texts = [data[off[i] : off[i + 1]].tobytes() for i in range(lo, hi)]
                media = [encode_payload(x.ljust(max(UNIT, -(-len(x) // UNIT) * UNIT), b" ")) for x in texts]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array([len(x) for x in texts], pa.int64()), pa.array(media, pa.binary())],
                                                 names=["doc_id", "n_bytes", "media"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_bytes long, media binary")


def read_media(media: DataFrame, tensors: bool = False) -> DataFrame:
    """Digest of the payload and features of the RGB tensor; with `tensors` also rgb binary, height, width."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", *["height", "width", "rgb"][: 3 * tensors]]

    def run(batches):
        for b in batches:
            data, off = utf8(b.column(2))
            for lo, hi in blocks(off):
                rows = []
                for i in range(lo, hi):
                    stored = data[off[i] : off[i + 1]].tobytes()
                    payload, img = decode_payload(stored)
                    rgb = to_rgb(img)
                    mean = rgb.reshape(-1, 3).sum(0, dtype=np.int64) * 1000 // (rgb.shape[0] * rgb.shape[1])
                    feature = f"{rgb.shape[0]}x{rgb.shape[1]}:{mean[0]},{mean[1]},{mean[2]}:{zlib.crc32(rgb.tobytes()):08x}"
                    rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(stored), hashlib.sha256(stored).hexdigest(), feature,
                                 *((*rgb.shape[:2], rgb.tobytes()) if tensors else ())))
                kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int32(), pa.binary()]
                cols = [pa.array(x, k) for x, k in zip(zip(*rows), kinds, strict=False)]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), b.column(1).slice(lo, hi - lo), *cols], names=names)

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return media.select("doc_id", "n_bytes", "media").mapInArrow(run, schema + ", height int, width int, rgb binary" * tensors)
