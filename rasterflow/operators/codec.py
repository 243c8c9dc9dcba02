"""Codecs for grey rasters in NumPy: PNG rows, a block-DCT codec by block rows, and a pyramid stored coarse first.

Partial decoding: png.decode_until inflates only the rows asked for; dct.decode_roi reads only block rows (by their
index) and blocks that the region touches; pyramid.decode reads a prefix.  deblock=False leaves out the filter.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

PNG_MAGIC = b"\x89PNG\r\n\x1a\n"
#: The usual luminance quantiser, row by row.
QUANTISER = np.array(
    [16, 11, 10, 16, 24, 40, 51, 61, 12, 12, 14, 19, 26, 58, 60, 55, 14, 13, 16, 24, 40, 57, 69, 56, 14, 17, 22, 29, 51, 87, 80, 62,
     18, 22, 37, 56, 68, 109, 103, 77, 24, 35, 55, 64, 81, 104, 113, 92, 49, 64, 78, 87, 103, 121, 120, 101, 72, 92, 95, 98, 112, 100, 103, 99]
).reshape(8, 8)


def text_raster(payload: bytes, width: int = 32) -> np.ndarray:
    """All bytes in rows of `width`, the last filled with zeros."""
    h = max(1, -(-len(payload) // width))
    return np.frombuffer(payload.ljust(h * width, b"\0"), np.uint8).reshape(h, width)


# PNG -----------------------------------------------------------------------


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def png_encode(r: np.ndarray, level: int = 6) -> bytes:
    """8-bit grey PNG; every row stores its difference to the one above."""
    up = np.diff(r.astype(np.int16), axis=0, prepend=0).astype(np.uint8)
    rows = np.concatenate([np.full((len(r), 1), 2, np.uint8), up], 1).tobytes()
    return PNG_MAGIC + _chunk(b"IHDR", struct.pack(">IIBBBBB", r.shape[1], r.shape[0], 8, 0, 0, 0, 0)) + _chunk(b"IDAT", zlib.compress(rows, level)) + _chunk(b"IEND", b"")


def png_decode(blob: bytes, n_rows: int | None = None) -> np.ndarray:
    """The first n_rows rows (None: all); no more is inflated than they need."""
    if blob[:8] != PNG_MAGIC:
        raise ValueError("not a PNG")
    at, data, w, h = 8, [], 0, 0
    while at + 8 <= len(blob):
        size, kind = struct.unpack_from(">I4s", blob, at)
        body = blob[at + 8 : at + 8 + size]
        if kind == b"IHDR":
            w, h, depth, colour = struct.unpack_from(">IIBB", body)
            if depth != 8 or colour != 0:
                raise ValueError("only 8-bit grey is decoded")
        elif kind == b"IDAT":
            data.append(body)
        at += 12 + size
    rows = h if n_rows is None else min(h, n_rows)
    raw = zlib.decompressobj().decompress(b"".join(data), rows * (w + 1)) if rows else b""
    if len(raw) < rows * (w + 1):
        raise ValueError("a truncated PNG")
    grid = np.frombuffer(raw, np.uint8).reshape(rows, w + 1)
    if np.isin(grid[:, 0], (0, 2)).all():
        out = grid[:, 1:].astype(np.int64)
        keep = grid[:, 0] == 0
        if not keep.any():
            return np.cumsum(out, 0).astype(np.uint8)
        for i in range(1, rows):
            if not keep[i]:
                out[i] += out[i - 1]
        return out.astype(np.uint8)
    raise ValueError("a row filter that isn't decoded")


# Block DCT -----------------------------------------------------------------

_k = np.arange(8)
BASIS = np.cos((2 * _k[None, :] + 1) * _k[:, None] * np.pi / 16) * np.where(_k[:, None] == 0, np.sqrt(1 / 8), 0.5)


def quantiser(quality: int) -> np.ndarray:
    scale = 5000 / quality if quality < 50 else 200 - 2 * quality
    return np.clip(np.floor((QUANTISER * scale + 50) / 100), 1, 255)


def _blocks(r: np.ndarray) -> np.ndarray:
    h, w = r.shape
    r = np.pad(r, ((0, -h % 8), (0, -w % 8)), mode="edge")
    return r.reshape(r.shape[0] // 8, 8, r.shape[1] // 8, 8).transpose(0, 2, 1, 3)


def dct_encode(r: np.ndarray, quality: int = 75) -> tuple[bytes, list[int]]:
    """Payload and the offset of each block row in it (and its end)."""
    c = np.rint(BASIS @ (_blocks(r).astype(np.float64) - 128) @ BASIS.T / quantiser(quality)).astype("<i2")
    parts = [zlib.compress(row.tobytes(), 6) for row in c]
    head = struct.pack("<III", *r.shape, quality)
    index = np.cumsum([len(head), *map(len, parts)]).tolist()
    return head + b"".join(parts), index


def dct_decode(payload: bytes, index: list[int], roi: tuple[int, int, int, int] | None = None, deblock: bool = True) -> np.ndarray:
    """The raster, or its region (left, top, right, bottom) from the blocks that the region touches.

    The filter looks over block edges, so a region decodes one more block around it; decode-and-crop gives the same.
    """
    h, w, quality = struct.unpack_from("<III", payload)
    left, top, right, bottom = roi or (0, 0, w, h)
    left, top, right, bottom = max(0, left), max(0, top), min(w, right), min(h, bottom)
    if right <= left or bottom <= top:
        return np.empty((max(0, bottom - top), max(0, right - left)), np.uint8)
    around = int(deblock)
    rows, cols = -(-h // 8), -(-w // 8)
    y0, y1 = max(0, top // 8 - around), min(rows, -(-bottom // 8) + around)
    x0, x1 = max(0, left // 8 - around), min(cols, -(-right // 8) + around)
    c = np.stack([np.frombuffer(zlib.decompress(payload[index[y] : index[y + 1]]), "<i2").reshape(cols, 8, 8)[x0:x1] for y in range(y0, y1)])
    p = BASIS.T @ (c * quantiser(quality)) @ BASIS + 128
    out = p.transpose(0, 2, 1, 3).reshape((y1 - y0) * 8, (x1 - x0) * 8)
    out = np.clip(np.rint(out), 0, 255)
    if deblock:
        out = smoothed(smoothed(out).T).T
    return out.astype(np.uint8)[top - 8 * y0 : bottom - 8 * y0, left - 8 * x0 : right - 8 * x0]


def smoothed(p: np.ndarray, most: float = 24.0) -> np.ndarray:
    """Small steps between the rows on both sides of block edges are halved."""
    out = p.copy()
    a, b = p[7:-1:8], p[8::8]
    step = (b - a) / 4
    weak = np.abs(b - a) < most
    out[7:-1:8] = np.floor(np.where(weak, a + step, a) + 0.5)
    out[8::8] = np.floor(np.where(weak, b - step, b) + 0.5)
    return out


class Scanlines:
    """Decodes a block-DCT payload line by line: skips lines without inverse transforms, and only transforms the blocks of the columns kept.

    Lines of skipped block rows are never inflated, as each block row has its offset; nothing after the last line read is.
    """

    def __init__(self, payload: bytes, index: list[int], left: int = 0, right: int | None = None):
        self.payload, self.index, self.at = payload, index, 0
        self.height, self.width, self.quality = struct.unpack_from("<III", payload)
        self.left, self.right = max(0, left), min(self.width, self.width if right is None else right)
        self.inflated = 0  # block rows

    def skip(self, lines: int) -> None:
        self.at = min(self.height, self.at + max(0, lines))

    def read(self, lines: int) -> np.ndarray:
        end = min(self.height, self.at + max(0, lines))
        if end <= self.at or self.right <= self.left:
            self.at = max(self.at, end)
            return np.empty((0, max(0, self.right - self.left)), np.uint8)
        x0, x1, cols = self.left // 8, -(-self.right // 8), -(-self.width // 8)
        out = []
        for y in range(self.at // 8, -(-end // 8)):
            c = np.frombuffer(zlib.decompress(self.payload[self.index[y] : self.index[y + 1]]), "<i2").reshape(cols, 8, 8)[x0:x1]
            self.inflated += 1
            p = BASIS.T @ (c * quantiser(self.quality)) @ BASIS + 128
            band = np.clip(np.rint(p), 0, 255).astype(np.uint8).transpose(1, 0, 2).reshape(8, -1)
            out.append(band[max(0, self.at - 8 * y) : end - 8 * y, self.left - 8 * x0 : self.right - 8 * x0])
        self.at = end
        return np.concatenate(out)


def decode_rows(payload: bytes, index: list[int], top: int, bottom: int, left: int, right: int) -> np.ndarray:
    """A region by scanlines: skip to its top, cut its columns, stop after its bottom (no filter over block edges)."""
    lines = Scanlines(payload, index, left, right)
    lines.skip(top)
    return lines.read(bottom - lines.at)


# Pyramid -------------------------------------------------------------------


def half(r: np.ndarray) -> np.ndarray:
    """Means of 2 x 2 cells, halves up; an odd edge counts twice."""
    r = np.pad(r, ((0, r.shape[0] % 2), (0, r.shape[1] % 2)), mode="edge").astype(np.int64)
    return ((r[::2, ::2] + r[1::2, ::2] + r[::2, 1::2] + r[1::2, 1::2] + 2) // 4).astype(np.uint8)


def double(r: np.ndarray, h: int, w: int) -> np.ndarray:
    return np.repeat(np.repeat(r, 2, 0), 2, 1)[:h, :w]


def pyramid_encode(r: np.ndarray, levels: int = 3) -> tuple[bytes, list[int]]:
    """Payload (coarsest level, then differences, finer and finer) and the ends of its segments."""
    stack = [r]
    for _ in range(levels):
        stack.append(half(stack[-1]))
    parts = [zlib.compress(stack[-1].tobytes(), 6)]
    for fine, coarse in zip(stack[-2::-1], stack[:0:-1], strict=True):
        parts.append(zlib.compress((fine - double(coarse, *fine.shape)).tobytes(), 6))
    head = struct.pack("<III", *r.shape, levels)
    return head + b"".join(parts), np.cumsum([len(head), *map(len, parts)]).tolist()


def pyramid_decode(payload: bytes, index: list[int], level: int = 0) -> np.ndarray:
    """Level 0 is the raster, level L its 2**L reduction; only a prefix of the payload is read."""
    h, w, levels = struct.unpack_from("<III", payload)
    shapes = [(h, w)]
    for _ in range(levels):
        shapes.append(tuple(-(-s // 2) for s in shapes[-1]))
    r = np.frombuffer(zlib.decompress(payload[index[0] : index[1]]), np.uint8).reshape(shapes[-1])
    for i in range(levels - level):
        shape = shapes[levels - 1 - i]
        r = np.frombuffer(zlib.decompress(payload[index[i + 1] : index[i + 2]]), np.uint8).reshape(shape) + double(r, *shape)
    return r


def stages() -> list[tuple[str, bool]]:
    """Stages of the block codec's decoding, and which must stay on the host: entropy decoding can't be spread, the others can."""
    return [("entropy", True), ("inverse_transform", False), ("deblock", False)]


def psnr(a: np.ndarray, b: np.ndarray) -> float:
    e = float(((a.astype(float) - b) ** 2).mean())
    return float("inf") if e == 0 else 10 * np.log10(255**2 / e)


FORMATS = ("full", "half_png", "half_dct95", "half_dct75")
LOSSLESS = ("full", "half_png", "quarter_png")


def encode(format_id: str, r: np.ndarray) -> tuple[bytes, list[int]]:
    small = half(r) if format_id.startswith("half") else half(half(r)) if format_id.startswith("quarter") else r
    if format_id in LOSSLESS:
        return png_encode(small), []
    return dct_encode(small, int(format_id[-2:]))


def decode(format_id: str, payload: bytes, index: list[int], deblock: bool = True) -> np.ndarray:
    return png_decode(payload) if format_id in LOSSLESS else dct_decode(payload, index, deblock=deblock)
