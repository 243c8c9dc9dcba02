"""Motion-JPEG in AVI: storing bytes, reading RIFF indexes, decoding intra frames and cutting shots.

A frame is a baseline JPEG.  Stored payloads use frames of 24 x 24 grey blocks: each block of 8 x 8 pixels has one
value, kept exactly by its DC coefficient at a quantiser step of 8, so 576 payload bytes are a frame that any JPEG
decoder reads back without loss.  The decoder takes any baseline frame with Huffman tables (AC coefficients, several
components); frames with equal headers advance together, one symbol of each at a step.

Shots: the total variation between the grey histograms of neighbouring frames is compared with a threshold that
adapts to the differences before it (mean and deviation of a window without the cuts in it, above a floor; the first
difference is compared with the floor alone).

Null text: empty; an empty text is one frame of padding; equal texts give equal media.  Null media give no clips;
damaged media give one row with an error.  Repeated rows are stored one by one; an empty table gives no rows; other
columns are ignored.
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

from .common import raw_texts, settled, slices

FRAME = 576
SIDE = 24
FPS = 25
BINS = 16
WINDOW, DEVIATIONS, FLOOR = 12, 3.0, 0.08

#: Code lengths of our DC categories (fewest bits for the steps between letters) and the one AC code, end of block.
DC_LENGTHS = {6: 2, 7: 2, 5: 3, 4: 3, 3: 4, 2: 5, 1: 5, 0: 6, 8: 6}
AC_LENGTHS = {0: 1}


def canonical(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """Symbol -> (code, length): codes ascend with length, then in the order given."""
    code, last, out = 0, 0, {}
    for symbol, n in sorted(lengths.items(), key=lambda x: x[1]):
        code <<= n - last
        out[symbol], last, code = (code, n), n, code + 1
    return out


def segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def table(kind: int, lengths: dict[int, int]) -> bytes:
    symbols = sorted(lengths, key=lambda s: lengths[s])
    return segment(0xC4, bytes([kind << 4]) + bytes(sum(v == n for v in lengths.values()) for n in range(1, 17)) + bytes(symbols))


def frame_header() -> bytes:
    pixels = SIDE * 8
    return b"".join([b"\xff\xd8", segment(0xDB, b"\0" + bytes([8]) + bytes([1]) * 63), segment(0xC0, struct.pack(">BHHB", 8, pixels, pixels, 1) + b"\1\x11\0"), table(0, DC_LENGTHS), table(1, AC_LENGTHS), segment(0xDA, b"\1\1\0\0\x3f\0")])


HEADER = frame_header()


def step_codes() -> tuple[np.ndarray, np.ndarray]:
    """Bits and length of a block by its DC difference plus 255; the end-of-block code is part of it."""
    codes = canonical(DC_LENGTHS)
    bits, length = np.zeros(511, np.int64), np.zeros(511, np.int64)
    for d in range(-255, 256):
        n = abs(d).bit_length()
        code, size = codes[n]
        bits[d + 255], length[d + 255] = ((code << n) | (d if d >= 0 else d + (1 << n) - 1)) << 1, size + n + 1
    return bits, length


STEP_BITS, STEP_LENGTH = step_codes()


def frames_of(payload: np.ndarray) -> list[bytes]:
    """JPEG frames of rows of 576 samples."""
    values = payload.astype(np.int64) - 128
    step = np.diff(values, axis=1, prepend=0) + 255
    bits, length = STEP_BITS[step], STEP_LENGTH[step]
    end = np.cumsum(length, 1)
    size = (end[:, -1] + 7) // 8
    start = np.concatenate([[0], np.cumsum(size)])
    at = (start[:-1, None] * 8 + end - length).ravel()
    word = (bits.ravel() << (24 - (at & 7) - length.ravel())).astype(np.int64)
    byte, total = at >> 3, int(start[-1]) + 2
    out = sum(np.bincount(byte + k, weights=(word >> (16 - 8 * k)) & 255, minlength=total) for k in range(3)).astype(np.uint8)
    out[start[1:] - 1] |= ((1 << (size * 8 - end[:, -1])) - 1).astype(np.uint8)
    data = out.tobytes()
    cut = start.tolist()
    return [HEADER + data[a:b].replace(b"\xff", b"\xff\0") + b"\xff\xd9" for a, b in zip(cut, cut[1:], strict=False)]


def chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)


def container(frames: list[bytes], width: int = SIDE * 8, height: int = SIDE * 8, fps: int = FPS) -> bytes:
    """An AVI file of JPEG frames with an index."""
    most = max(map(len, frames), default=0)
    avih = struct.pack("<14I", 1_000_000 // fps, most * fps, 0, 0x10, len(frames), 0, 1, most, width, height, 0, 0, 0, 0)
    strh = struct.pack("<4s4sIHHIIIIIIII4H", b"vids", b"MJPG", 0, 0, 0, 0, 1, fps, 0, len(frames), most, 0xFFFFFFFF, 0, 0, 0, width, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 24, b"MJPG", width * height * 3, 0, 0, 0, 0)
    size = np.array([len(f) for f in frames], np.int64)
    offset = 4 + np.concatenate([[0], np.cumsum(8 + size + (size & 1))[:-1]]) if len(frames) else np.empty(0)
    index = np.zeros((len(frames), 4), "<u4")
    index[:, 0], index[:, 1], index[:, 2], index[:, 3] = int.from_bytes(b"00dc", "little"), 0x10, offset, size
    hdrl = b"hdrl" + chunk(b"avih", avih) + chunk(b"LIST", b"strl" + chunk(b"strh", strh) + chunk(b"strf", strf))
    movi = b"movi" + b"".join([chunk(b"00dc", f) for f in frames])
    return chunk(b"RIFF", b"AVI " + chunk(b"LIST", hdrl) + chunk(b"LIST", movi) + chunk(b"idx1", index.tobytes()))


@dataclass
class Video:
    fps: float
    frames: list[bytes]


def parse(media: bytes) -> Video:
    """The frames that the index lists (or, without one, those of the movi list in order)."""
    if media[:4] != b"RIFF" or media[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    at, movi, index, fps = 12, 0, None, float(FPS)
    movi_end = 0
    while at + 8 <= len(media):
        name, size = media[at : at + 4], int.from_bytes(media[at + 4 : at + 8], "little")
        if name == b"LIST" and media[at + 8 : at + 12] == b"hdrl":
            if (h := media.find(b"strh", at, at + 8 + size)) >= 0:
                scale, rate = struct.unpack_from("<II", media, h + 8 + 20)
                fps = rate / scale if scale else fps
        elif name == b"LIST" and media[at + 8 : at + 12] == b"movi":
            movi, movi_end = at + 8, at + 8 + size
        elif name == b"idx1":
            index = np.frombuffer(media, "<u4", size // 16 * 4, at + 8).reshape(-1, 4)
        at += 8 + size + (size & 1)
    if not movi:
        raise ValueError("no movi list")
    if index is not None:
        video = index[(index[:, 0] >> 16) == int.from_bytes(b"dc", "little")]
        base = movi if not len(video) or media[movi + int(video[0, 2]) : movi + int(video[0, 2]) + 4] == b"00dc" else 0
        spans = [(base + o + 8, base + o + 8 + n) for o, n in video[:, 2:].tolist()]
    else:
        spans, at = [], movi + 4
        while at + 8 <= movi_end:
            size = int.from_bytes(media[at + 4 : at + 8], "little")
            if media[at + 2 : at + 4] == b"dc":
                spans.append((at + 8, at + 8 + size))
            at += 8 + size + (size & 1)
    if any(b > len(media) for _, b in spans):
        raise ValueError("the index points beyond the file")
    return Video(fps, [media[a:b] for a, b in spans])


@dataclass
class Head:
    """What a frame's header says."""

    size: int = 0  # bytes up to the scan
    height: int = 0
    width: int = 0
    quant: dict[int, np.ndarray] = field(default_factory=dict)
    components: list[list[int]] = field(default_factory=list)  # id, horizontal, vertical, quantiser, DC table, AC table
    huffman: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)


def lookup(counts: bytes, symbols: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Length and symbol of the code at the head of every 16 bits; length 0: none."""
    length, symbol, code, i = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64), 0, 0
    for n in range(1, 17):
        for _ in range(counts[n - 1]):
            a = code << (16 - n)
            b = a + (1 << (16 - n))
            length[a:b], symbol[a:b] = n, symbols[i]
            code, i = code + 1, i + 1
        code <<= 1
    return length, symbol


def head_of(frame: bytes) -> Head:
    h, at = Head(), 2
    if frame[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG frame")
    while True:
        if at + 4 > len(frame) or frame[at] != 0xFF:
            raise ValueError("a damaged JPEG header")
        marker, size = frame[at + 1], int.from_bytes(frame[at + 2 : at + 4], "big")
        body = frame[at + 4 : at + 2 + size]
        at += 2 + size
        if marker == 0xDB:
            while body:
                wide = body[0] >> 4
                h.quant[body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else np.uint8).astype(np.int64)
                body = body[65 + 64 * wide :]
        elif marker == 0xC4:
            while body:
                n = sum(body[1:17])
                h.huffman[body[0]] = lookup(body[1:17], body[17 : 17 + n])
                body = body[17 + n :]
        elif marker == 0xC0:
            _, h.height, h.width, n = struct.unpack_from(">BHHB", body)
            h.components = [[body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i], 0, 0] for i in range(n)]
        elif marker in (0xC1, 0xC2, 0xC3, 0xC5, 0xC6, 0xC7, 0xC9, 0xCA, 0xCB, 0xCD, 0xCE, 0xCF):
            raise ValueError("only baseline frames are decoded")
        elif marker == 0xDD and any(body[:2]):
            raise ValueError("restart intervals are not decoded")
        elif marker == 0xDA:
            for i in range(body[0]):
                for c in h.components:
                    if c[0] == body[1 + 2 * i]:
                        c[4], c[5] = body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15
            h.size = at
            return h


def zigzag() -> np.ndarray:
    """Place in the block of each coefficient in scan order."""
    cells = sorted(((r, c) for r in range(8) for c in range(8)), key=lambda x: (x[0] + x[1], x[0] if (x[0] + x[1]) % 2 else x[1]))
    return np.array([8 * r + c for r, c in cells])


ZIGZAG = zigzag()


@dataclass
class Decoded:
    """Coefficients of the first component: dc (frames, blocks), and the others where not zero."""

    head: Head
    dc: np.ndarray
    frame: np.ndarray
    block: np.ndarray
    place: np.ndarray
    value: np.ndarray

    @property
    def grid(self) -> tuple[int, int]:
        _, hs, vs, *_ = self.head.components[0]
        most_h, most_v = max(c[1] for c in self.head.components), max(c[2] for c in self.head.components)
        mcu_w, mcu_h = -(-self.head.width // (8 * most_h)), -(-self.head.height // (8 * most_v))
        if len(self.head.components) == 1:
            return -(-self.head.height // 8), -(-self.head.width // 8)
        return mcu_h * vs, mcu_w * hs

    def flat(self) -> np.ndarray:
        """The value of each block where a frame has DC coefficients only."""
        q = int(self.head.quant[self.head.components[0][3]][0])
        return np.clip(np.floor(self.dc * q / 8 + 128.5), 0, 255).astype(np.uint8)

    def pixels(self, frame: int) -> np.ndarray:
        """The grey plane of a frame."""
        q, (rows, columns) = self.head.quant[self.head.components[0][3]], self.grid
        own = self.frame == frame
        c = np.zeros((rows * columns, 64))
        c[:, 0] = self.dc[frame] * q[0]
        c[self.block[own], ZIGZAG[self.place[own]]] = self.value[own] * q[self.place[own]]
        k = np.arange(8)
        basis = np.cos((2 * k[None, :] + 1) * k[:, None] * np.pi / 16) * np.where(k[:, None] == 0, np.sqrt(1 / 8), 0.5)
        blocks = np.clip(np.rint(basis.T @ c.reshape(-1, 8, 8) @ basis + 128), 0, 255).astype(np.uint8)
        return blocks.reshape(rows, columns, 8, 8).transpose(0, 2, 1, 3).reshape(8 * rows, 8 * columns)[: self.head.height, : self.head.width]


def decode(frames: list[bytes]) -> list[tuple[np.ndarray, Decoded]]:
    """Decode frames, those of equal headers together: pairs of (their numbers, what was decoded)."""
    groups: dict[bytes, list[int]] = {}
    last = None
    for i, f in enumerate(frames):
        if last is None or not f.startswith(last):
            last = f[: head_of(f).size]
        groups.setdefault(last, []).append(i)
    return [(np.array(own), _decode(head_of(frames[own[0]]), [frames[i][len(h) :] for i in own])) for h, own in groups.items()]


def _decode(head: Head, scans: list[bytes]) -> Decoded:
    clean = [s[: s.rfind(b"\xff\xd9")].replace(b"\xff\0", b"\xff") + b"\xff" * 8 for s in scans]
    start = np.cumsum([0] + [len(x) for x in clean])
    b = np.frombuffer(b"".join(clean), np.uint8).astype(np.uint32)
    window = b[:-3] << 24 | b[1:-2] << 16 | b[2:-1] << 8 | b[3:]
    several = len(head.components) > 1
    pattern = [i for i, c in enumerate(head.components) for _ in range(c[1] * c[2] if several else 1)]
    most_h, most_v = max(c[1] for c in head.components), max(c[2] for c in head.components)
    mcus = -(-head.width // (8 * (most_h if several else 1))) * -(-head.height // (8 * (most_v if several else 1)))
    component, blocks = np.array(pattern), mcus * len(pattern)
    used = [head.huffman[k << 4 | c[4 + k]] for c in head.components for k in (0, 1)]
    length, symbol = np.concatenate([t[0] for t in used]), np.concatenate([t[1] for t in used])
    n = len(clean)
    pos, stop = start[:-1].astype(np.int64) * 8, start[1:].astype(np.int64) * 8
    block, k, live = np.zeros(n, np.int64), np.zeros(n, np.int64), np.arange(n)
    pred, dc, other = np.zeros((n, len(head.components)), np.int64), np.zeros((n, blocks), np.int32), []
    while len(live):
        peek = window[pos >> 3].astype(np.int64) >> (16 - (pos & 7)) & 0xFFFF
        comp = component[block % len(pattern)] if several else 0
        at = ((2 * comp + (k > 0)) << 16) + peek
        size, sym = length[at], symbol[at]
        pos = pos + size
        extra = sym & 15
        more = window[pos >> 3].astype(np.int64) >> (16 - (pos & 7)) & 0xFFFF
        value = more >> (16 - extra)
        value = np.where(value < (1 << extra) >> 1, value - (1 << extra) + 1, value)
        pos = pos + extra
        if (size == 0).any() or (pos > stop[live]).any():
            raise ValueError("a damaged JPEG scan")
        first = k == 0
        if first.any():
            f = np.flatnonzero(first)
            g, own = live[f], (comp[f] if several else 0)
            pred[g, own] += value[f]
            dc[g, block[f]] = pred[g, own]
        run = sym >> 4
        here = k + run
        ac = ~first & (extra > 0)
        if ac.any():
            f = np.flatnonzero(ac)
            other.append((live[f], block[f], np.minimum(here[f], 63), value[f]))
        k = np.where(first, 1, np.where(sym == 0, 64, here + 1))
        done = k > 63
        block = block + done
        k[done] = 0
        if done.any() and (over := block >= blocks).any():
            keep = ~over
            live, pos, block, k = live[keep], pos[keep], block[keep], k[keep]
    frame, where, place, value = (np.concatenate(x) for x in zip(*other, strict=True)) if other else (np.empty(0, np.int64),) * 4
    if several:  # only the first component stays, its blocks from MCU order to rows
        hs, vs = head.components[0][1:3]
        wide = -(-head.width // (8 * most_h))
        i = np.arange(mcus)[:, None] * len(pattern) + np.arange(hs * vs)
        row = (np.arange(mcus) // wide)[:, None] * vs + np.arange(hs * vs) // hs
        column_ = (np.arange(mcus) % wide)[:, None] * hs + np.arange(hs * vs) % hs
        to = np.full(blocks, -1)
        to[i] = row * wide * hs + column_
        luma = np.empty((n, mcus * hs * vs), dc.dtype)
        luma[:, to[i].ravel()] = dc[:, i.ravel()]
        own = to[where] >= 0
        return Decoded(head, luma, frame[own], to[where[own]], place[own], value[own])
    return Decoded(head, dc, frame, where, place, value)


def histograms(frames: list[bytes]) -> tuple[np.ndarray, list[tuple[np.ndarray, Decoded]]]:
    """Grey histogram of each frame, as shares."""
    out, decoded = np.zeros((len(frames), BINS)), decode(frames)
    for own, d in decoded:
        rich = np.unique(d.frame)
        flat = d.flat()
        count = np.bincount((np.arange(len(own))[:, None] * BINS + (flat >> 4)).ravel(), minlength=len(own) * BINS).reshape(-1, BINS).astype(float)
        for i in rich:
            count[i] = np.bincount(d.pixels(int(i)).ravel() >> 4, minlength=BINS)
        out[own] = count / count.sum(1, keepdims=True)
    return out, decoded


def shots(histogram: np.ndarray) -> list[tuple[int, int, float]]:
    """Shots (first frame, end, difference at its start) from the histograms of one video."""
    n = len(histogram)
    if not n:
        return []
    d = np.concatenate([[0.0], np.abs(np.diff(histogram, axis=0)).sum(1) / 2])
    cut = np.zeros(n, bool)
    for t in np.flatnonzero(d > FLOOR).tolist():
        before = slice(max(1, t - WINDOW), t)
        kept = d[before][~cut[before]]
        if not len(kept):  # nothing but cuts: with these, so that steady noise isn't cut at each frame
            kept = d[before]
        cut[t] = not len(kept) or d[t] > kept.mean() + DEVIATIONS * max(kept.std(), 1e-3)
    cuts = np.flatnonzero(cut)
    starts = [0, *cuts.tolist()]
    return [(a, b, float(d[a])) for a, b in zip(starts, [*starts[1:], n], strict=True)]


def payload_of(text: bytes) -> bytes:
    n = max(FRAME, -(-len(text) // FRAME) * FRAME)
    return text.ljust(n, b"\xff")


def store(payloads: list[bytes]) -> list[bytes]:
    """One AVI file for each payload, whose length is a positive multiple of 576."""
    frames = frames_of(np.frombuffer(b"".join(payloads), np.uint8).reshape(-1, FRAME))
    out, at = [], 0
    for p in payloads:
        out.append(container(frames[at : at + len(p) // FRAME]))
        at += len(p) // FRAME
    return out


def read_back(media: list[bytes]) -> list[tuple[bytes, list[tuple[int, int, float]]]]:
    """Payload and shots of each file that `store` wrote."""
    videos = [parse(m) for m in media]
    histogram, decoded = histograms([f for v in videos for f in v.frames])
    total = sum(len(v.frames) for v in videos)
    samples = np.empty((total, FRAME), np.uint8)
    for own, d in decoded:
        samples[own] = d.flat()
    out, at = [], 0
    for v in videos:
        n = len(v.frames)
        out.append((samples[at : at + n].tobytes(), shots(histogram[at : at + n])))
        at += n
    return out


def media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, media): each text stored as an AVI file."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, text_col, 2 << 20):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(store([payload_of(x) for x in raw_texts(b, text_col)]), pa.binary())], [id_col, "media"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(settled(run), f"{id_col} {kind}, media binary")


def clips(media: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """Rows (id, clip, first_frame, end_frame, start_s, end_s, difference, error), one for each shot of each file."""
    names = ["clip", "first_frame", "end_frame", "start_s", "end_s", "difference", "error"]
    types = [pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, media_col, 4 << 20):
            at, rows = [], []
            for i, m in enumerate(b.column(1).to_pylist()):
                if m is None:
                    continue
                try:
                    v = parse(m)
                    found = [(k, s, e, s / v.fps, e / v.fps, x, None) for k, (s, e, x) in enumerate(shots(histograms(v.frames)[0]))]
                except (ValueError, struct.error, IndexError, KeyError) as e:
                    found = [(None, None, None, None, None, None, str(e))]
                at += [i] * len(found)
                rows += found
            columns = zip(*rows, strict=True) if rows else [()] * 7
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, pa.int64())), *[pa.array(c, t) for c, t in zip(columns, types, strict=True)]], [id_col, *names])

    kind = media.schema[id_col].dataType.simpleString()
    return media.select(id_col, media_col).mapInArrow(settled(run), f"{id_col} {kind}, clip int, first_frame long, end_frame long, start_s double, end_s double, difference double, error string")


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """What op1 returns: every text stored, and read back from the stored bytes."""
    names = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, text_col, 2 << 20):
            raw = raw_texts(b, text_col)
            stored = store([payload_of(x) for x in raw])
            rows = []
            for x, m, (p, found) in zip(raw, stored, read_back(stored), strict=True):
                feature = f"frames={len(p) // FRAME} shots={len(found)} starts={','.join(str(s) for s, _, _ in found)}"
                rows.append((len(x), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]), len(m), hashlib.sha256(m).hexdigest(), feature))
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)]], [id_col, *names])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(settled(run), f"{id_col} {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
