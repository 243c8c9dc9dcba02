"""Byte-level BPE by contiguous rank arrays.

A short word is a row of part ids beside a row of the ranks of adjacent pairs.  The smallest rank is found by
scanning, the boundary there is deleted, and the two neighbouring ranks are looked up again, until no pair has a
rank.  Rows of many words advance together as one matrix.  Words longer than SHORT bytes, for which scanning would be
quadratic, take a linked list with a heap, which merges in the same order.

Texts: null encodes as an empty text (no ids); any Unicode text, however long, is encoded whole; equal texts get
equal ids; an empty table gives no rows; columns other than those named are ignored.
"""

from __future__ import annotations

import gc
import hashlib
import heapq
import json
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import settled, slices, texts

SHORT = 64
#: Bytes that the words and pieces a worker has seen may take, all memories together.
REMEMBERED = 48 << 20
#: Pieces of more characters than this are forgotten after their slice of texts.
BRIEF = 64
#: Bytes of text in a slice: what a slice adds to the memories is bounded by it.
SLICE = 2 << 20
#: Fixed value: the public pattern that splits text before the merges.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
NEVER = np.int32(2**31 - 1)
#: A space between two characters that aren't white space starts a word wherever it stands.
PLAIN_GAP = re.compile(r"(?<=\S) (?=\S)")


def byte_letters() -> list[str]:
    """The printable character that stands for each byte in the vocabulary: itself if visible, else the next free one from 256."""
    visible = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = iter(range(256, 512))
    return [chr(b) if b in visible else chr(next(hidden)) for b in range(256)]


class Memory:
    """Ids of pieces in two generations: what isn't met again while the younger one fills up goes with the older one."""

    def __init__(self) -> None:
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def lacking(self, pieces: set[str]) -> set[str]:
        """The pieces that aren't remembered; all others are in the younger generation after this."""
        new = pieces - self.young.keys()
        if self.old:
            again = new & self.old.keys()
            self.young.update((p, self.old[p]) for p in again)
            new -= again
        return new


class RankArrayBPE:
    """Encoder and decoder for a byte-level vocabulary file of the tokenizers library."""

    def __init__(self, spec: bytes | str):
        spec = json.loads(spec)
        model, letters = spec["model"], byte_letters()
        vocab = model["vocab"]
        back = {c: b for b, c in enumerate(letters)}
        special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        n = max([*vocab.values(), *special.values()]) + 1
        self.token_bytes = [b""] * n
        for token, i in vocab.items():
            self.token_bytes[i] = bytes(back[c] for c in token if c in back)
        for token, i in special.items():
            self.token_bytes[i] = token.encode()
        self.token_length = np.array([len(x) for x in self.token_bytes], np.int64)
        self.decimal = [str(i) for i in range(n)]
        self.first_ids = np.array([vocab.get(c, 0) for c in letters], np.int32)
        pairs = [x if isinstance(x, list) else x.split(" ") for x in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys = np.append(keys[order], np.int64(2**62))
        self.ranks = np.append(order.astype(np.int32), NEVER)
        self.merged = np.array([vocab[a + b] for a, b in pairs], np.int32)
        self.special = special
        self.split_special = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")") if special else None
        self.kind = np.dtype("<u2" if n <= 1 << 16 else "<u4")
        self.pair_ranks: dict[int, int] | None = None  # for long words, made when the first comes
        self.held = 0  # bytes that the younger generations were given, about
        self.passing: list[tuple[Memory, str]] = []  # what goes after this slice
        self.words, self.odd = Memory(), Memory()  # odd: pieces of texts with other white space beside a space
        self.opening, self.spaced = Memory(), Memory()  # pieces at the start of a text, and after one space
        self.split_words = regex.compile(PATTERN).findall

    def rank_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        wanted = left.astype(np.int64) << 20 | right
        at = np.searchsorted(self.keys, wanted)
        return np.where(self.keys[at] == wanted, self.ranks[at], NEVER)

    def merge_rows(self, words: list[bytes], width: int) -> list[bytes]:
        """Ids (as little-endian 16- or 32-bit numbers) of words of at most `width` bytes."""
        n = len(words)
        size = np.fromiter(map(len, words), np.int64, n)
        grid = np.frombuffer(b"".join(w.ljust(width, b"\0") for w in words), np.uint8).reshape(n, width)
        parts = self.first_ids[grid]
        column = np.arange(width)
        ranks = np.full((n, width), NEVER, np.int32)
        if width > 1:
            ranks[:, :-1] = self.rank_of(parts[:, :-1], parts[:, 1:])
            ranks[column[None, :] >= size[:, None] - 1] = NEVER
        live = np.arange(n)
        while len(live):
            p, r = parts[live], ranks[live]
            row, at = np.arange(len(live)), r.argmin(1)
            low = r[row, at]
            go = low < NEVER
            if not go.all():
                live, p, r, at, low = live[go], p[go], r[go], at[go], low[go]
                row = row[: len(live)]
                if not len(live):
                    break
            p[row, at] = self.merged[low]
            take = np.minimum(column + (column > at[:, None]), width - 1)  # delete the boundary after `at`
            p = np.take_along_axis(p, take, 1)
            r = np.take_along_axis(r, np.minimum(column + (column >= at[:, None]), width - 1), 1)
            size[live] -= 1
            r[:, -1] = NEVER
            end = size[live] - 1
            before = np.maximum(at - 1, 0)
            r[row, before] = np.where(at > 0, self.rank_of(p[row, before], p[row, at]), r[row, before])
            after = np.minimum(at + 1, width - 1)
            r[row, at] = np.where(at < end, self.rank_of(p[row, at], p[row, after]), NEVER)
            parts[live], ranks[live] = p, r
        flat = parts[column[None, :] < size[:, None]].astype(self.kind).tobytes()
        end = (np.cumsum(size) * self.kind.itemsize).tolist()
        return [flat[i:j] for i, j in zip([0, *end], end, strict=False)]

    def merge_long(self, word: bytes) -> bytes:
        ids = self.first_ids[np.frombuffer(word, np.uint8)].tolist()
        n = len(ids)
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        if self.pair_ranks is None:
            self.pair_ranks = dict(zip(self.keys.tolist(), self.ranks.tolist(), strict=True))
        known = self.pair_ranks
        rank = lambda i, j: known.get(ids[i] << 20 | ids[j])
        heap = [(k, i, ids[i], ids[i + 1]) for i in range(n - 1) if (k := rank(i, i + 1)) is not None]
        heapq.heapify(heap)
        while heap:
            k, i, left, right = heapq.heappop(heap)
            j = after[i]
            if ids[i] != left or j < 0 or ids[j] != right:
                continue
            ids[i], ids[j], after[i] = int(self.merged[k]), -1, after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for x, y in ((before[i], i), (i, after[i])):
                if x >= 0 and y >= 0 and (k := rank(x, y)) is not None:
                    heapq.heappush(heap, (k, x, ids[x], ids[y]))
        return np.array([x for x in ids if x >= 0], self.kind).tobytes()

    def encode_words(self, words: list[str]) -> list[bytes]:
        """Ids of whole words, rows of similar length together."""
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        out: list[bytes] = [b""] * len(words)
        size = np.fromiter(map(len, raw), np.int64, len(raw))
        low = 0
        for width in (6, 8, 12, 16, 24, 32, SHORT):
            here = np.flatnonzero((size > low) & (size <= width)).tolist()
            for i in range(0, len(here), 1 << 15):
                part = here[i : i + (1 << 15)]
                for k, ids in zip(part, self.merge_rows([raw[k] for k in part], width), strict=True):
                    out[k] = ids
            low = width
        for k in np.flatnonzero(size > SHORT).tolist():
            out[k] = self.merge_long(raw[k])
        return out

    def _fill(self, memory: Memory, missing: list[str], lead: str) -> None:
        """Remember pieces: a space (or nothing) and what follows it."""
        whole = [p for p in missing if p.isalpha()]  # these are single words
        self._keep(memory, whole, self.encode_words([lead + p for p in whole]))
        rest = [p for p in missing if not p.isalpha()]
        parts = [self.split_words(lead + p) for p in rest]
        new = list(self.words.lacking({w for ws in parts for w in ws}))
        self._keep(self.words, new, self.encode_words(new))
        get = self.words.young.__getitem__
        self._keep(memory, rest, [b"".join(map(get, ws)) for ws in parts])

    def _keep(self, memory: Memory, pieces: list[str], ids: list[bytes]) -> None:
        memory.young.update(zip(pieces, ids, strict=True))
        self.held += 250 * len(pieces) + 2 * sum(map(len, pieces)) + sum(map(len, ids))
        self.passing += [(memory, p) for p in pieces if len(p) > BRIEF]

    def forget(self, all_of_it: bool = True) -> None:
        """Drop long pieces, and the older generations if the younger are full, or all."""
        for memory, p in self.passing:
            self.held -= 250 + 2 * len(p) + len(memory.young.pop(p, b""))
        self.passing = []
        if all_of_it or self.held > REMEMBERED // 2:
            for memory in (self.words, self.opening, self.spaced, self.odd):
                memory.young, memory.old = {}, {} if all_of_it else memory.young
            self.held = 0

    def _plain(self, many: list[str]) -> list[np.ndarray]:
        """Ids of texts without special tokens.

        Between characters that aren't white space, a space opens a new word whatever stands around, so the pieces
        between spaces encode alone.  Where a piece is empty or touches other white space, the text is cut at the
        plain gaps only.
        """
        pieces = [x.split(" ") for x in many]
        missing = self.spaced.lacking(set().union(*pieces))
        bad = {p for p in missing if not p or p[0].isspace() or p[-1].isspace()}
        odd = {i for i, p in enumerate(pieces) if not bad.isdisjoint(p)} if bad else set()
        self._fill(self.spaced, [p for p in missing if p not in bad], " ")
        self._fill(self.opening, list(self.opening.lacking({p[0] for i, p in enumerate(pieces) if i not in odd})), "")
        cut = {i: [x if k == 0 else " " + x for k, x in enumerate(PLAIN_GAP.split(many[i]))] for i in odd}
        self._fill(self.odd, list(self.odd.lacking({x for c in cut.values() for x in c})), "")
        get, rare, out = self.spaced.young.__getitem__, self.odd.young.__getitem__, []
        for i, p in enumerate(pieces):
            ids = b"".join(map(rare, cut[i])) if i in cut else self.opening.young[p[0]] + b"".join(map(get, p[1:]))
            out.append(np.frombuffer(ids, self.kind))
        self.forget(all_of_it=False)
        return out

    def encode_batch(self, many: list[str]) -> list[np.ndarray]:
        """Ids of each text.  A special token's string in a text is that token."""
        # Nothing here makes cycles; without the collector's passes over the memories this is a third faster.
        collecting = gc.isenabled()
        gc.disable()
        try:
            return self._encode(many)
        finally:
            if collecting:
                gc.enable()

    def _encode(self, many: list[str]) -> list[np.ndarray]:
        if not self.split_special:
            return self._plain(many)
        out: list[np.ndarray | None] = [None] * len(many)
        plain = []
        for i, x in enumerate(many):
            if any(s in x for s in self.special):
                parts = self.split_special.split(x)
                ids = self._plain(parts[::2])
                out[i] = np.concatenate([y for k, a in enumerate(ids) for y in ((a, np.array([self.special[parts[2 * k + 1]]], self.kind)) if 2 * k + 1 < len(parts) else (a,))])
            else:
                plain.append(i)
        for i, ids in zip(plain, self._plain([many[i] for i in plain]), strict=True):
            out[i] = ids
        return out

    def decode(self, ids: Iterable[int]) -> str:
        return b"".join(map(self.token_bytes.__getitem__, ids)).decode("utf-8", "replace")


_loaded: dict[str, RankArrayBPE] = {}


def loaded(spec: bytes) -> RankArrayBPE:
    """The encoder of a vocabulary, once in each worker."""
    key = hashlib.sha256(spec).hexdigest()
    if key not in _loaded:
        _loaded.clear()
        _loaded[key] = RankArrayBPE(spec)
    _loaded[key].forget()  # a task starts without another's words, so no worker carries them through other stages
    return _loaded[key]


def unloaded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches; at their end the worker forgets the words that it has seen."""
    try:
        yield from batches
    finally:
        for bpe in _loaded.values():
            bpe.forget()


def vocabulary(path: str) -> bytes:
    """The vocabulary file (some MB), read on the driver and sent to the executors."""
    with open(path, "rb") as f:
        return f.read()


def encode(df: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, ids array<int>): every text encoded."""
    spec = df.sparkSession.sparkContext.broadcast(vocabulary(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(spec.value)
        for b in slices(unloaded(batches), text_col, SLICE):
            ids = bpe.encode_batch(texts(b, text_col))
            offsets = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, np.concatenate([*ids, np.empty(0, "<u2")]).astype(np.int32))], [id_col, "ids"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, text_col).mapInArrow(settled(run), f"{id_col} {kind}, ids array<int>")


def decode(df: DataFrame, path: str, id_col: str = "doc_id") -> DataFrame:
    """Rows (id, text) from rows (id, ids)."""
    spec = df.sparkSession.sparkContext.broadcast(vocabulary(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(spec.value)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([bpe.decode(x or []) for x in b.column(1).to_pylist()], pa.string())], [id_col, "text"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, "ids").mapInArrow(settled(run), f"{id_col} {kind}, text string")


def round_trip(df: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, n_tokens, ids_sha256, decoded_sha256) of each text: encoded, and decoded from its ids, in one pass."""
    spec = df.sparkSession.sparkContext.broadcast(vocabulary(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(spec.value)
        decimal = bpe.decimal.__getitem__
        for b in slices(unloaded(batches), text_col, SLICE):
            counts, hashes, decoded = [], [], []
            for ids in bpe.encode_batch(texts(b, text_col)):
                numbers = ids.tolist()
                counts.append(len(numbers))
                hashes.append(hashlib.sha256(",".join(map(decimal, numbers)).encode()).hexdigest())
                decoded.append(hashlib.sha256(bpe.decode(numbers).encode("utf-8", "surrogatepass")).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(counts, pa.int64()), pa.array(hashes, pa.string()), pa.array(decoded, pa.string())], [id_col, "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, text_col).mapInArrow(settled(run), f"{id_col} {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
