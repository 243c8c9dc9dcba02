"""Token counts by offset-mapped attribution.

A whole document is encoded once.  Byte lengths of its tokens give their offsets; sections (or named fields) are
disjoint intervals of code points, and both lists being in order, one merge joins them.  A token that crosses a
boundary goes to one section by an explicit rule: `first` (the section of its first byte), `last`, `largest` (most
bytes; ties to the earlier) or `share` (each section gets its part, as a fraction).

Null text: empty, one section without tokens.  Tokens outside of all fields count under the name null.  Sections may
be empty.  Equal texts get equal counts; repeated rows are counted one by one; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .bpe import SLICE, loaded, unloaded, vocabulary
from .common import settled, slices, texts

RULES = ("first", "last", "largest", "share")


def char_places(raw: np.ndarray) -> np.ndarray:
    """Byte offset of each code point of UTF-8 text, and its length at the end."""
    return np.append(np.flatnonzero((raw & 0xC0) != 0x80), len(raw))


def lines(raw: np.ndarray) -> np.ndarray:
    """Byte bounds of a text's lines; a line keeps its newline."""
    ends = np.flatnonzero(raw == 10) + 1
    return np.unique(np.concatenate([[0], ends[ends < len(raw)], [len(raw)]])) if len(raw) else np.array([0, 0])


def cut_by(fields: list[dict] | None, n: int) -> tuple[np.ndarray, list[str | None]]:
    """Bounds that cover a text of n code points, and the field between each two (null: none)."""
    clipped = lambda x, other: min(max(0, other if x is None else x), n)
    own = sorted(((clipped(f["first_char"], 0), clipped(f["end_char"], n), k, f["name"]) for k, f in enumerate(fields or []) if f is not None), key=lambda f: f[:3])
    cuts, tags, at = [0], [], 0
    for first, end, _, name in own:
        if first > at:
            cuts.append(first), tags.append(None)
        at = max(first, at)
        at = max(end, at)
        cuts.append(at), tags.append(name)
    if at < n or not tags:
        cuts.append(n), tags.append(None)
    return np.array(cuts), tags


def attributed(token_end: np.ndarray, bounds: np.ndarray, rule: str = "first") -> tuple[np.ndarray, np.ndarray]:
    """Tokens of each section [bounds[i], bounds[i+1]), and how many of them cross a boundary.

    The sections cover the text, and so do the tokens, which end at token_end.
    """
    n = len(bounds) - 1
    if not len(token_end):
        return np.zeros(n), np.zeros(n, np.int64)
    start = np.concatenate([[0], token_end[:-1]])
    first = np.searchsorted(bounds, start, "right") - 1
    last = np.searchsorted(bounds, token_end, "left") - 1
    first, last = np.clip(first, 0, n - 1), np.clip(last, 0, n - 1)
    cross = last > first
    own = {"first": first, "last": last}.get(rule, first).copy()
    count = None
    if rule == "largest":
        for t in np.flatnonzero(cross):
            inside = np.minimum(bounds[first[t] + 1 : last[t] + 2], token_end[t]) - np.maximum(bounds[first[t] : last[t] + 1], start[t])
            own[t] = first[t] + int(inside.argmax())
    elif rule == "share":
        count = np.bincount(first[~cross], minlength=n).astype(float)
        for t in np.flatnonzero(cross):
            inside = np.minimum(bounds[first[t] + 1 : last[t] + 2], token_end[t]) - np.maximum(bounds[first[t] : last[t] + 1], start[t])
            count[first[t] : last[t] + 1] += inside / (token_end[t] - start[t])
    if count is None:
        count = np.bincount(own, minlength=n).astype(float)
    return count, np.bincount(own[cross], minlength=n)


def sections(docs: DataFrame, path: str, rule: str = "first", id_col: str = "doc_id", text_col: str = "text", fields_col: str | None = None) -> DataFrame:
    """Rows (id, section, name, first_char, end_char, n_tokens double, n_crossing, doc_tokens), one for each line of each document.

    With fields_col, an array of (name, first_char, end_char), one row for each field, and one for each gap that has
    characters (name null).  Fields are cut to the text (null bounds: its ends) and taken by their first character; one
    that begins inside another starts at the end of it, and is empty if it ends there too.
    """
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    spec = docs.sparkSession.sparkContext.broadcast(vocabulary(path))
    names = ["section", "name", "first_char", "end_char", "n_tokens", "n_crossing", "doc_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(spec.value)
        for b in slices(unloaded(batches), text_col, SLICE):
            many = texts(b, text_col)
            fields = b.column(2).to_pylist() if fields_col else [None] * len(many)
            out: list[list[np.ndarray]] = [[] for _ in range(8)]
            labels: list[str | None] = []
            for i, (text, ids, named) in enumerate(zip(many, bpe.encode_batch(many), fields, strict=True)):
                raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
                place = char_places(raw)
                if fields_col:
                    chars, tags = cut_by(named, len(place) - 1)
                    bounds = place[chars]
                else:
                    bounds = lines(raw)
                    chars = np.searchsorted(place, bounds)
                    tags = [None] * (len(bounds) - 1)
                count, cross = attributed(np.cumsum(bpe.token_length[ids]), bounds, rule)
                n = len(count)
                labels += tags
                for k, x in enumerate((np.full(n, i), np.arange(n), chars[:-1], chars[1:], count, cross, np.full(n, len(ids)))):
                    out[k].append(x)
            cat = [np.concatenate([*x, np.empty(0, np.int64)]) for x in out[:7]]
            arrays = [pa.array(cat[1].astype(np.int32)), pa.array(labels, pa.string()), *[pa.array(c.astype(np.int64)) for c in cat[2:4]], pa.array(cat[4].astype(np.float64)), *[pa.array(c.astype(np.int64)) for c in cat[5:7]]]
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(cat[0].astype(np.int64))), *arrays], [id_col, *names])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col, *([fields_col] if fields_col else [])).mapInArrow(settled(run), f"{id_col} {kind}, section int, name string, first_char long, end_char long, n_tokens double, n_crossing long, doc_tokens long")
