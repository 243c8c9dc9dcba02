"""Rasters as arrays, in Catalyst expressions: byte and vector rasters, resize, crop, normalise, layout, 8 x 8 DCT.

A text's raster is all its UTF-8 bytes, in rows of `width`, the last filled with zeros.  A vector of 64 floats is one
8 x 8 block.  These are for small rasters and for checking; the Arrow stage has the same operators for volume.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, functions as F

WIDTH = 32


def let(value: Column, body) -> Column:
    """body(value), with the value computed once: an expression that stands inside of a lambda is computed for each element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def byte_pixels(text: Column, width: int = WIDTH) -> Column:
    """array<int> of a text's bytes, filled up to whole rows (one row at least)."""
    h = F.hex(F.encode(F.coalesce(text, F.lit("")), "UTF-8"))
    n = (F.length(h) / 2).cast("int")
    padded = F.rpad(h, (F.greatest(F.ceil(n / width), F.lit(1)) * 2 * width).cast("int"), F.lit("0"))
    # one pass: a substring by position would scan the string from its start for each pixel
    return F.transform(F.regexp_extract_all(padded, F.lit(".."), F.lit(0)), lambda x: F.conv(x, 16, 10).cast("int"))


def vector_pixels(vector: Column) -> Column:
    return F.transform(vector, lambda v: F.greatest(F.lit(0), F.least(F.lit(255), F.floor((v.cast("double") + 1) * 127.5).cast("int"))))


def at(pixels: Column, i: Column) -> Column:
    return F.element_at(pixels, (i + 1).cast("int"))


def grid(n: Column | int) -> Column:
    return F.sequence(F.lit(0), (n if isinstance(n, Column) else F.lit(n)) - 1)


def box_half(pixels: Column, width: int, height: Column) -> Column:
    """Mean of each 2 x 2 cell, halves up; an odd last row counts twice."""
    half = width // 2
    rows = F.floor((height + 1) / 2).cast("int")

    def cell(pixels: Column, i: Column) -> Column:
        r, c = F.floor(i / half).cast("int") * 2, (i % half) * 2
        below = F.least(r + 1, height - 1)
        total = at(pixels, r * width + c) + at(pixels, r * width + c + 1) + at(pixels, below * width + c) + at(pixels, below * width + c + 1)
        return F.floor((total + 2) / 4).cast("int")

    return let(pixels, lambda p: F.transform(grid((rows * half).cast("int")), lambda i: cell(p, i)))


def nearest_double(pixels: Column, width: int, height: Column) -> Column:
    """Each pixel twice in both directions, cut to `height` rows of 2 x width."""
    return let(pixels, lambda p: F.transform(grid((height * 2 * width).cast("int")), lambda i: at(p, F.floor(F.floor(i / (2 * width)) / 2) * width + F.floor((i % (2 * width)) / 2))))


def resize_nearest(pixels: Column, h: int, w: int, h2: int, w2: int) -> Column:
    return let(pixels, lambda p: F.transform(grid(h2 * w2), lambda i: at(p, F.floor((F.floor(i / w2) + 0.5) * h / h2).cast("int") * w + F.floor((i % w2 + 0.5) * w / w2).cast("int"))))


def resize_bilinear(pixels: Column, h: int, w: int, h2: int, w2: int) -> Column:
    """Pixel centres aligned, edges held."""

    def cell(pixels: Column, i: Column) -> Column:
        y = F.greatest(F.lit(0.0), F.least(F.lit(h - 1.0), (F.floor(i / w2) + 0.5) * h / h2 - 0.5))
        x = F.greatest(F.lit(0.0), F.least(F.lit(w - 1.0), (i % w2 + 0.5) * w / w2 - 0.5))
        y0, x0 = F.floor(y).cast("int"), F.floor(x).cast("int")
        y1, x1 = F.least(y0 + 1, F.lit(h - 1)), F.least(x0 + 1, F.lit(w - 1))
        fy, fx = y - y0, x - x0
        top = at(pixels, y0 * w + x0) * (1 - fx) + at(pixels, y0 * w + x1) * fx
        low = at(pixels, y1 * w + x0) * (1 - fx) + at(pixels, y1 * w + x1) * fx
        return top * (1 - fy) + low * fy

    return let(pixels, lambda p: F.transform(grid(h2 * w2), lambda i: cell(p, i)))


def crop(pixels: Column, w: int, left: int, top: int, right: int, bottom: int) -> Column:
    return let(pixels, lambda p: F.flatten(F.array(*[F.slice(p, r * w + left + 1, right - left) for r in range(top, bottom)])))


def normalised(pixels: Column, mean: list[float], std: list[float], channels: int = 1) -> Column:
    """(value / 255 - mean) / deviation of its channel, channels last."""
    m, s = F.array(*map(F.lit, mean)), F.array(*map(F.lit, std))
    return F.transform(pixels, lambda v, i: (v / 255.0 - F.element_at(m, i % channels + 1)) / F.element_at(s, i % channels + 1))


def channels_first(pixels: Column, n: int, channels: int) -> Column:
    """n pixels from channels last to channels first."""
    return let(pixels, lambda p: F.transform(grid(n * channels), lambda i: at(p, (i % n) * channels + F.floor(i / n))))


def fused(pixels: Column, n: int, mean: list[float], std: list[float], channels: int = 1) -> Column:
    """Normalise, cast and reorder in one pass: a multiplication and an addition for each value."""
    a, b = F.array(*[F.lit(1 / (255.0 * s)) for s in std]), F.array(*[F.lit(-m / s) for m, s in zip(mean, std, strict=True)])
    place = lambda i: F.floor(i / n).cast("int") + 1
    return let(pixels, lambda p: F.transform(grid(n * channels), lambda i: at(p, (i % n) * channels + F.floor(i / n)) * F.element_at(a, place(i)) + F.element_at(b, place(i))))


def basis() -> list[float]:
    """The orthonormal 8-point cosine basis, frequency by frequency."""
    return [math.sqrt((1 if k == 0 else 2) / 8) * math.cos((2 * x + 1) * k * math.pi / 16) for k in range(8) for x in range(8)]


def _half_dct(values: Column, inverse: bool) -> Column:
    """One separable pass over rows, with the result transposed: two passes make the transform."""
    c = F.array(*map(F.lit, basis()))

    def cell(values: Column, i: Column) -> Column:
        k, row = F.floor(i / 8), i % 8
        term = lambda x: at(values, row * 8 + x) * (at(c, x * 8 + k) if inverse else at(c, k * 8 + x))
        return F.aggregate(grid(8), F.lit(0.0), lambda s, x: s + term(x))

    return let(values, lambda v: F.transform(grid(64), lambda i: cell(v, i)))


def dct(values: Column, inverse: bool = False) -> Column:
    """8 x 8 cosine transform of 64 values (orthonormal)."""
    return _half_dct(_half_dct(values, inverse), inverse)


def mse(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v) / F.size(a)


def histogram(pixels: Column, bins: int) -> Column:
    """Counts of `bins` equal ranges of 0..255."""
    scale = 256 // bins
    return let(pixels, lambda p: F.transform(grid(bins), lambda b: F.size(F.filter(p, lambda v: F.floor(v / scale) == b))))
