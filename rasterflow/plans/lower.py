"""Lowering of a chain's operators after decoding: to one Catalyst expression, or to one NumPy function for the Arrow stage.

Rasters are grey, row by row.  Both forms take any run of a chain, so a chain can be cut anywhere: the part before the
cut runs in the Arrow stage, the part after it in the JVM beside the model.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import Column, functions as F

from ..functions import rasters as R
from .dag import Op, shape_after


def shape(ops: Sequence[Op], h: int, w: int) -> tuple[int, int]:
    for o in ops:
        h, w = shape_after(o, h, w)
    return h, w


def centre(h: int, w: int, size: int) -> tuple[int, int, int, int]:
    """left, top, right, bottom of the middle."""
    top, left = (h - min(h, size)) // 2, (w - min(w, size)) // 2
    return left, top, left + min(w, size), top + min(h, size)


def to_column(ops: Sequence[Op], pixels: Column, h: int, w: int, mean: float, std: float) -> Column:
    """The values of a raster of h x w after `ops`; pointwise operators become one pass each, `fused` one for all."""
    for o in ops:
        h2, w2 = shape_after(o, h, w)
        if o.name == "resize":
            pixels = R.resize_nearest(pixels, h, w, h2, w2)
        elif o.name == "crop":
            pixels = R.crop(pixels, w, *centre(h, w, o.size))
        elif o.name == "cast":
            pixels = F.transform(pixels, lambda v: v.cast("double"))
        elif o.name == "normalise":
            pixels = R.normalised(pixels, [mean], [std])
        elif o.name == "reorder":
            pixels = R.channels_first(pixels, h2 * w2, 1)
        elif o.name == "fused":
            pixels = F.transform(pixels, lambda v: v * F.lit(1 / (255 * std)) + F.lit(-mean / std))
        h, w = h2, w2
    return pixels


def to_kernel(ops: Sequence[Op], h: int, w: int, mean: float, std: float) -> Callable[[np.ndarray], np.ndarray]:
    """The same on arrays (..., h, w) of many rasters; index maps of resizes and crops are made once."""
    todo: list[Callable[[np.ndarray], np.ndarray]] = []
    for o in ops:
        h2, w2 = shape_after(o, h, w)
        if o.name == "resize":
            rows, cols = (np.floor((np.arange(m) + 0.5) * n / m).astype(int) for n, m in ((h, h2), (w, w2)))
            todo.append(lambda x, rows=rows, cols=cols: x[..., rows[:, None], cols[None, :]])
        elif o.name == "crop":
            left, top, right, bottom = centre(h, w, o.size)
            todo.append(lambda x, box=(left, top, right, bottom): x[..., box[1] : box[3], box[0] : box[2]])
        elif o.name == "cast":
            todo.append(lambda x: x.astype(np.float64))
        elif o.name == "normalise":
            todo.append(lambda x: (x / 255.0 - mean) / std)
        elif o.name == "reorder":
            todo.append(np.ascontiguousarray)  # one channel: the order is the same
        elif o.name == "fused":
            todo.append(lambda x: x * (1 / (255 * std)) + (-mean / std))
        h, w = h2, w2

    def run(x: np.ndarray) -> np.ndarray:
        for f in todo:
            x = f(x)
        return x

    return run
