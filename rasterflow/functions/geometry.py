"""Where pixels are: resized sizes, crops mapped back to the source, block-aligned regions."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def resized(h: Column, w: Column, short: Column) -> tuple[Column, Column]:
    """Height and width once the short side is `short`, halves up."""
    s = F.least(h, w)
    return F.floor(h * short / s + 0.5), F.floor(w * short / s + 0.5)


def center_crop_source(h: Column, w: Column, short: Column, crop: Column) -> dict[str, Column]:
    """Source rectangle of the centre crop that is taken after the resize."""
    rh, rw = resized(h, w, short)
    scale = F.least(h, w) / short
    left, top = F.floor((rw - crop) / 2), F.floor((rh - crop) / 2)
    zero = F.lit(0).cast("long")
    return {
        "left": F.greatest(zero, F.floor(left * scale)),
        "top": F.greatest(zero, F.floor(top * scale)),
        "right": F.least(w.cast("long"), F.ceil((left + crop) * scale)),
        "bottom": F.least(h.cast("long"), F.ceil((top + crop) * scale)),
    }


def aligned(roi: dict[str, Column], h: Column, w: Column, block: int = 8) -> dict[str, Column]:
    """The region widened to whole blocks, within the padded image."""
    up = lambda v: F.ceil(v / block) * block
    return {"left": F.floor(roi["left"] / block) * block, "top": F.floor(roi["top"] / block) * block, "right": F.least(up(w), up(roi["right"])), "bottom": F.least(up(h), up(roi["bottom"]))}


def block_share(region: dict[str, Column], h: Column, w: Column, block: int = 8) -> Column:
    """Blocks of an aligned region over all blocks."""
    return ((region["right"] - region["left"]) / block) * ((region["bottom"] - region["top"]) / block) / (F.ceil(w / block) * F.ceil(h / block))
