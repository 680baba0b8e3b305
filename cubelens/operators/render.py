"""Pictures as PNG bytes, for the images chosen to be seen."""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubelens.functions.intensity import IMAGE


def png(rgb: np.ndarray) -> bytes:
    """An 8-bit RGB picture (height, width, 3) as a PNG file."""
    h, w, _ = rgb.shape

    def chunk(kind: bytes, data: bytes) -> bytes:
        return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))

    raw = np.zeros((h, 1 + 3 * w), np.uint8)
    raw[:, 1:] = rgb.reshape(h, 3 * w)
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", w, h, 8, 2, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(raw.tobytes(), 6)) + chunk(b"IEND", b"")


def picture(x, y, r, g, b, bins: int, scale: int = 1) -> np.ndarray:
    """Cells as pixels, y upwards; absent cells are blue (nothing where something was expected)."""
    out = np.zeros((bins, bins, 3))
    out[..., 2] = 1.0
    out[bins - 1 - np.asarray(y), np.asarray(x)] = np.column_stack([r, g, b])
    out = np.clip(np.round(out * 255), 0, 255).astype(np.uint8)
    return out.repeat(scale, 0).repeat(scale, 1)


def render_png(pixels: DataFrame, bins: int, scale: int = 1) -> DataFrame:
    """(xdim, ydim, zdim, slab, width, height, png): one task holds one image's bins x bins cells."""

    def draw(pdf: pd.DataFrame) -> pd.DataFrame:
        p = picture(pdf.x, pdf.y, pdf.r, pdf.g, pdf.b, bins, scale)
        return pd.DataFrame({**{k: [pdf[k].iloc[0]] for k in IMAGE}, "width": [p.shape[1]], "height": [p.shape[0]], "png": [png(p)]})

    return pixels.groupBy(*IMAGE).applyInPandas(draw, "xdim string, ydim string, zdim string, slab int, width int, height int, png binary")


def montage(pixels: DataFrame, bins: int, gap: int = 2) -> DataFrame:
    """The slabs of each (xdim, ydim, zdim) side by side."""

    def draw(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = []
        for _, one in pdf.sort_values("slab").groupby("slab"):
            parts += [picture(one.x, one.y, one.r, one.g, one.b, bins), np.full((bins, gap, 3), 255, np.uint8)]
        p = np.concatenate(parts[:-1], 1)
        return pd.DataFrame({**{k: [pdf[k].iloc[0]] for k in IMAGE[:3]}, "width": [p.shape[1]], "height": [p.shape[0]], "png": [png(p)]})

    return pixels.groupBy(*IMAGE[:3]).applyInPandas(draw, "xdim string, ydim string, zdim string, width int, height int, png binary")
