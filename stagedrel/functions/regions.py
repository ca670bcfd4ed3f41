"""Object crops: a box out of a square grid of cells, pooled means, and substrings of pages as another carrier."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def crop_region(grid: Column, x0: Column, y0: Column, w: int = 4, h: int = 4, width: int = 8) -> Column:
    """The w x h cells of the box, row by row."""
    rows = F.array(*[F.lit(i) for i in range(h)])
    return F.flatten(F.transform(rows, lambda i: F.slice(grid, (y0 + i) * width + x0 + 1, w)))


def block_mean(grid: Column, row: int, col: int, width: int) -> Column:
    """Mean of the 2 x 2 block, added in a fixed order so that every engine rounds alike."""
    at = [row * width + col, row * width + col + 1, (row + 1) * width + col, (row + 1) * width + col + 1]
    a, b, c, d = (F.get(grid, F.lit(i)) for i in at)
    return (a + b + c + d) / 4


def pool(grid: Column, width: int) -> Column:
    """Means of all 2 x 2 blocks, row by row."""
    return F.array(*[block_mean(grid, r, c, width) for r in range(0, width, 2) for c in range(0, width, 2)])


def crop_text(html: Column, start: Column, end: Column) -> Column:
    return F.substring(html, start + 1, end - start)
