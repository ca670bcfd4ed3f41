"""Randomness that any engine and any retry repeats: md5 over seed, stream and ids, compared as text."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash_hex(seed: int | str, stream: str, *ids: Column) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(stream), *[i.cast("string") for i in ids]).cast("binary"))


def hash_int(seed: int | str, stream: str, *ids: Column, digits: int = 7) -> Column:
    """A whole number below 16**digits."""
    return F.conv(F.substring(hash_hex(seed, stream, *ids), 1, digits), 16, 10).cast("long")


def hex_cut(share: float, digits: int = 8) -> str:
    """Hashes below this text are a share of all."""
    if not 0 <= share <= 1:
        raise ValueError("a share lies between 0 and 1")
    return "g" if share == 1 else f"{int(share * 16**digits):0{digits}x}"
