"""A uniform number from an id that every SQL engine can repeat, for splits, folds, samples and coins."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def draw(key: Column, seed: str = "") -> Column:
    """In [0, 1): the first 32 bits of the MD5 of the key's text and a seed."""
    digest = F.md5(F.concat(key.cast("string"), F.lit(f"|{seed}")))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def draw_sql(key: str, seed: str = "") -> str:
    return f"(('0x' || substr(md5({key}::VARCHAR || '|{seed}'), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"
