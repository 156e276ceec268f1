"""Counter-based random numbers: a function of a key, not of partitions or retries.

The same number is available in SQL as ``conv(substr(md5(key), 1, 13), 16, 10) / 2**52``.
"""

from __future__ import annotations

from hashlib import md5

from pyspark.sql import Column
from pyspark.sql import functions as F

_SPAN = float(1 << 52)


def uniform(*key) -> float:
    return int(md5("|".join(map(str, key)).encode()).hexdigest()[:13], 16) / _SPAN


def uniform_column(*key) -> Column:
    parts = [k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in key]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 13), 16, 10).cast("double") / F.lit(_SPAN)
