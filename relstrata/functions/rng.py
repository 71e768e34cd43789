"""Counter-hash uniforms: a draw depends on its key alone, not on partitions or retries."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _text(part) -> Column:
    return part.cast("string") if isinstance(part, Column) else F.lit(str(part))


def uniform_md5(*parts) -> Column:
    """First 13 hex digits of the md5 of the |-joined key over 2**52; DuckDB gives the same double."""
    key = F.md5(F.concat_ws("|", *map(_text, parts)))
    return F.conv(F.substring(key, 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def uniform_md5_py(*parts) -> float:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) / 2**52


def uniform_xx(*parts) -> Column:
    """The fast form: 53 bits of xxhash64."""
    bits = F.shiftrightunsigned(F.xxhash64(*(p if isinstance(p, Column) else F.lit(p) for p in parts)), 11)
    return bits.cast("double") / F.lit(float(2**53))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser; wraps."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def uniform_np(*parts) -> np.ndarray:
    """Vector form for kernels; parts are integers or integer arrays that broadcast."""
    h = np.zeros((), np.uint64)
    with np.errstate(over="ignore"):
        for p in parts:
            h = mix((h + np.uint64(0x9E3779B97F4A7C15)) ^ np.asarray(p).astype(np.int64).view(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    return (h >> np.uint64(11)).astype(float) / 2.0**53
