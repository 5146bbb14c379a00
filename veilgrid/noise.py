"""Uniform numbers for reports.

'secure' draws from the operating system in Python workers, 'rand' uses Spark's generator, 'hash' derives them from a
seed and the user's id. Hash draws can be replayed by whoever knows the seed, so they protect nobody: they
are for tests and comparisons and must be asked for.
"""

from __future__ import annotations

import math
import os

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: 13 hexadecimal digits.
SPAN = float(1 << 52)


def hash_uniform(user: Column, draw: int | Column, seed: int = 42) -> Column:
    """The first 13 digits of md5('seed:user:draw') over 2^52."""
    draw = draw if isinstance(draw, Column) else F.lit(draw)
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), user.cast("string"), draw.cast("string")).cast("binary"))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long").cast("double") / F.lit(SPAN)


def hash_limit(p: float) -> Column:
    """The digits that the draws below p stay under, as text; draws are compared by their digits and never parsed."""
    return F.lit(f"{min(math.ceil(p * SPAN), (1 << 52) - 1):013x}" if p < 1 else "g")


def hash_below(user: Column, draw: Column, limit: Column, seed: int = 42) -> Column:
    """hash_uniform(user, draw, seed) < p for the limit of p."""
    return F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), user.cast("string"), draw.cast("string")).cast("binary")), 1, 13) < limit


def _secure_uniform(like: Column) -> Column:
    @F.pandas_udf("double")
    def draw(ids):
        bits = np.frombuffer(os.urandom(8 * len(ids)), dtype="<u8") >> np.uint64(11)
        return ids.__class__(bits.astype(np.float64) / float(1 << 53))

    return draw.asNondeterministic()(like)


def uniform_columns(df: DataFrame, names: list[str], mode: str = "secure", user: str = "user_id", seed: int | None = None, unsafe_deterministic: bool = False) -> DataFrame:
    """Adds named uniform columns in one projection, so that no later expression draws them twice."""
    if mode == "hash":
        if not unsafe_deterministic:
            raise ValueError("hash draws can be replayed: pass unsafe_deterministic=True for tests")
        return df.withColumns({n: hash_uniform(F.col(user), k, 42 if seed is None else seed) for k, n in enumerate(names)})
    if mode == "rand":
        return df.withColumns({n: F.rand() if seed is None else F.rand(seed + k) for k, n in enumerate(names)})
    if mode == "secure":
        return df.withColumns({n: _secure_uniform(F.col(df.columns[0])) for n in names})
    raise ValueError("mode is secure, rand or hash")
