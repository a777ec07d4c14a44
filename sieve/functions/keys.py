"""Keys of any type to 64-bit words, and the portable hash that SQL engines share."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.functions.hashing import murmur, shift_right

FAMILIES = ("xxhash64", "murmur64", "md5")


def _all_there(cols: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, [c.isNotNull() for c in cols])


def key64(*cols: str | Column, family: str = "xxhash64") -> Column:
    """A 64-bit key of one or more columns; null if any of them is null.

    xxhash64 stays in generated code. md5 keeps 60 bits that any engine can
    recompute. murmur64 runs the murmur finaliser in numpy over xxhash64's value.
    """
    cs = [F.col(c) if isinstance(c, str) else c for c in cols]
    if family == "xxhash64":
        value = F.xxhash64(*cs)
    elif family == "md5":
        value = portable("", F.concat_ws("|", *[c.cast("string") for c in cs]))
    elif family == "murmur64":
        value = _murmur()(F.xxhash64(*cs))
    else:
        raise ValueError(f"unknown hash family {family}")
    return F.when(_all_there(cs), value)


def _murmur():
    @F.pandas_udf("bigint")
    def mixed(x: pd.Series) -> pd.Series:
        return pd.Series(murmur(x.to_numpy(np.int64).view(np.uint64), 42).view(np.int64))

    return mixed


def shard(key: Column, bits: Column | int) -> Column:
    """The high bits of a key; a shift by 64 would be a shift by 0 on the JVM."""
    width = F.lit(63) - bits if isinstance(bits, Column) else 63 - bits
    return shift_right(shift_right(key, 1), width).cast("int")


def with_key(df: DataFrame, cols: list[str], bits: int, family: str = "xxhash64") -> DataFrame:
    """Adds ``key64`` and ``shard``; nothing is dropped."""
    return df.withColumn("key64", key64(*cols, family=family)).withColumn("shard", shard(F.col("key64"), bits))


def portable(tag: str, x: Column, first: int = 1) -> Column:
    """15 hex digits of md5(tag:x) from digit ``first`` as a bigint below 2**60."""
    text = F.concat(F.lit(f"{tag}:"), x.cast("string"))
    return F.conv(F.substring(F.md5(text), first, 15), 16, 10).cast("bigint")
