"""Join keys of one common type, and the hashes of the draws and filters."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def one_key(c: Column, kind: T.DataType) -> Column:
    """Whole numbers as bigint, doubles with one NaN and one zero, decimals at one scale, all else as it is; maps are refused."""
    if isinstance(kind, T.MapType):
        raise TypeError("a map can't be a join key")
    if isinstance(kind, T.StringType) and getattr(kind, "collationId", 0):
        raise TypeError("a string key needs the binary collation")
    if isinstance(kind, T.ByteType | T.ShortType | T.IntegerType | T.LongType):
        return c.cast("bigint")
    if isinstance(kind, T.FloatType | T.DoubleType):
        d = c.cast("double")
        return F.when(F.isnan(d), F.lit(float("nan"))).when(d == 0, F.lit(0.0)).otherwise(d)
    return c.cast("decimal(38,6)") if isinstance(kind, T.DecimalType) else c


def join_key(columns: Sequence[Column], kinds: Sequence[T.DataType]) -> Column:
    """One column: the key itself, or a struct of several; null if any of them is."""
    parts = [one_key(c, k) for c, k in zip(columns, kinds, strict=True)]
    if len(parts) == 1:
        return parts[0]
    whole = F.struct(*(p.alias(f"k{i}") for i, p in enumerate(parts)))
    missing = parts[0].isNull()
    for p in parts[1:]:
        missing = missing | p.isNull()
    return F.when(~missing, whole)


def text_hash(*parts: Column | str | int) -> Column:
    """A hash that any engine can repeat: the first 60 bits of the MD5 of the parts, joined by a bar."""
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *(c.cast("string") for c in cols)).cast("binary")), 1, 15), 16, 10).cast("bigint")


def key_text(kind: T.DataType) -> Column:
    return F.concat_ws(",", *(F.col(f"jk.{f.name}").cast("string") for f in kind.fields)) if isinstance(kind, T.StructType) else F.col("jk").cast("string")


def draw_hash(key: Column, draw: Column, side: int, seed: int, family: str = "xx") -> Column:
    """Not negative. family: xx is fast, portable can be replayed by other engines."""
    if family == "portable":
        return text_hash(key, draw, side, seed)
    return F.pmod(F.xxhash64(key, draw, F.lit(side), F.lit(seed)), F.lit(1 << 60))
