"""Values as unsigned numbers of few bits, and back."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass
class Codec:
    width: int
    encode: Callable[[Column], Column]
    decode: Callable[[Column], Column]


def bit() -> Codec:
    return Codec(1, lambda c: c.cast("int").cast("bigint"), lambda c: c.cast("int"))


def offset(low: int, width: int, kind: str = "int") -> Codec:
    return Codec(width, lambda c: c.cast("bigint") - low, lambda c: (c + low).cast(kind))


def dictionary(df: DataFrame, column: str, most: int = 1 << 16) -> Codec:
    """The distinct values in order; more than ``most`` are refused, since they go into the plan."""
    values = [r[0] for r in df.select(column).distinct().filter(F.col(column).isNotNull()).limit(most + 1).collect()]
    if len(values) > most:
        raise ValueError(f"{column} has more than {most} values")
    values.sort()
    array = F.array(*[F.lit(v) for v in values]) if values else F.array(F.lit(None).cast("string"))
    return Codec(max(1, (len(values) - 1).bit_length()), lambda c: F.array_position(array, c) - 1, lambda c: F.try_element_at(array, (c + 1).cast("int")))


def decimal(scale: int, width: int) -> Codec:
    return Codec(width, lambda c: F.round(c * 10**scale).cast("bigint"), lambda c: F.round(c / 10**scale, scale))


def days(width: int = 15) -> Codec:
    return Codec(width, lambda c: F.unix_date(c.cast("date")).cast("bigint"), lambda c: F.date_from_unix_date(c.cast("int")))


def pair(a: Codec, b: Codec) -> tuple[int, Callable[[Column, Column], Column], Callable[[Column], tuple[Column, Column]]]:
    """(width, encode, decode) of two values in one number."""
    shift = F.lit(1 << b.width)
    return a.width + b.width, lambda x, y: a.encode(x) * shift + b.encode(y), lambda c: (a.decode(F.floor(c / shift).cast("bigint")), b.decode(F.pmod(c, shift)))
