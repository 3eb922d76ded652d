"""Total orders over columns of a frame: as one ascending struct, as sort expressions, and as fields that are never null."""

from __future__ import annotations

import base64
import datetime
import decimal
import json
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SortKey:
    name: str
    desc: bool = False
    nulls_first: bool = True


def _clock(name: str) -> Column:
    """Microseconds of a timestamp without time zone, whatever the session's zone."""
    c = F.col(name)
    seconds = F.unix_date(c.cast("date")).cast("long") * 86400 + F.hour(c) * 3600 + F.minute(c) * 60
    return seconds * 1_000_000 + (F.date_part(F.lit("SECONDS"), c) * 1_000_000).cast("long")


def _value(df: DataFrame, key: SortKey) -> tuple[Column, str]:
    """A column that rises as the key does, and its type: times are whole numbers, a negative zero is a zero."""
    kind, c = dict(df.dtypes)[key.name], F.col(key.name)
    if kind.startswith(("map", "variant")):
        raise TypeError(f"{key.name}: {kind} has no order")
    if kind in ("double", "float"):
        c = F.when(c == 0, F.lit(0.0).cast(kind)).otherwise(c)
    elif kind == "timestamp_ntz":
        kind, c = "bigint", _clock(key.name)
    elif kind == "timestamp":
        kind, c = "bigint", F.unix_micros(c)
    elif kind == "date":
        kind, c = "int", F.unix_date(c)
    if key.desc:
        if kind == "boolean":
            c = ~c
        elif kind.startswith(("bigint", "int", "smallint", "tinyint", "double", "float", "decimal")):
            c = -c
        else:
            raise TypeError(f"{key.name}: descending order needs a number, time or boolean, not {kind}")
    return c, kind


def _ascending(df: DataFrame, key: SortKey) -> list[Column]:
    empty = F.col(key.name).isNull()
    return [(~empty if key.nulls_first else empty), _value(df, key)[0]]


def parse(keys: list[str | SortKey]) -> list[SortKey]:
    """Names, with a leading minus for descending."""
    return [k if isinstance(k, SortKey) else SortKey(k.lstrip("-"), k.startswith("-")) for k in keys]


def total_order_key(df: DataFrame, keys: list[str | SortKey]) -> Column:
    """A struct that orders rows as the keys do: nulls by choice, NaN last, negative zero as zero."""
    cols = [c for k in parse(keys) for c in _ascending(df, k)]
    return F.struct(*[c.alias(f"c{i}") for i, c in enumerate(cols)])


def order_by(df: DataFrame, keys: list[str | SortKey]) -> list[Column]:
    """The same order as sort expressions; ascending keys are plain columns."""
    out = []
    for k in parse(keys):
        c = _value(df, k)[0] if k.desc else F.col(k.name)
        out.append(c.asc_nulls_first() if k.nulls_first else c.asc_nulls_last())
    return out


def fields(df: DataFrame, keys: list[str | SortKey]) -> list[tuple[Column, str, bool]]:
    """The same order as columns to compare one after another, none of them null: (column, type, whether a null flag).

    Each key is a flag for its nulls, then its value, with a fixed value in the place of a null.
    """
    out = []
    for k in parse(keys):
        c, kind = _value(df, k)
        if kind.startswith(("array", "struct")):
            raise TypeError(f"{k.name}: name the parts of a {kind} as keys of their own")
        flag = F.col(k.name).isNull()
        out += [(~flag if k.nulls_first else flag, "boolean", True), (F.coalesce(c, F.lit("" if kind in ("string", "binary") else 0).cast(kind)), kind, False)]
    return out


def _plain(value):
    if isinstance(value, decimal.Decimal):
        return str(value)
    if isinstance(value, (bytes, bytearray)):
        return base64.b64encode(value).decode()
    if isinstance(value, (datetime.date, datetime.datetime)):
        return value.isoformat()
    return value


def array_literal(values: list, kind: str) -> Column:
    """A list as one array constant of the plan: read from text when the plan is optimised, one node whatever its length."""
    return F.from_json(F.lit(json.dumps([_plain(v) for v in values])), f"array<{kind}>")


def coin_of(columns: list[str], bound: Column | int, seed: int) -> Column:
    """A coin that is one hash of the columns: its upper 32 bits below a bound (`coin_limit` of a rate)."""
    return F.shiftrightunsigned(F.xxhash64(*columns, F.lit(seed)), 32) < bound


def coin_limit(rate: float) -> int:
    return min(max(int(rate * 2**32), 0), 2**32)


def portable_coin(columns: list[str], rate: float, seed: int) -> Column:
    """A coin of the given rate that any engine with MD5 tosses alike: eight hex digits of a digest below a bound.

    Integer and text columns only, whose text is the same everywhere.
    """
    return F.substring(F.md5(F.concat_ws("|", *[F.col(c).cast("string") for c in columns], F.lit(str(seed)))), 1, 8) < F.lit(coin_bound(rate))


def coin_bound(rate: float) -> str:
    return f"{min(max(int(rate * 2**32), 0), 2**32 - 1):08x}"


def portable_coin_sql(columns: list[str], rate: float, seed: int) -> str:
    return f"substr(md5(concat_ws('|', {', '.join(columns)}, '{seed}')), 1, 8) < '{coin_bound(rate)}'"
