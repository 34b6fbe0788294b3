"""Blocking keys as columns. A null key is the lowest key, the empty string."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, functions as F


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def prefix_key(c: Column | str, chars: int = 2) -> Column:
    return F.coalesce(F.lower(F.substring(_col(c), 1, chars)), F.lit(""))


def concat_prefix_key(parts: list[tuple[Column | str, int]], sep: str = "") -> Column:
    return F.concat_ws(sep, *(prefix_key(c, n) for c, n in parts))


def attribute_key(c: Column | str) -> Column:
    return F.coalesce(_col(c).cast("string"), F.lit(""))


def composite_key(*cols: Column | str) -> Column:
    return F.concat_ws("/", *(attribute_key(c) for c in cols))


def initials_year_key(names: Column | str, year: Column | str) -> Column:
    """First letters of the names (an array, or a text split at spaces) and the year."""
    names = _col(names)
    return F.concat(F.coalesce(F.array_join(F.transform(names, lambda n: F.upper(F.substring(n, 1, 1))), ""), F.lit("")), F.coalesce(_col(year).cast("string"), F.lit("")))


def ordinal_key(c: Column | str) -> Column:
    """A numeric or date key as a bigint that sorts alike; dates count days, null is lowest."""
    c = _col(c)
    return F.coalesce(F.try_to_number(c.cast("string"), F.lit("S999999999999999999")).cast("long"), F.lit(-(1 << 63)))


def date_key(c: Column | str) -> Column:
    return F.coalesce(F.unix_date(_col(c).cast("date")).cast("long"), F.lit(-(1 << 63)))


def suffix_key(c: Column | str, chars: int = 3) -> Column:
    return F.coalesce(F.lower(F.right(_col(c), F.lit(chars))), F.lit(""))


def soundex_key(c: Column | str) -> Column:
    return F.coalesce(F.soundex(_col(c)), F.lit(""))


def host_key(c: Column | str) -> Column:
    return F.coalesce(F.lower(F.try_parse_url(_col(c), F.lit("HOST"))), F.lit(""))


@dataclass(frozen=True)
class KeySet:
    """One key a pass."""

    keys: tuple[Column, ...]
