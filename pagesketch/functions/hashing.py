"""Item keys and hash families as native column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from pagesketch.config import PageGeometry, SketchConfig

#: A prime under 2^31 for the affine family.
PRIME = (1 << 31) - 1
INTEGERS = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


def fingerprint(text: Column, mode: str = "portable") -> Column:
    """A BIGINT for a string or binary: 60 bits of md5 (portable to other engines) or xxHash64 (fast)."""
    if mode == "fast":
        return F.xxhash64(text)
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("bigint")


def as_text(col: Column, kind: T.DataType) -> Column:
    """A canonical string of a value; -0.0 is 0.0 and all NaN are one."""
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        col = F.when(F.isnan(col), F.lit(float("nan"))).when(col == 0, F.lit(0.0)).otherwise(col)
    if isinstance(kind, T.ArrayType):
        return F.array_join(F.transform(col, lambda x: prefixed(as_text(x, kind.elementType))), "")
    if isinstance(kind, T.StructType):
        return F.concat(*(prefixed(as_text(col[f.name], f.dataType)) for f in kind.fields))
    if isinstance(kind, T.MapType):
        raise TypeError("a map has no canonical order and cannot be an item")
    return col.cast("string")


def prefixed(text: Column) -> Column:
    """length:text, so that concatenations of different parts never agree."""
    return F.coalesce(F.concat(F.length(text).cast("string"), F.lit(":"), text), F.lit("n"))


def item_key(df: DataFrame, *names: str, mode: str = "portable") -> Column:
    """The BIGINT key of an item that one or several columns make up; null if a single column is null.

    Integers are themselves, dates days, timestamps microseconds, decimals up to 18 digits their unscaled value;
    all else is a fingerprint.
    """
    if len(names) > 1:
        kinds = [(F.col(n), df.schema[n].dataType) for n in names]
        return fingerprint(F.concat(*(prefixed(as_text(c, k)) for c, k in kinds)), mode)
    col, kind = F.col(names[0]), df.schema[names[0]].dataType
    if isinstance(kind, INTEGERS):
        return col.cast("bigint")
    if isinstance(kind, T.DateType):
        return F.unix_date(col).cast("bigint")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(col)
    if isinstance(kind, T.DecimalType) and kind.precision <= 18:
        return (col * F.lit(10**kind.scale)).cast("bigint")
    return fingerprint(as_text(col, kind), mode)


def hash_cell(key: Column, i: int, width: Column | int, family: str = "murmur32") -> Column:
    """Member i of a hash family over [0, width)."""
    width = F.lit(width) if isinstance(width, int) else width
    if family in ("murmur32", "portable"):
        return F.pmod(F.hash(F.lit(i), key), width.cast("bigint"))
    if family == "xx64":
        return F.pmod(F.xxhash64(F.lit(i), key), width.cast("bigint"))
    a, b = affine_terms(i)
    return F.pmod((F.pmod(key, F.lit(PRIME)) * F.lit(a) + F.lit(b)) % F.lit(PRIME), width.cast("bigint"))


def affine_terms(i: int) -> tuple[int, int]:
    """Multiplier and addend of member i, drawn by a fixed congruential rule."""
    x = (i + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1
    x = x * 0xD1342543DE82EF95 + 1 & (1 << 64) - 1
    return 1 + (x >> 33) % (PRIME - 1), (x >> 7) % PRIME


def flat_columns(key: Column, cfg: SketchConfig) -> list[Column]:
    """Column of the key in each row of a flat sketch."""
    return [hash_cell(key, cfg.seed_base + 1 + i, cfg.width, cfg.flat_family) for i in range(cfg.depth)]


def page_of(key: Column, geom: PageGeometry) -> Column:
    return hash_cell(key, geom.cfg.seed_base, geom.pages, geom.family)


def first_column(page: Column, geom: PageGeometry) -> Column:
    """Number of columns before a page."""
    if geom.mode == "aligned":
        return page * F.lit(geom.columns)
    return F.floor(page * F.lit(geom.cells) / F.lit(geom.cfg.depth)).cast("bigint")


def page_width(page: Column, geom: PageGeometry) -> Column:
    if geom.mode == "aligned":
        return F.lit(geom.columns)
    return first_column(page + F.lit(1), geom) - first_column(page, geom)


def page_columns(key: Column, page: Column, geom: PageGeometry) -> list[Column]:
    """Column of the key inside its page, in each row."""
    width = page_width(page, geom)
    return [hash_cell(key, geom.cfg.seed_base + 1 + i, width, geom.family) for i in range(geom.cfg.depth)]


def address(row: Column, col: Column, layout: str, width: int, depth: int) -> Column:
    """Counter number of a flat cell, rows first or columns first."""
    return row * F.lit(width) + col if layout == "row" else col * F.lit(depth) + row


def page_address(page: Column, row: Column, col: Column, geom: PageGeometry) -> Column:
    """Counter number of a paged cell."""
    if geom.mode == "aligned":
        return page * F.lit(geom.cells) + col * F.lit(geom.cfg.depth) + row
    return (first_column(page, geom) + col) * F.lit(geom.cfg.depth) + row


def block_of(addr: Column, geom_or_cells: PageGeometry | int) -> Column:
    cells = geom_or_cells if isinstance(geom_or_cells, int) else geom_or_cells.cells
    return F.floor(addr / F.lit(cells)).cast("bigint")
