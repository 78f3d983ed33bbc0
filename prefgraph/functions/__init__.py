"""Column functions shared by the operators."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Labels and widths are packed in one long, so that a minimum is a hash aggregation: least label first, then the greatest width.
#: Both are below TOP: ids are dense numbers, and widths are ranks of weights where weights themselves are not small whole numbers.
TOP = (1 << 31) - 1
NOTHING = TOP * (1 << 31) + TOP


def pack(label: Column, width: Column) -> Column:
    return label * F.lit(1 << 31) + (F.lit(TOP) - width)


def label_of(packed: Column) -> Column:
    return F.shiftright(packed, 31)


def width_of(packed: Column) -> Column:
    return F.lit(TOP) - packed.bitwiseAND(F.lit(TOP).cast("long"))


def path_width(widths: Column) -> Column:
    """The width of a path from the array of its edges' weights; null for none or a missing edge."""
    return F.when(F.exists(widths, lambda x: x.isNull()) | (F.size(widths) == 0), None).otherwise(F.array_min(widths))


def url_host(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-z]+://([^/:?#]+)", 1)
