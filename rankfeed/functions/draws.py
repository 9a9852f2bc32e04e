"""Reproducible draws from a seed string: the same value on every engine, task and retry."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def hex32(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint")


def uniform(text: Column) -> Column:
    return hex32(text) / F.lit(2.0**32)


def normal(text: Column) -> Column:
    radius = F.sqrt(-2 * F.log((hex32(F.concat(text, F.lit(":a"))) + 1) / F.lit(2.0**32 + 1)))
    return radius * F.cos(F.lit(2 * math.pi) * uniform(F.concat(text, F.lit(":b"))))
