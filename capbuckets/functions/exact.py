"""Column helpers for whole-number arithmetic and for randomness that any engine can repeat."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def div(a: Column, b: Column | int) -> Column:
    """Integer quotient, as bigint; operands must not be negative."""
    return F.call_function("div", a, b if isinstance(b, Column) else F.lit(b))


def ceil_div(a: Column, b: Column | int) -> Column:
    """Smallest whole number not under a / b, for a >= 0 and b > 0."""
    b = b if isinstance(b, Column) else F.lit(b)
    return div(a + b - 1, b)


def quota(size: Column, num: Column, den: Column) -> Column:
    """Most copies of a value in one bucket of ``size``: floor(size * num / den), exactly."""
    return F.least(size.cast("bigint"), div(size.cast("bigint") * num, den))


def order_key(salt: str, *keys: Column) -> Column:
    """md5 of the salt and the keys: a repeatable shuffle of rows that follows from their values alone."""
    return F.md5(F.concat_ws("|", F.lit(salt), *[k.cast("string") for k in keys]))


def uniform(salt: str, *keys: Column) -> Column:
    """A number in (0, 1) from the first 13 hexadecimal digits of :func:`order_key`."""
    return (F.conv(F.substring(order_key(salt, *keys), 1, 13), 16, 10).cast("bigint") + 0.5) / float(1 << 52)


def pick(salt: str, below: int, *keys: Column) -> Column:
    """A repeatable whole number from 0 to ``below`` - 1."""
    return F.pmod(F.conv(F.substring(order_key(salt, *keys), 1, 13), 16, 10).cast("bigint"), F.lit(below))
