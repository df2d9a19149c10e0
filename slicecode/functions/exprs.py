"""Column expressions used all over: months, symbols, exact costs."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The calendar: 83 months from 2017-01; the testing period begins with month 72 (2023-01).
MONTHS, TEST_FROM, MICRO = 83, 72, 1_000_000


def month_index(ident: Column) -> Column:
    """Month of a row without a date: its id modulo the (prime) number of months."""
    return F.pmod(ident, F.lit(MONTHS)).cast("int")


def month_date(index: Column) -> Column:
    return F.add_months(F.lit("2017-01-01").cast("date"), index)


def month_of_date(day: Column, shift_years: int = 22) -> Column:
    """Month index of a dated row whose calendar lies ``shift_years`` before ours."""
    return ((F.year(day) + shift_years - 2017) * 12 + F.month(day) - 1).cast("int")


def month_label(index: Column) -> Column:
    return F.date_format(month_date(index), "yyyy-MM")


def byte_symbols(text: Column) -> Column:
    """The UTF-8 bytes as an array of two-digit hexadecimals; one linear pass, unlike substring by position."""
    return F.regexp_extract_all(F.hex(F.encode(text, "UTF-8")), F.lit(".."), F.lit(0))


def char_symbols(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def word_symbols(text: Column) -> Column:
    """Runs of letters and digits, single other characters, single white space: lossless."""
    return F.regexp_extract_all(text, F.lit(r"[\p{L}\p{N}]+|[^\p{L}\p{N}\s]|\s"), F.lit(0))


def micro_bits(p: Column) -> Column:
    """-log2 p in whole millionths of a bit, so that sums do not depend on their order."""
    return F.round(-F.log2(p) * MICRO).cast("long")


def bits(total: Column) -> Column:
    return F.round(total / MICRO, 3)


def rate(total_micro: Column, raw_bytes: Column) -> Column:
    """Compressed size in percent of the raw size; null where there is nothing to compress. Not clipped at 100."""
    return F.round(F.try_divide(F.lit(100.0) * total_micro / MICRO, F.lit(8.0) * raw_bytes), 4)


def least_bits(p: float) -> int:
    """The ideal upper bound of a message's code length."""
    return math.ceil(-math.log2(p)) + 1
