"""Columns that the text operators share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def text_bytes(column: str = "text") -> Column:
    """A text as UTF-8 bytes, empty for null."""
    return F.coalesce(F.col(column).cast("binary"), F.lit(b"")).alias(column)
