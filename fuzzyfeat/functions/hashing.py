"""The hash that folds, splits and samples are made by: the first eight hex digits of md5."""

from pyspark.sql import Column
from pyspark.sql import functions as F


def h(salt: str, column: str | Column) -> Column:
    c = F.col(column) if isinstance(column, str) else column
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), c.cast("string"))), 1, 8), 16, 10).cast("long")
