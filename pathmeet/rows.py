"""Row numbers and column names that collide with nothing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathmeet.scratch import staged


def free_name(columns: list[str], name: str) -> str:
    """``name``, lengthened until no column is called so in any case."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def numbered(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """``df`` written once with a number of its own for each row, and the name of that column.

    The numbers are frozen by the write, so decisions made for them survive lost executors and repeated reads."""
    row = free_name(df.columns, "row_number")
    return staged(df.withColumn(row, F.monotonically_increasing_id()), name), row


def without_rows(df: DataFrame, gone: DataFrame, row: str) -> DataFrame:
    """The rows of a numbered table whose number is not in the written table ``gone``; the number goes too."""
    from pathmeet.joins import fits

    listed = gone.select(row)
    return df.join(F.broadcast(listed) if fits(listed) else listed, row, "left_anti").drop(row)
