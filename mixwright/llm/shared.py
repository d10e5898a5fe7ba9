"""Tables and files in the folder that all executors and the driver share."""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mixwright.functions.storage import checked, kept, lean, lean_cogroup, lean_group, release_memory, removed, scratch

folder = scratch
stored = kept
sized = checked


def dropped(*tables: DataFrame) -> None:
    """Delete stored tables that nothing reads any more."""
    for df in tables:
        removed(df.sparkSession, df.stored_at)


def free_names(df: DataFrame, *names: str) -> list[str]:
    """Working column names that the input does not have."""
    taken = {c.lower() for c in df.columns}
    out = []
    for n in names:
        while n.lower() in taken:
            n = "_" + n
        taken.add(n.lower())
        out.append(n)
    return out


#: Column of ``numbered``.
PLACE = "_n_place"


def numbered(df: DataFrame) -> DataFrame:
    """Append each row's place, from 0 and without gaps, in the order of its files' names and of the rows in them, however tasks read them.

    A table that is not read from Parquet files is stored first, as its partitions lie.
    """
    part, row, first, key = "_n_part", "_n_row", "_n_first", "_n_key"

    def with_rows(table: DataFrame) -> DataFrame:
        return table.withColumns({part: F.col("_metadata.file_name"), row: F.col("_metadata.row_index")})

    try:
        placed = with_rows(df)
        placed.schema  # noqa: B018  names are resolved here
    except AnalysisException:
        placed = with_rows(stored(df, "numbered"))
    files = placed.groupBy(F.col(part).alias(key)).agg(F.max(row).alias(row))
    upto = Window.orderBy(key).rowsBetween(Window.unboundedPreceding, -1)  # a row per file
    starts = files.select(key, F.coalesce(F.sum(F.col(row) + 1).over(upto), F.lit(0)).alias(first))
    return placed.join(F.broadcast(starts), F.col(part) == F.col(key)).withColumn(PLACE, (F.col(first) + F.col(row)).cast("long")).drop(part, row, first, key)


def id_name(id_col: str, *results: str) -> None:
    """A clear refusal of an id column that is named like a column of the result."""
    if id_col.lower() in results:
        raise ValueError(f"the id column may not be named {id_col}: the result has a column of that name")


__all__ = ["PLACE", "dropped", "folder", "free_names", "id_name", "lean", "lean_cogroup", "lean_group", "numbered", "release_memory", "sized", "stored"]
