"""Storage of the library, under the name that this subpackage uses, and frames whose columns may have any names."""

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.storage import Settled, folder, pieced, settle, settle_last

__all__ = ["Settled", "folder", "pieced", "renamed", "settle", "settle_last", "small"]
#: A table of at most so many bytes is broadcast; a larger one is joined by shuffle.
BROADCAST_BYTES = 16 << 20


def renamed(df: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """df under column names that nothing else uses, and the new name of each: inner columns can then clash with none."""
    names = {c: f"__in{i}" for i, c in enumerate(df.columns)}
    return df.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()]), names


def small(table: DataFrame, bytes_of_row: Column) -> DataFrame:
    """A written table, marked for broadcast if its rows are known to have few bytes together."""
    total = table.agg(F.sum(bytes_of_row)).first()[0] or 0
    return F.broadcast(table) if total <= BROADCAST_BYTES else table
