"""A caller's columns in one struct, so that no name an operator uses clashes with them."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class Packed:
    """The columns of a table, but for ``replaced`` ones, in a struct named ``row``, beside those an operator works on.

    ``apart`` names the latter; ``extra`` columns are computed from the table as it was.
    """

    def __init__(self, df: DataFrame, replaced: Iterable[str] = (), apart: Iterable[str] = (), extra: Iterable[Column] = ()) -> None:
        gone, self._apart = set(replaced), tuple(apart)
        self._names = [name for name in df.columns if name not in gone]
        quoted = {name: F.col("`" + name.replace("`", "``") + "`") for name in self._names}
        inside = [quoted[name] for name in self._names if name not in self._apart]
        self.rows = df.select((F.struct(*inside) if inside else F.lit(0)).alias("row"), *[quoted[name] for name in self._apart], *extra)

    def back(self, *without: str) -> list[Column]:
        """The columns as they were."""
        return [F.col(name) if name in self._apart else F.col("row").getField(name).alias(name) for name in self._names if name not in without]


def text_key(text: Column) -> Column:
    """Tells rows of one doc_id with different texts apart."""
    return F.xxhash64(F.coalesce(text.cast("string"), F.lit("")))
