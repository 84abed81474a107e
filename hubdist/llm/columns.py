"""Column names that a frame does not have yet."""

from __future__ import annotations

from pyspark.sql import DataFrame


def own_names(df: DataFrame, n: int) -> list[str]:
    """``n`` names free in ``df``, whatever it calls its columns; names are compared without case, as Spark does."""
    taken = {c.lower() for c in df.columns}
    return [x for k in range(n + len(taken)) if (x := f"_own{k}") not in taken][:n]
