"""The index for SQL users: views and functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@F.pandas_udf("long")
def hub_distance(hubs_a: pd.Series, dists_a: pd.Series, hubs_b: pd.Series, dists_b: pd.Series) -> pd.Series:
    """Least sum over shared hubs of two packed labels; null without one. A batch is one merge of all its rows' entries."""
    flat = lambda x: np.concatenate([np.asarray(v, np.int64) for v in x if v is not None] or [np.zeros(0, np.int64)])

    def side(hubs, dists):
        n = np.array([0 if v is None else len(v) for v in hubs], np.int64)
        return pd.DataFrame({"row": np.repeat(np.arange(len(n)), n), "hub": flat(hubs), "dist": flat(dists)})

    both = side(hubs_a, dists_a).merge(side(hubs_b, dists_b), on=["row", "hub"])
    best = (both["dist_x"] + both["dist_y"]).groupby(both["row"]).min()
    return best.reindex(range(len(hubs_a))).astype("Int64")


@F.udtf(returnType="hub: bigint, dist: bigint")
class LabelEntries:
    """Table function: the entries of one packed label, for SQL joins by hub."""

    def eval(self, hubs, dists):
        for h, d in zip(hubs or (), dists or (), strict=True):
            yield int(h), int(d)


@F.pandas_udf("long")
def least_sum(a: pd.Series, b: pd.Series) -> int:
    """Grouped aggregate: the least sum of two columns, as ``min(a + b)`` gives it without Python."""
    return int((a + b).min())


def register(spark: SparkSession, packed: DataFrame, view: str = "labels_packed") -> None:
    """View of packed labels and the functions ``hub_distance``, ``least_sum`` and ``label_entries`` in the session."""
    packed.createOrReplaceTempView(view)
    spark.udf.register("hub_distance", hub_distance)
    spark.udf.register("least_sum", least_sum)
    spark.udtf.register("label_entries", LabelEntries)
