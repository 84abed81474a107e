"""The index on disk: files clustered by vertex, with a manifest."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_index(labels: DataFrame, path: str, bp: DataFrame | None = None, files: int | None = None) -> None:
    """Labels range-partitioned and sorted by vertex, so that a point query's filter skips all but its row groups; ``hub_band`` serves prefix reads."""
    n = files or int(labels.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    banded = labels.withColumn("hub_band", F.floor(F.log2(F.col("hub") + 1)).cast("int"))
    banded.repartitionByRange(n, "v").sortWithinPartitions("v", "hub").write.mode("overwrite").parquet(f"{path}/labels")
    parts = [("labels", labels)]
    if bp is not None:
        bp.repartitionByRange(n, "v").sortWithinPartitions("v", "slot").write.mode("overwrite").parquet(f"{path}/bp_labels")
        parts.append(("bp_labels", bp))
    rows = [(name, df.count()) for name, df in parts]
    labels.sparkSession.createDataFrame(rows, "part string, rows long").coalesce(1).write.mode("overwrite").json(f"{path}/manifest")


def open_index(spark: SparkSession, path: str) -> dict[str, DataFrame]:
    """Parts by name, checked against the manifest."""
    out = {}
    for part, rows in spark.read.schema("part string, rows long").json(f"{path}/manifest").collect():
        out[part] = spark.read.parquet(f"{path}/{part}").drop("hub_band")
        if out[part].count() != rows:
            raise ValueError(f"{part} does not match its manifest")
    return out
