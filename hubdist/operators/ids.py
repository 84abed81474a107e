"""Dense ids in a total order without a window over one partition."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut


def dense_ids(df: DataFrame, order: list, name: str) -> DataFrame:
    """``df`` with ids 0..n-1 in front, in the given total order: range-sorted parts, each shifted by the rows of the parts before it."""
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    cols = df.columns
    sorted_ = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    held = cut(sorted_.withColumn("_m", F.monotonically_increasing_id()), "ids")
    part = F.shiftright("_m", 33)
    counts = held.groupBy(part.alias("p")).count().orderBy("p").collect()  # a row for each partition
    shift, total = [], 0
    for r in counts:
        shift += [F.lit(r[0]), F.lit(total)]
        total += r[1]
    if not counts:
        return held.select(F.lit(0).cast("long").alias(name), *cols)
    at = F.create_map(*shift)[part] + F.col("_m").bitwiseAND((1 << 33) - 1)
    return cut(held.select(at.cast("long").alias(name), *cols), "ids")


def relabel(edges: DataFrame, ranks: DataFrame) -> DataFrame:
    """Edges in rank space: ends become ranks."""
    a, b = ranks.select(F.col("vid").alias("src"), F.col("rnk").alias("u")), ranks.select(F.col("vid").alias("dst"), F.col("rnk").alias("v"))
    return cut(edges.join(a, "src").join(b, "dst").select("u", "v", *(["w"] if "w" in edges.columns else [])), "ranked")
