"""Tables that cut lineage, kept in the folder all executors share.

Iterative operators write every round as Parquet and read it back, so that a
lost executor costs the running stage only and no plan is deeper than a round.
"""

from __future__ import annotations

import atexit
import os
import uuid

from pyspark.sql import DataFrame, SparkSession

_made: list[tuple[SparkSession, str]] = []


def base(spark: SparkSession) -> str:
    """The shared folder: ``spark.checkpoint.dir``; only a local master without it gets a folder of its own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return "/tmp/checkpoints/hubdist"
    raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{base(spark)}/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` to a new scratch table and return the table as read back."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def drop(df: DataFrame | None) -> None:
    """Remove the scratch table behind a frame made by ``cut``; nothing may read it afterwards."""
    path = getattr(df, "_scratch_path", None)
    if path:
        _delete(df.sparkSession, path)


def exists(spark: SparkSession, path: str) -> bool:
    """Whether a table or folder stands at ``path``, in whatever store Spark reads."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    for x in [x for x in _made if x[1] == path]:
        _made.remove(x)


@atexit.register
def _clean() -> None:
    for spark, path in list(_made):
        try:
            _delete(spark, path)
        except Exception:  # the session may be gone already
            return


def ship(spark: SparkSession) -> None:
    """Give executors this package, once per context, where their path may lack it."""
    sc = spark.sparkContext
    if getattr(sc, "_hubdist_shipped", False):
        return
    sc._hubdist_shipped = True
    import io
    import tempfile
    import zipfile

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    held = io.BytesIO()
    with zipfile.ZipFile(held, "w") as z:
        for d, dirs, names in os.walk(root):
            dirs[:] = [x for x in dirs if x != "__pycache__"]
            for x in names:
                if x.endswith(".py"):
                    full = os.path.join(d, x)
                    z.write(full, os.path.join("hubdist", os.path.relpath(full, root)))
    at = os.path.join(tempfile.mkdtemp(), "hubdist_package.zip")
    with open(at, "wb") as f:
        f.write(held.getvalue())
    sc.addPyFile(at)
