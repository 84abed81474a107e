"""Connected components of a link table, without collecting links anywhere.

Each round rewires every node's neighbours to the smallest node it can see,
first larger neighbours, then smaller ones. Stars appear after few rounds. Keys
may be of any type with an order, structs included. What a join meets is written
first, so that both its sides are plain exchanges and the centre of a large star,
one key of many rows, can be dealt over several tasks by the skew join.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut, drop

#: Pairs that a task holds; more wait in a file of the task.
PAIRS = 1 << 22


def star_edges(df: DataFrame, key: str, item: str) -> DataFrame:
    """(a, b), once: b is the smallest item under a key of item a; a bucket of any size spills, and sorting by the key alone is a radix sort."""
    from pyspark.sql import Window

    return df.select(F.min(item).over(Window.partitionBy(key)).alias("b"), F.col(item).alias("a")).where("a <> b").distinct()


def packed(key: np.ndarray, item: np.ndarray, parts: int) -> pa.RecordBatch:
    """Pairs of spread 64-bit keys and items as rows (part, pairs), one for each part that has a key."""
    part = (key % np.uint64(parts)).astype(np.uint16)
    order = np.argsort(part, kind="stable")
    pairs = np.empty((len(key), 2), np.int64)
    pairs[:, 0], pairs[:, 1] = key.view(np.int64)[order], item[order]
    count = np.bincount(part, minlength=parts)
    some = np.flatnonzero(count)
    off = np.concatenate([[0], np.cumsum(16 * count[some])]).astype(np.int32)
    blobs = pa.Array.from_buffers(pa.binary(), len(some), [None, pa.py_buffer(off), pa.py_buffer(pairs)])
    return pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), blobs], ["part", "pairs"])


def _least(key: np.ndarray, low: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each key once, with its smallest item and whether it has more than one."""
    order = np.argsort(key)
    key, low, many = key[order], low[order], many[order]
    cuts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    if len(cuts) == len(key):
        return key, low, many
    least = np.minimum.reduceat(low, cuts)
    return key[cuts], least, (np.maximum.reduceat(low, cuts) != least) | np.logical_or.reduceat(many, cuts)


def packed_stars(blobs: Iterator[bytes], held: int = 0) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """``star_edges`` of one part of ``packed`` pairs, some repeated: (items, the smallest item under their key).

    At most about ``held`` pairs are in memory: a larger part goes to a file that ends
    with the task and is read twice for each of several ranges of its keys, first for the
    smallest items and then for the others, so that a key of any size fits.
    """
    held = held or PAIRS
    with tempfile.TemporaryFile() as file:
        kept, size, written = [], 0, 0

        def chunks() -> Iterator[np.ndarray]:
            file.seek(0)
            while data := file.read(16 * held):
                yield np.frombuffer(data, np.int64).reshape(-1, 2)

        for x in blobs:
            kept.append(x)
            size += len(x) // 16
            if size >= held:
                file.write(b"".join(kept))
                kept, size, written = [], 0, written + size
        if written:
            file.write(b"".join(kept))
        last = [] if written else [np.frombuffer(b"".join(kept), np.int64).reshape(-1, 2)]
        ranges = -(-(written + size) // held) if written else 1
        for r in range(ranges):
            some = lambda x, r=r: x if ranges == 1 else x[(x[:, 0].view(np.uint64) >> np.uint64(32)) * np.uint64(ranges) >> np.uint64(32) == r]
            key, low, many = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)
            for x in map(some, last or chunks()):
                key, low, many = _least(np.concatenate([key, x[:, 0]]), np.concatenate([low, x[:, 1]]), np.concatenate([many, np.zeros(len(x), bool)]))
            key, low = key[many], low[many]
            if not len(key):
                continue
            for x in map(some, last or chunks()):
                k = np.minimum(np.searchsorted(key, x[:, 0]), len(key) - 1)
                at = (key[k] == x[:, 0]) & (low[k] != x[:, 1])
                yield x[at, 1], low[k[at]]


def components(edges: DataFrame) -> DataFrame:
    """(node, comp) for all nodes of ``edges`` (a, b); comp is the smallest node that links reach.

    Null ends and loops are ignored, repeated links count once; no links, no rows.
    """
    now = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "links")
    while not _stars(now):
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = cut(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")), "low")
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.when(F.col("b") != F.col("m"), F.col("b")).otherwise(F.col("a")).alias("a"), F.col("m").alias("b"))
        nxt = cut(small.where("a <> b").distinct(), "links")
        for x in (low, now):
            drop(x)
        now = nxt
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("comp")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("comp")).unionByName(roots)


def _stars(df: DataFrame) -> bool:
    """Whether every node with a link has just one, to a node that has none: links go to smaller nodes, so that one is the smallest."""
    ends = df.select(F.col("a").alias("x"), F.lit(1).alias("out")).unionByName(df.select(F.col("b").alias("x"), F.lit(0).alias("out")))
    return ends.groupBy("x").agg(F.sum("out").alias("out"), F.count("*").alias("n")).where("out > 1 or (out = 1 and n > 1)").isEmpty()
