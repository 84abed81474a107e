"""Self-join of documents by the Jaccard similarity of their word n-grams, exact.

1. Equal sets are one class from the start, however many copies it has.
2. Candidates by a T-occurrence search over the whole table. Sets of n elements
   that link share T(n) of them at least. In the order of the elements' hashes the
   first n - T + L elements of both then share L at least; only these are posted.
   An element that one set posts says nothing. Of the rest a set leaves its L' - 1
   longest lists out, L' being the L of its smallest partner, and still meets every
   partner in the lists it keeps. A passage that many texts share makes long lists,
   so it goes unless it is most of a text.
3. Inside tasks an occurrence search over inverted lists (``overlap``) finds the
   links, which then give components.

Nothing is sampled or capped; every link has its pair in one list at least.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.scratch import cut
from . import textvec as tv
from .columns import own_names
from .graph import components, star_edges
from .overlap import distinct, linked_items

_WHITE = np.zeros(256, bool)
_WHITE[[32, *range(9, 14)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def shingle_sets(data: np.ndarray, off: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text, one after another, and their offsets."""
    n = len(off) - 1
    low = _LOWER[data]
    white = _WHITE[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[off] = True
    word = ~white
    begins = word.copy()
    begins[1:] &= white[:-1] | edge[1:-1]
    ends = word.copy()
    ends[:-1] &= white[1:] | edge[1:-1]
    s, e = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    h = tv.word_hashes(low, s, e)
    row, words = tv.spans_of(s, n, off)
    first = np.concatenate([[0], np.cumsum(words)])
    # a shingle is a span over word hashes, taken as characters of a second text
    q = tv.prefix(h, 1)
    last = np.maximum(words - width + 1, (words > 0).astype(np.int64))
    owner = np.repeat(np.arange(n), last)
    at = np.arange(len(owner)) - np.repeat(np.cumsum(last) - last, last) + first[owner]
    x = tv.span_hash(q, at, np.minimum(at + width, first[owner + 1]), 1)
    return distinct(x, owner, n)


def overlap_needed(n, num: int, den: int):
    """T: elements that a set of n shares with any partner, at least."""
    return -(-num * n // den)


def agreed(n, num: int, den: int):
    """L: posted elements that two linked sets share, of which the smaller has n; the more, the more long lists can be left out."""
    return 1 + n * (den - num) // den


def posted(x: np.ndarray, at: np.ndarray, num: int, den: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Elements that each set posts, its owner, and how many of the longest lists the owner leaves out; sets that link only with equal ones post none."""
    n = np.diff(at)
    owner = np.repeat(np.arange(len(n)), n)
    uniq, code = np.unique(x, return_inverse=True)
    pair = np.sort(owner * len(uniq) + code)
    owner, code = np.divmod(pair, max(1, len(uniq)))
    need = overlap_needed(n, num, den)
    first = np.where(n * den >= num * (n + 1), n - need + agreed(n, num, den), 0)
    keep = np.arange(len(owner)) - at[:-1][owner] < first[owner]
    return uniq[code[keep]], owner[keep], agreed(need, num, den) - 1


def digest(x: np.ndarray, at: np.ndarray) -> np.ndarray:
    """64 bits for each set, whatever the order of its elements."""
    total = np.concatenate([[np.uint64(0)], np.cumsum(tv.fmix(x))])
    return tv.fmix(total[at[1:]] - total[at[:-1]]).view(np.int64)


def classes(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, n, d1, d2): set size and a digest of 128 bits of each document's set."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def run(batches):
        for keys, data, off in _pieces(batches):
            x, at = shingle_sets(data, off, width)
            d1, d2 = digest(x, at), digest(x + np.uint64(0x9E3779B97F4A7C15), at)
            yield pa.RecordBatch.from_arrays([keys, pa.array(np.diff(at)), pa.array(d1), pa.array(d2)], ["doc_id", "n", "d1", "d2"])

    return docs.mapInArrow(run, "doc_id long, n long, d1 long, d2 long")


def _pieces(batches, limit: int = 1 << 21):
    for batch in batches:
        data, off = tv.utf8(batch.column(1))
        for i, j in tv.slices(np.diff(off), limit):
            yield batch.column(0).slice(i, j - i), data[off[i] : off[j]], off[i : j + 1] - off[i]


def linked_classes(docs: DataFrame, width: int = 4, num: int = 85, den: int = 100) -> DataFrame:
    """(doc_id, n, component_id) of every row.

    Null or empty text and text without words: an empty set, linked with nothing.
    Rows with a null doc_id keep their size and get a null component. Rows that
    repeat a doc_id are taken as versions of one document and linked by it.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    every = cut(classes(docs, width), "sets")
    real = every.where("n > 0 and doc_id is not null")
    reps = cut(real.groupBy("d1", "d2", "n").agg(F.min("doc_id").alias("rep")), "classes")
    named = docs.where("doc_id is not null and text is not null").select("doc_id", "text")

    def posts(batches):
        # a set is named by 64 bits of its digest: equal sets of a task count once, and two sets of one name only share their lists
        met = set()
        for _, data, off in _pieces(batches, 1 << 20):
            x, at = shingle_sets(data, off, width)
            names = digest(x, at)
            fresh = np.zeros(len(names), bool)
            for k in np.flatnonzero(np.diff(at)).tolist():
                if names[k] not in met:
                    met.add(names[k])
                    fresh[k] = True
            n = np.diff(at)
            x, names = x[np.repeat(fresh, n)], names[fresh]
            key, owner, out = posted(x, np.concatenate([[0], np.cumsum(n[fresh])]), num, den)
            key, owner, out = key.view(np.int64), names[owner], out[owner].astype(np.int32)
            for i in range(0, len(key), 200_000):
                yield pa.RecordBatch.from_arrays([pa.array(v[i : i + 200_000]) for v in (key, owner, out)], ["key", "d1", "out"])

    key = Window.partitionBy("key")
    held = named.mapInArrow(posts, "key long, d1 long, out int").select("*", F.count("*").over(key).alias("size"), F.min("d1").over(key).alias("lo"), F.max("d1").over(key).alias("hi")).where("lo < hi")
    longest = F.row_number().over(Window.partitionBy("d1").orderBy(F.desc("size"), "key"))
    kept = held.dropDuplicates(["key", "d1"]).withColumn("place", longest).where("place > out")
    near = cut(star_edges(kept.select("key", "d1"), "key", "d1"), "near")

    def sets(table):
        text = table["text"].combine_chunks()
        held = [shingle_sets(data, off, width) for _, data, off in _pieces([pa.RecordBatch.from_arrays([text, text], ["id", "text"])], 1 << 19)]
        sizes = np.concatenate([np.zeros(1, np.int64), *[np.diff(at) for _, at in held]])
        return np.concatenate([np.zeros(0, np.uint64), *[x for x, _ in held]]).view(np.int64), np.cumsum(sizes), np.arange(table.num_rows)

    items = reps.select(F.col("d1").alias("node"), F.col("rep").alias("item"), F.col("n").alias("weight"))
    texts = named.select(F.col("doc_id").alias("item"), "text", F.xxhash64("text").alias("mark"))
    repeated = linked_items(near, items, texts, sets, num, den)
    same = real.join(reps, ["d1", "d2", "n"]).where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    # a class whose rows carry one doc_id twice is tied by that id, so copies enter as links only where they meet several classes
    many = real.groupBy("doc_id").agg(F.count_distinct("d1", "d2").alias("k")).where("k > 1").select("doc_id")
    tied = every.join(many, "doc_id", "left_semi")
    if tied.limit(1).count():
        repeated = components(repeated.select(F.col("node").alias("a"), F.col("comp").alias("b")).unionByName(same))
    comp = repeated.select(F.col("node").alias("rep"), "comp")
    placed = reps.join(comp, "rep", "left").select("d1", "d2", "n", F.coalesce("comp", "rep").alias("comp"))
    out = every.join(placed, ["d1", "d2", "n"], "left")
    return out.select("doc_id", "n", F.when(F.col("doc_id").isNull(), None).when(F.col("n") == 0, F.col("doc_id")).otherwise(F.coalesce("comp", "doc_id")).alias("component_id"))


def keep_one(docs: DataFrame, width: int = 4, num: int = 85, den: int = 100) -> DataFrame:
    """One row of each component, of its smallest doc_id; rows with a null doc_id stay.

    Of rows that repeat this doc_id the longest text stays, then by its hash, then any of equal rows.
    """
    found = linked_classes(docs, width, num, den)
    free = own_names(docs, 3)
    gone = found.where("component_id <> doc_id").select(F.col("doc_id").alias(free[0])).distinct()
    many = docs.where("doc_id is not null").groupBy(F.col("doc_id").cast("long").alias(free[1])).agg(F.count("*").alias(free[2])).where(F.col(free[2]) > 1).select(free[1])
    left = docs.join(gone, F.col("doc_id").cast("long") == F.col(free[0]), "left_anti")
    if not many.limit(1).count():
        return left
    w = Window.partitionBy("doc_id").orderBy(F.length("text").desc_nulls_last(), F.xxhash64("text"))
    twice = F.col("doc_id").cast("long") == F.col(free[1])
    several = left.join(many, twice, "left_semi").withColumn(free[2], F.row_number().over(w)).where(F.col(free[2]) == 1).drop(free[2])
    return left.join(many, twice, "left_anti").unionByName(several)
