"""Fuzzy line dedup: MinHash over character shingles, banding, exact check, components.

Lines are split at line feeds and taken as they are. A line of white space only
is blank: never a duplicate, always kept. Equal lines are one class from the
start (two hashes of 64 bits). Signatures fill all their slots from one hash per
shingle and round (later rounds only fill slots still empty, by the same rule for
every line), so a long line costs a few hashes a shingle and a short one a few
hundred in all. Lines that share
a band of slots are candidates; each meets the centre of its band lines, then what
is still apart in its block (``overlap``), by exact Jaccard; components of the links
keep their first line.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import cut
from . import textvec as tv
from .columns import own_names
from .graph import packed, packed_stars
from .overlap import distinct, linked_items
from .pretokens import WHITE

SHINGLE = 8
INK = "[^" + "".join(f"\\x{{{c:x}}}" for c in WHITE) + "]"  # what a line must hold not to be blank
HELD = 1 << 20  # bands that a task packs at once
ROWS, BANDS = 6, 16  # a pair at similarity 0.8 shares a band with probability 0.992, at 0.9 with 0.9999


def digests(line: str) -> tuple[Column, Column]:
    """Two hashes of a line, h1 and h2."""
    return F.xxhash64(line).alias("h1"), F.xxhash64(F.lit(1), line).alias("h2")


def line_shingles(cp: np.ndarray, start: np.ndarray, end: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of the lines, and the line of each; a shorter line is one shingle."""
    n = np.maximum(end - start - width + 1, 1)
    owner = np.repeat(np.arange(len(start)), n)
    a = np.arange(len(owner)) + np.repeat(start - (np.cumsum(n) - n), n)
    p = tv.prefix(cp)
    size = max(len(p) - width, 0)
    h = p[width:] - p[:size]
    h *= tv.powers(len(p))[1][:size]
    h += np.uint64(width * 0x9FB21C651E98DF25 & 0xFFFFFFFFFFFFFFFF)
    short = end - start < width
    x = tv.fmix(h)[np.minimum(a, max(size - 1, 0))] if size else np.zeros(len(a), np.uint64)
    if short.any():
        at = (np.cumsum(n) - n)[short]
        x[at] = tv.span_hash(p, start[short], end[short])
    return x, owner


def signatures(x: np.ndarray, owner: np.ndarray, lines: int, slots: int) -> np.ndarray:
    """Minimum per line and slot, a function of the line's distinct shingles alone.

    Round r sends each shingle to one slot; rounds from ``slots`` on send all to slot
    r - slots. A slot keeps the value of the first round that reaches it, and a line
    goes on until all its slots are filled, whatever its length.
    """
    empty, low = np.uint64(0xFFFFFFFFFFFFFFFF), np.uint64(0xFFFFFFFF)
    sig = np.full(lines * slots, empty)
    for r in range(2 * slots):
        h = x if r == 0 else tv.fmix(x + np.uint64(r * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        at = owner * slots
        if r < slots:
            slot = h >> np.uint64(32)
            slot *= np.uint64(slots)
            slot >>= np.uint64(32)
            at += slot.view(np.int64)
        else:
            at += r - slots
        np.minimum.at(sig, at, (h & low) | np.uint64(r << 32))
        live = (sig == empty).reshape(lines, slots).any(axis=1)[owner]
        if not live.any():
            break
        x, owner = x[live], owner[live]
        if r == 3:  # a long line still open repeats few shingles: once each is enough, as a minimum does not count
            big = (np.bincount(owner, minlength=lines) > 2 * slots)[owner]
            if big.any():
                once, off = distinct(x[big], owner[big], lines)
                x, owner = np.concatenate([x[~big], once]), np.concatenate([owner[~big], np.repeat(np.arange(lines), np.diff(off))])
    return sig.reshape(lines, slots)


def split_lines(docs: DataFrame) -> DataFrame:
    """(doc_id, line_no, line) of all lines; null text is one blank line."""
    return docs.select("doc_id", F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n", -1)).alias("line_no", "line"))


def line_table(docs: DataFrame) -> DataFrame:
    """(doc_id, line_no, h1, h2, ink, size) of all lines."""
    return split_lines(docs).select("doc_id", "line_no", *digests("line"), F.col("line").rlike(INK).alias("ink"), F.length("line").cast("long").alias("size"))


def line_hubs(docs: DataFrame, width: int, rows_per_band: int, bands: int) -> DataFrame:
    """(a, b), once: b is the smallest h1 under a band of line a; equal lines of a batch count once.

    Bands travel as arrays, a row for each part of the keys and ``HELD`` bands, not a
    row for each band of each line.
    """
    slots = rows_per_band * bands
    parts = min(1 << 16, 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def keys(batches):
        once = (b.take(pa.array(np.unique(b.column(0).to_numpy(), return_index=True)[1])) for b in batches)
        for piece in tv.piece_batches(once, 1 << 17):  # arrays of a piece stay in a core's cache
            cp, off = tv.column_points(piece.column(1))
            x, owner = line_shingles(cp, off[:-1], off[1:], width)
            sig = signatures(x, owner, piece.num_rows, slots)
            key = np.zeros((piece.num_rows, bands), np.uint64)
            for r in range(rows_per_band):
                key = tv.fmix(key + sig[:, r::rows_per_band] + np.uint64(0x9E3779B97F4A7C15))
            key = tv.fmix(key + np.arange(bands, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))
            yield key.ravel(), np.repeat(piece.column(0).to_numpy(), bands)

    def run(batches):
        kept, size = [], 0
        for x in keys(batches):
            kept.append(x)
            size += len(x[0])
            if size >= HELD:
                yield packed(*map(np.concatenate, zip(*kept, strict=True)), parts)
                kept, size = [], 0
        if size:
            yield packed(*map(np.concatenate, zip(*kept, strict=True)), parts)

    def stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for a, b in packed_stars(y for x in batches for y in x.column(x.schema.get_field_index("pairs")).to_pylist()):
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

    inked = split_lines(docs).where(F.col("line").rlike(INK)).select(digests("line")[0], "line")
    return inked.mapInArrow(run, "part int, pairs binary").groupBy("part").applyInArrow(stars, "a long, b long").distinct()


def line_classes(docs: DataFrame, num: int = 80, den: int = 100, width: int = SHINGLE, rows_per_band: int = ROWS, bands: int = BANDS) -> DataFrame:
    """(doc_id, line_no, class_doc, class_line, kept) of every line.

    A class is a component of lines whose shingle sets have den * overlap >= num *
    union; its name is its first line by (doc_id, line_no), which alone is kept.
    Blank lines and lines of rows with a null doc_id are their own class and kept.
    Null text is one blank line. Of rows that repeat a doc_id each line counts by
    its content; equal places count as equal lines only if their texts are equal.
    """
    return placed_lines(docs, num, den, width, rows_per_band, bands).drop("h1")


def placed_lines(docs: DataFrame, num: int = 80, den: int = 100, width: int = SHINGLE, rows_per_band: int = ROWS, bands: int = BANDS) -> DataFrame:
    """``line_classes`` with the hash h1 of each line, which tells lines of rows that repeat a doc_id apart."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    every = cut(line_table(docs), "lines")
    near = cut(line_hubs(docs, width, rows_per_band, bands), "near")
    place = F.struct("doc_id", "line_no")
    inked = every.where("ink and doc_id is not null")
    first = cut(inked.groupBy("h1", "h2").agg(F.min(place).alias("rep"), F.count("*").alias("n"), F.max("size").alias("size")), "reps")
    nodes = near.select(F.explode(F.array("a", "b")).alias("h1")).distinct()
    chosen = cut(first.join(nodes, "h1").select(F.monotonically_increasing_id().alias("id"), "rep", "h1", "h2", F.col("size").alias("weight")), "chosen")
    wanted = chosen.groupBy(F.col("rep.doc_id").alias("doc_id")).agg(F.collect_list(F.struct("rep.line_no", "h1", "h2", "id")).alias("want"))
    line = docs.join(wanted, "doc_id").select("doc_id", "want", F.split("text", "\n", -1).alias("lines"))
    line = line.select("doc_id", F.explode(F.transform("want", lambda w: F.struct(w.alias("w"), F.get("lines", w.line_no).alias("line")))).alias("x"))
    line = line.select("doc_id", "x.w.*", "x.line")
    h1, h2 = digests("line")
    same = line.where((h1 == F.col("h1")) & (h2 == F.col("h2")))  # a repeated doc_id may hold another line there
    texts = same.select(F.col("id").alias("item"), F.col("line").alias("text"))
    items = chosen.select(F.col("h1").alias("node"), F.col("id").alias("item"), "weight")

    def sets(table):
        found, sizes = [np.zeros(0, np.uint64)], []
        for piece in tv.piece_batches(table.select(["text"]).to_batches(), 1 << 17, 0):
            cp, off = tv.column_points(piece.column(0))
            x, at = distinct(*line_shingles(cp, off[:-1], off[1:], width), len(off) - 1)
            found.append(x)
            sizes.append(np.diff(at))
        return np.concatenate(found).view(np.int64), np.concatenate([[0], *sizes]).cumsum(), np.arange(table.num_rows)

    linked = chosen.join(linked_items(near, items, texts, sets, num, den).withColumnRenamed("node", "id"), "id").select("h1", "h2", "rep", "comp")
    comp = linked.join(linked.groupBy("comp").agg(F.min("rep").alias("cls")), "comp").select("h1", "h2", F.col("cls").alias("comp"))
    # only classes of several lines say anything; the rest are their own
    named = first.join(comp, ["h1", "h2"], "left").where("n > 1 or comp is not null").select("h1", "h2", F.coalesce("comp", "rep").alias("cls"))
    out = every.join(named, ["h1", "h2"], "left")
    own = F.when(F.col("ink") & F.col("doc_id").isNotNull(), F.coalesce("cls", place)).otherwise(place)
    return out.select("doc_id", "line_no", "h1", own.alias("cls")).select("doc_id", "line_no", "h1", F.col("cls.doc_id").alias("class_doc"), F.col("cls.line_no").alias("class_line"), (F.col("doc_id").eqNullSafe(F.col("cls.doc_id")) & (F.col("line_no") == F.col("cls.line_no"))).alias("kept"))


def drop_repeated_lines(docs: DataFrame, **how) -> DataFrame:
    """Documents with only the kept lines in ``text`` (and ``n_chars`` to match, where there is one); no row goes, columns stay.

    Of rows that repeat a doc_id each loses only lines of its own; equal lines at one
    place of such rows stay in all of them, as rows go in the document join.
    """
    found = placed_lines(docs, **how)
    cut_, key = own_names(docs, 2)
    gone = found.where(~F.col("kept")).groupBy(F.col("doc_id").alias(key)).agg(F.collect_set(F.struct("line_no", "h1")).alias(cut_))
    out = docs.join(gone, F.col("doc_id").cast("long") == F.col(key), "left")
    lines = F.split("text", "\n", -1)
    kept = F.array_join(F.filter(lines, lambda x, i: ~F.array_contains(F.col(cut_), F.struct(i.alias("line_no"), F.xxhash64(x).alias("h1")))), "\n")
    changed = {"text": F.when(F.col(cut_).isNull(), F.col("text")).otherwise(kept)}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.when(F.col(cut_).isNull(), F.col("n_chars")).otherwise(F.length(changed["text"]).cast(docs.schema["n_chars"].dataType))
    return out.withColumns(changed).select(*docs.columns)
