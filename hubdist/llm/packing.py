"""Packing token pieces into sequences by minimum bin slack.

A sequence is filled with the fullest feasible set of the lengths at hand, found
by a subset-sum over bit sets, and those pieces are taken out; then the next.
The search runs over the histogram of lengths, never over pieces: one filling
repeats as often as its lengths allow, so it costs the same for any corpus. The
pieces find their places by their running number within their length.
"""

from __future__ import annotations

import re
import zlib
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.scratch import cut
from . import textvec as tv
from .pretokens import piece_starts

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
MEMO = 100_000
_TOK: dict = {}
_KNOWN: dict = {}


def tokenizer(path: str):
    """A merger of single pieces over the vocabulary of a tokenizer file, whose ids are merge ranks, and the special tokens."""
    if path not in _TOK:
        import json

        import tiktoken

        from .bpe import byte_symbols

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        byte = {s: b for b, s in enumerate(byte_symbols())}
        merged = [model["vocab"]["".join(m) if isinstance(m, list) else m.replace(" ", "")] for m in model["merges"]]
        if merged != sorted(merged):
            raise ValueError("ids of this vocabulary do not follow its merges")
        ranks = {bytes(byte[c] for c in t): i for t, i in model["vocab"].items() if t not in special}
        one = tiktoken.Encoding("ranks", pat_str=r"\S+|\s+", mergeable_ranks=ranks, special_tokens={})
        _TOK[path] = one._core_bpe.encode_single_piece, special
    return _TOK[path]


class Known:
    """Ids of known pieces in flat arrays, found by the pieces' bytes; emptied when full."""

    def __init__(self) -> None:
        self.place: dict[bytes, int] = {}
        self.at, self.n, self.pool = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)

    def find(self, words: list[bytes], encode) -> np.ndarray:
        """Place of each of the distinct ``words``; new ones are encoded."""
        if len(self.place) > MEMO or len(self.pool) > 8 * MEMO:
            self.__init__()
        lost = [w for w in words if w not in self.place]
        ids = [encode(w) for w in lost]
        n = np.fromiter(map(len, ids), np.int64, len(ids))
        self.at, self.n = np.concatenate([self.at, len(self.pool) + np.cumsum(n) - n]), np.concatenate([self.n, n])
        self.pool = np.concatenate([self.pool, np.fromiter(chain.from_iterable(ids), np.uint32, int(n.sum()))])
        self.place.update(zip(lost, range(len(self.place), len(self.place) + len(lost)), strict=True))
        return np.fromiter((self.place[w] for w in words), np.int64, len(words))


def token_arrays(rows: list[str], path: str) -> list[np.ndarray]:
    """Ids of each text as the library encodes it; each distinct piece between merge borders is encoded once."""
    one, special = tokenizer(path)
    known = _KNOWN.setdefault(path, Known())
    if special and any("<|" in t for t in rows):
        cutter = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")")
        parts = [cutter.split(t) if "<|" in t else [t] for t in rows]
    else:
        parts = [[t] for t in rows]
    flat = [s if k % 2 == 0 else "" for p in parts for k, s in enumerate(p)]
    cp, off = tv.code_points(flat)
    starts = np.flatnonzero(piece_starts(cp, off, keep_space=True))
    ends = np.append(starts[1:], len(cp))
    place = tv.utf8_places(cp)
    data = np.frombuffer("".join(flat).encode("utf-8", "surrogatepass"), np.uint8)
    code, uniq = tv.same_words(tv.words_of(data, place[starts], place[ends]))
    held = known.find(uniq.to_pylist(), one)
    at, count, pool = known.at[held], known.n[held], known.pool
    n = count[code]
    before = np.concatenate([[0], np.cumsum(n)])
    ids = pool[np.repeat(at[code] - before[:-1], n) + np.arange(before[-1])] if len(code) else np.zeros(0, np.uint32)
    edge = before[np.searchsorted(starts, off)]
    out, k = [], 0
    for p in parts:
        if len(p) == 1:
            out.append(ids[edge[k] : edge[k + 1]])
        else:
            out.append(np.concatenate([np.array([special[s]], np.uint32) if i % 2 else ids[edge[k + i] : edge[k + i + 1]] for i, s in enumerate(p)]))
        k += len(p)
    return out


def pieces(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2) -> DataFrame:
    """Token pieces of whole texts with the end id: (doc_id, piece, start, length, ids_crc32). Longer texts are cut; the first piece is the shorter one."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def run(batches):
        for keys, rows, _ in tv.text_batches(batches, 1 << 20):
            cols: list[list] = [[], [], [], [], []]
            for key, ids in zip(keys, token_arrays(rows, path), strict=True):
                ids = np.append(ids, np.uint32(end_id)).astype("<u4")
                n = len(ids)
                first = (n - 1) % capacity + 1
                raw = memoryview(ids.tobytes())
                a = 0
                for k, b in enumerate(range(first, n + 1, capacity)):
                    for c, v in zip(cols, (key, k, a, b - a, zlib.crc32(raw[4 * a : 4 * b])), strict=True):
                        c.append(v)
                    a = b
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.mapInArrow(run, PIECES)


def fullest(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """The fullest feasible filling that holds the longest piece: {length: times}.

    ``counts`` goes from long to short. A bit set holds all reachable sums after
    each length; the search ends once the sequence is full.
    """
    top = next(iter(counts))
    room = capacity - top
    mask = (1 << (room + 1)) - 1
    reach, trail = 1, []
    for length, n in counts.items():
        n = min(n - (length == top), room // length)
        step = 1
        while n > 0:
            step = min(step, n)
            new = (reach | reach << (step * length)) & mask
            if new != reach:
                trail.append((length, step, reach))
                reach = new
            n -= step
            step *= 2
        if reach >> room & 1:
            break
    left = reach.bit_length() - 1
    found = {top: 1}
    for length, step, before in reversed(trail):
        if not before >> left & 1:
            left -= length * step
            found[length] = found.get(length, 0) + step
    return found


def plan_bins(histogram: dict[int, int], capacity: int) -> list[tuple[int, dict[int, int]]]:
    """Fillings and how often each repeats, until nothing is left."""
    counts = {k: histogram[k] for k in sorted(histogram, reverse=True) if histogram[k]}
    out = []
    while counts:
        fill = fullest(counts, capacity)
        times = min(counts[k] // v for k, v in fill.items())
        out.append((times, fill))
        for k, v in fill.items():
            counts[k] -= v * times
            if not counts[k]:
                del counts[k]
    return out


def pack(items: DataFrame, capacity: int = 1024, order: tuple[str, ...] = ("doc_id", "piece"), per_bucket: int = 100_000) -> DataFrame:
    """Give every row of ``items`` (with ``length``, 1 to ``capacity``) a ``sequence_id`` and an ``offset``.

    Null or too long lengths are refused by an error, as no place exists. Repeated
    rows are separate pieces. Reaching the driver: the histogram of lengths, at
    most ``capacity`` rows.
    """
    histogram = {r[0]: r[1] for r in items.groupBy("length").count().collect()}
    if any(k is None or not 1 <= k <= capacity for k in histogram):
        raise ValueError("lengths must be between 1 and the capacity")
    plan = plan_bins(histogram, capacity)
    runs: dict[int, list[tuple[int, int, int, int]]] = {}
    taken: dict[int, int] = {}
    first = 0
    for times, fill in plan:
        at = 0
        for length, need in fill.items():
            runs.setdefault(length, []).append((taken.get(length, 0), need, first, at))
            taken[length] = taken.get(length, 0) + need * times
            at += need * length
        first += times
    table = {k: np.array(v, np.int64) for k, v in runs.items()}
    buckets = max(8, sum(histogram.values()) // per_bucket)
    dealt = items.withColumn("_b", F.pmod(F.xxhash64(*order), F.lit(buckets)))
    counts = dealt.groupBy("length", "_b").count()
    before = counts.withColumn("_before", F.sum("count").over(Window.partitionBy("length").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1))).select("length", "_b", F.coalesce("_before", F.lit(0)).alias("_before"))
    ranked = dealt.withColumn("_k", F.row_number().over(Window.partitionBy("length", "_b").orderBy(*order)))
    ranked = ranked.join(before, ["length", "_b"]).withColumn("_rank", F.col("_before") + F.col("_k") - 1)
    kept = [c for c in items.columns]

    def place(batches):
        for batch in batches:
            length, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy().astype(np.int64) for c in ("length", "_rank"))
            seq, off = np.empty(len(length), np.int64), np.empty(len(length), np.int64)
            order = np.argsort(length, kind="stable")
            cuts = np.flatnonzero(np.diff(length[order])) + 1
            for rows in np.split(order, cuts):
                if not len(rows):
                    continue
                own = table[int(length[rows[0]])]
                r = own[np.searchsorted(own[:, 0], rank[rows], "right") - 1]
                k = rank[rows] - r[:, 0]
                seq[rows] = r[:, 2] + k // r[:, 1]
                off[rows] = r[:, 3] + k % r[:, 1] * length[rows]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(c)) for c in kept), pa.array(seq), pa.array(off)], [*kept, "sequence_id", "offset"])

    from pyspark.sql.types import LongType, StructField, StructType

    schema = StructType([*items.schema.fields, StructField("sequence_id", LongType()), StructField("offset", LongType())])
    return ranked.select(*kept, "_rank").mapInArrow(place, schema)


def pack_documents(docs: DataFrame, path: str, capacity: int = 1024, end_id: int = 2) -> DataFrame:
    """Pieces of all documents, packed. Null text is empty: one piece with the end id. An empty table gives no rows."""
    return pack(cut(pieces(docs, path, capacity, end_id), "pieces"), capacity)
