"""Quality classifier by attention over passages.

A text is a bag of passages of equal length; only whole texts have labels. Each
passage is encoded from the frequencies of its character-class pairs; gated
attention gives each passage a weight, and the weighted mean is scored. Encoder,
gate and scorer are trained together on the labels of whole texts.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec as tv
from .pretokens import LETTER, NUMBER, SPACE, classes

PASSAGE = 256
SAMPLE = 1500  # labelled rows of a fit; it looks at all their passages
LOT = 1 << 13  # passages unpacked at once
#: Punctuation with a class of its own.
MARKS = ".,!?$%&*#|"
KINDS = 13 + len(MARKS)


@cache
def kinds() -> np.ndarray:
    """Class of every code point: letters by case and plainness, digits, white space, single marks, the rest."""
    base = classes()
    out = np.full(0x110000, 12, np.int64)
    out[base == NUMBER] = 2
    out[base == SPACE] = 5
    out[base == LETTER] = 6
    for c in np.flatnonzero(base == LETTER):
        if chr(c).isupper():
            out[c] = 7
    out[97:123], out[65:91] = 0, 1
    out[32], out[10] = 3, 4
    for c in range(33, 127):
        if base[c] not in (LETTER, NUMBER):
            ch = chr(c)
            out[c] = 13 + MARKS.index(ch) if ch in MARKS else 8 if ch in "\"'`" else 9 if ch in "()[]{}<>" else 10 if ch in "@/:_-+=" else 11
    return out


def passages(rows: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages and the passage bounds of each text; an empty text is one empty passage."""
    cp, off = tv.code_points(rows)
    k = kinds()[cp]
    n = np.diff(off)
    count = np.maximum(-(-n // PASSAGE), 1)
    first = np.concatenate([[0], np.cumsum(count)])
    row = np.repeat(np.arange(len(rows)), n)
    own = first[row] + (np.arange(len(cp)) - off[row]) // PASSAGE
    follow = np.append(k[1:], 3)
    follow[off[1:][n > 0] - 1] = 3  # a text ends as if by a space
    x = np.bincount((own * KINDS + k) * KINDS + follow, minlength=first[-1] * KINDS * KINDS).reshape(first[-1], -1)
    return np.sqrt(x / np.maximum(x.sum(axis=1, keepdims=True), 1)).astype(np.float32), first


def pack(x: np.ndarray) -> bytes:
    """The features of a bag without their zeros, which are most of them."""
    row, col = np.nonzero(x)
    held = np.bincount(row, minlength=len(x)).astype(np.uint16)
    return np.uint32(len(x)).tobytes() + held.tobytes() + col.astype(np.uint16).tobytes() + x[row, col].tobytes()


def unpack(b: bytes) -> np.ndarray:
    n = int(np.frombuffer(b, np.uint32, 1)[0])
    held = np.frombuffer(b, np.uint16, n, 4)
    total = int(held.sum(dtype=np.int64))
    x = np.zeros((n, KINDS * KINDS), np.float32)
    x[np.repeat(np.arange(n), held), np.frombuffer(b, np.uint16, total, 4 + 2 * n)] = np.frombuffer(b, np.float32, total, 4 + 2 * n + 2 * total)
    return x


@dataclass
class Model:
    w: np.ndarray
    b: np.ndarray
    v: np.ndarray
    u: np.ndarray
    a: np.ndarray
    c: np.ndarray
    d: np.ndarray

    def parts(self) -> list[np.ndarray]:
        return [self.w, self.b, self.v, self.u, self.a, self.c, self.d]


def forward(m: Model, x: np.ndarray, first: np.ndarray) -> tuple:
    """Score of each bag, with what the backward pass needs."""
    n = np.diff(first)
    h = np.tanh(x @ m.w + m.b)
    t, g = np.tanh(h @ m.v), 1 / (1 + np.exp(-np.clip(h @ m.u, -30, 30)))
    e = (t * g) @ m.a
    e = np.exp(e - np.repeat(np.maximum.reduceat(e, first[:-1]), n))
    att = e / np.repeat(np.add.reduceat(e, first[:-1]), n)
    z = np.add.reduceat(att[:, None] * h, first[:-1], axis=0)
    s = 1 / (1 + np.exp(-np.clip(z @ m.c + m.d[0], -30, 30)))
    return s, h, t, g, att, z


def gradients(m: Model, x: np.ndarray, first: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
    s, h, t, g, att, z = forward(m, x, first)
    n = np.diff(first)
    ds = (s - y) / len(y)
    dz = np.repeat(ds[:, None] * m.c, n, axis=0)
    datt = (dz * h).sum(axis=1)
    de = att * (datt - np.repeat(np.add.reduceat(att * datt, first[:-1]), n))
    dt, dg = de[:, None] * m.a * g * (1 - t * t), de[:, None] * m.a * t * g * (1 - g)
    dh = (dz * att[:, None] + dt @ m.v.T + dg @ m.u.T) * (1 - h * h)
    return [x.T @ dh, dh.sum(axis=0), h.T @ dt, h.T @ dg, (t * g).T @ de, z.T @ ds, np.array([ds.sum()])]


def fit(bags: list[bytes], y: np.ndarray, epochs: int = 40, width: int = 24, gate: int = 12, seed: int = 3) -> Model:
    """Train by Adam on small lots of packed bags, with at most ``LOT`` passages or one bag unpacked at a time; the same sample gives the same model."""
    rng = np.random.default_rng(seed)
    dims = KINDS * KINDS
    r = lambda *k: (rng.normal(size=k) / np.sqrt(k[0])).astype(np.float32)
    m = Model(r(dims, width) * 4, np.zeros(width, np.float32), r(width, gate), r(width, gate), r(gate), r(width), np.zeros(1, np.float32))
    mean, var, step = [np.zeros_like(p) for p in m.parts()], [np.zeros_like(p) for p in m.parts()], 0
    sizes = np.array([int(np.frombuffer(b, np.uint32, 1)[0]) for b in bags], np.int64)
    for _ in range(epochs):
        order = rng.permutation(len(bags))
        for i in range(0, len(order), 64):
            lot = order[i : i + 64]
            step += 1
            total = [np.zeros_like(p) for p in m.parts()]
            for j, k in tv.slices(sizes[lot], LOT):
                held = [unpack(bags[b]) for b in lot[j:k]]
                first = np.concatenate([[0], np.cumsum(sizes[lot[j:k]])])
                for t, g in zip(total, gradients(m, np.concatenate(held), first, y[lot[j:k]]), strict=True):
                    t += g * ((k - j) / len(lot))
            for p, g, a, b in zip(m.parts(), total, mean, var, strict=True):
                a += 0.1 * (g - a)
                b += 0.001 * (g * g - b)
                p -= 0.01 * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.999**step)) + 1e-8)
    return m


def held_out(doc_id) -> F.Column:
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("long").cast("string").cast("binary")), F.lit(3)) == 1, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, label: str = "quality") -> Model | None:
    """Fit from at most ``sample`` labelled rows outside the held-out third, picked by a hash of the id; None if there are none.

    Rows with a null label or id are left out; a doc_id labelled twice counts with
    its largest label.
    """
    rows = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out("doc_id")).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y"))
    picked = rows.orderBy(F.xxhash64("doc_id", F.lit(29)), "doc_id").limit(sample).groupBy("doc_id").agg(F.max("y").alias("y"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(picked), "doc_id")  # at most ``sample`` ids

    def run(batches):
        for keys, rows, piece in tv.text_batches(batches, 1 << 20):
            x, first = passages(rows)
            packed = [pack(x[a:b]) for a, b in zip(first[:-1], first[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(packed, pa.binary()), piece.column(2)], ["doc_id", "x", "y"])

    got = texts.select("doc_id", "text", "y").mapInArrow(run, "doc_id long, x binary, y int").toArrow()
    order = np.argsort(got["doc_id"].to_numpy(), kind="stable")
    y = got["y"].to_numpy()
    if not len(y):
        return None
    packed = got["x"].to_pylist()
    return fit([packed[k] for k in order], y[order].astype(np.float32))


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row; null text is empty; without a model every score is 0.5."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def run(batches):
        for keys, rows, _ in tv.text_batches(batches, 1 << 20):
            for i in range(0, len(rows), 1000):
                x, first = passages(rows[i : i + 1000])
                s = forward(model, x, first)[0].astype(float) if model is not None else np.full(len(first) - 1, 0.5)
                yield pa.RecordBatch.from_arrays([pa.array(keys[i : i + 1000], pa.int64()), pa.array(s)], ["doc_id", "score"])

    out = docs.mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", held_out("doc_id").alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Documents that the classifier does not reject; columns stay. The text is scored in place, so no join moves it."""
    model = learn(docs, labels)
    fields = docs.columns
    at = fields.index("text")

    def run(batches):
        for batch in batches:
            lens = np.diff(tv.utf8(batch.column(at))[1])
            for i, j in tv.slices(lens, 1 << 20):
                for k in range(i, j, 1000):
                    piece = batch.slice(k, min(1000, j - k))
                    x, first = passages(tv.texts(piece.column(at)))
                    good = forward(model, x, first)[0].astype(float) >= 0.5 if model is not None else np.ones(piece.num_rows, bool)
                    yield piece.filter(pa.array(good))

    return docs.mapInArrow(run, docs.schema)
