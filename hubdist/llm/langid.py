"""Language identification by error-correcting output codes over character n-grams.

Each language gets a codeword; one binary classifier per bit, over hashed counts
of letter n-grams of the whole text, predicts the bits. Decoding sums every bit's
logistic loss, weighted by how well the bit was learned, and takes the codeword
of least loss; a small gap to the next one flags the text as ambiguous.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import textvec as tv
from .pretokens import LETTER, classes

DIMS = 4096
SAMPLE = 1200  # labelled rows that a fit looks at, whatever the input's size


@dataclass
class Model:
    names: list[str]
    code: np.ndarray  # languages x bits, +1 or -1
    weights: np.ndarray  # dims + 1 x bits
    trust: np.ndarray  # bits


@cache
def _letters() -> np.ndarray:
    return classes() == LETTER


def features(rows: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Root of hashed n-gram shares (n = 1, 2, 3) of each text, and whether it has a letter. Runs of anything but letters count as one gap."""
    cp, off = tv.code_points([t.lower() for t in rows])
    cp = np.where(_letters()[cp], cp, 0).astype(np.uint64)
    keep = cp > 0
    after = np.zeros(len(cp), bool)
    after[1:] = keep[:-1]
    after[off[:-1][np.diff(off) > 0]] = False  # a gap belongs to its own text, whatever stands before it in the batch
    keep |= after
    row = np.repeat(np.arange(len(rows)), np.diff(off))[keep]
    cp = cp[keep]
    out = np.zeros(len(rows) * DIMS)
    gram = np.zeros(len(cp), np.uint64)
    for n in range(3):
        if len(cp) <= n:
            break
        gram = gram[: len(cp) - n] * np.uint64(0x9E3779B1) + cp[n:]
        same = row[: len(row) - n] == row[n:]
        h = (tv.fmix(gram + np.uint64(n)) >> np.uint64(40)).astype(np.int64) % DIMS
        out += np.bincount((row[: len(row) - n] * DIMS + h)[same], minlength=len(out))
    out = out.reshape(len(rows), DIMS)
    total = out.sum(axis=1, keepdims=True)
    has = np.bincount(row, weights=cp > 0, minlength=len(rows)) > 0
    return np.sqrt(out / np.maximum(total, 1)), has


def codewords(n: int, seed: int = 5) -> np.ndarray:
    """Codewords as rows of +1 and -1: every split of the languages while these are few, else random splits with the largest least distance found."""
    if n <= 7:
        bits = max(1, 2 ** (n - 1) - 1)
        out = np.ones((n, bits), int)
        for b in range(bits):
            for i in range(1, n):
                out[i, b] = 1 if (b >> (i - 1)) & 1 else -1
        return out
    bits, rng = 15 + math.ceil(10 * math.log2(n)), np.random.default_rng(seed)
    best, far = None, -1
    for _ in range(50):
        c = rng.choice([-1, 1], (n, bits))
        gram = c @ c.T - 2 * bits * np.eye(n, dtype=int)
        d = (bits - gram.max()) // 2
        if d > far and (abs(c.sum(axis=0)) < n).all():
            best, far = c, d
    return best


def fit(x: np.ndarray, y: list[str], steps: int = 400) -> Model:
    """Logistic bit classifiers by gradient descent with momentum; trust of a bit is its accuracy on the sample above chance."""
    names = sorted(set(y))
    code = codewords(len(names))
    t = code[[names.index(v) for v in y]].astype(float)
    x = np.hstack([x, np.ones((len(x), 1))])
    share = np.bincount([names.index(v) for v in y], minlength=len(names))
    weight = np.array([1.0 / share[names.index(v)] for v in y])
    weight /= weight.sum()
    w, m = np.zeros((x.shape[1], code.shape[1])), np.zeros((x.shape[1], code.shape[1]))
    for _ in range(steps):
        g = x.T @ (-t / (1 + np.exp(np.clip(t * (x @ w), -30, 30))) * weight[:, None]) + 1e-5 * w
        m = 0.9 * m - 2.0 * g
        w += m
    right = ((x @ w * t > 0) * weight[:, None]).sum(axis=0)
    return Model(names, code, w, np.maximum(2 * right - 1, 0.05))


def predict(model: Model, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Index of the language, its share of belief, and the gap to the next."""
    f = np.hstack([x, np.ones((len(x), 1))]) @ model.weights
    loss = np.stack([(model.trust * np.log1p(np.exp(np.clip(-f * c, -30, 30)))).sum(axis=1) for c in model.code], axis=1)
    p = np.exp(-(loss - loss.min(axis=1, keepdims=True)))
    p /= p.sum(axis=1, keepdims=True)
    top = np.sort(p, axis=1)
    gap = top[:, -1] - (top[:, -2] if p.shape[1] > 1 else 0)
    return p.argmax(axis=1), p.max(axis=1), gap


def learn(docs: DataFrame, sample: int = SAMPLE) -> Model | None:
    """Fit from the rows of ``docs`` (doc_id, text, lang), even over languages and picked by a hash of the id; None without any.

    Each language gives at most ``sample`` divided by their number, but 4 at least, so the
    rows are at most the larger of ``sample`` and 4 a language; no language is left out.
    """
    known = docs.where("lang is not null and text is not null and doc_id is not null")
    counts = {r[0]: r[1] for r in known.groupBy("lang").count().collect()}
    if not counts:
        return None
    quota = max(4, sample // len(counts))
    share = F.create_map(*[v for k, n in counts.items() for v in (F.lit(k), F.lit(min(1.0, 1.5 * quota / n + 8 / n)))])
    draw = F.pmod(F.xxhash64(F.col("doc_id").cast("long"), F.lit(11)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    picked = known.where(draw < share[F.col("lang")]).select(F.col("text"), F.col("lang"), draw.alias("draw"))

    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 100):
                part = batch.slice(i, 100)
                x, has = features(tv.texts(part.column(0)))
                keep = pa.array(np.flatnonzero(has))
                flat = x[has].astype(np.float32)
                yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(np.arange(len(flat) + 1) * DIMS, pa.int32()), pa.array(flat.ravel())), part.column(1).take(keep), part.column(2).take(keep)], ["x", "lang", "draw"])

    got = picked.mapInArrow(run, "x array<float>, lang string, draw double")
    place = F.row_number().over(Window.partitionBy("lang").orderBy("draw"))
    got = got.withColumn("place", place).where(F.col("place") <= quota).orderBy("draw", "lang").toArrow()
    y = got["lang"].to_pylist()
    if not y:
        return None
    return fit(got["x"].combine_chunks().flatten().to_numpy().reshape(len(y), DIMS).astype(float), y)


def identify(docs: DataFrame, model: Model | None, ambiguous_below: float = 0.2) -> DataFrame:
    """(doc_id, lang_pred, score, ambiguous) for every row; `und` with score 0 if the text is null or has no letter, or nothing was learned."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def run(batches):
        for keys, rows, _ in tv.text_batches(batches, 1 << 20):
            for i in range(0, len(rows), 500):
                x, has = features(rows[i : i + 500])
                if model is None:
                    k, p, gap, has, names = np.zeros(len(x), int), np.zeros(len(x)), np.zeros(len(x)), np.zeros(len(x), bool), ["und"]
                else:
                    (k, p, gap), names = predict(model, x), model.names
                lang = [names[a] if b else "und" for a, b in zip(k.tolist(), has.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(keys[i : i + 500], pa.int64()), pa.array(lang), pa.array(np.where(has, p, 0.0)), pa.array(~has | (gap < ambiguous_below))], ["doc_id", "lang_pred", "score", "ambiguous"])

    return docs.mapInArrow(run, "doc_id long, lang_pred string, score double, ambiguous boolean")
