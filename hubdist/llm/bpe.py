"""Byte-pair encoding by dynamic programming over prefixes, and decoding.

For every prefix of a word the last token of its encoding is unique. It is the
one token, among the vocabulary entries that end there, which may stand after
the (already known) last token of the shorter prefix. The entries that end at a
place are read off an automaton of reversed tokens; whether two tokens may stand
side by side is decided by undoing their merges from the latest to the earliest.
Following the back-pointers gives exactly the ids of merge-by-merge encoding.

Words repeat, so each executor process keeps a bounded memo of finished words.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textvec as tv
from .pretokens import SPACE, classes, piece_starts

END = "</w>"
MEMO = 400_000


def byte_symbols() -> list[str]:
    """The printable stand-in of every byte: printable Latin-1 bytes stand for themselves, the others for code points from 256."""
    keep = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in keep else chr(next(spare)) for b in range(256)]


class PrefixEncoder:
    """Exact encoder of single words over a merge list."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.ids: dict[str, int] = model["vocab"]
        self.end = model.get("end_of_word_suffix") or ""
        self.text = {i: t for t, i in self.ids.items()}
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.rank = {}
        self.parts: dict[int, tuple[int, int]] = {}
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        for k, m in enumerate(model["merges"]):
            a, b = m.split(" ") if isinstance(m, str) else m
            x, y, z = self.ids[a], self.ids[b], self.ids[a + b]
            self.merge.setdefault((x, y), (k, z))
            if z not in self.rank:
                self.rank[z], self.parts[z] = k, (x, y)
        self.order = {x << 20 | y: k for (x, y), (k, _) in self.merge.items()}
        by_id = [-1] * (max(self.ids.values()) + 1)
        for z, k in self.rank.items():
            by_id[z] = k
        self.rank = by_id
        self.symbols = byte_symbols()
        self.code = {s: b for b, s in enumerate(self.symbols)}
        self.goto: dict[int, int] = {}
        self.accept: dict[int, int] = {}
        self.fits: dict[int, bool] = {}
        self.whole: dict[int, bool] = {}
        states = 1
        for t, i in self.ids.items():
            if t in self.special:
                continue
            at = 0
            for c in reversed(self.split(t)):
                nxt = self.goto.get(at << 9 | c)
                if nxt is None:
                    nxt, states = states, states + 1
                    self.goto[at << 9 | c] = nxt
                at = nxt
            self.accept[at] = i

    def split(self, token: str) -> list[int]:
        """Symbol codes of a token: a byte, plus 256 if the word ends with it."""
        closed = bool(self.end) and token.endswith(self.end)
        out = [self.code[c] for c in (token[: -len(self.end)] if closed else token)]
        if closed:
            out[-1] += 256
        return out

    def base(self, code: int) -> int:
        return self.ids[self.symbols[code & 255] + (self.end if code > 255 else "")]

    def by_merges(self, codes: list[int]) -> list[int]:
        """Encoding by repeated lowest-rank merges; used to judge single tokens and in tests."""
        out = [self.base(c) for c in codes]
        while len(out) > 1:
            k, at = min(((self.merge.get(p, (1 << 30, 0))[0], i) for i, p in enumerate(zip(out, out[1:], strict=False))))
            if k == 1 << 30:
                break
            out[at : at + 2] = [self.merge[out[at], out[at + 1]][1]]
        return out

    def compatible(self, a: int, b: int) -> bool:
        """Whether tokens a, b stay apart when their joint text is merged."""
        key = a << 20 | b
        known = self.fits.get(key)
        if known is not None:
            return known
        limit, ok, order, rank = 1 << 30, True, self.order, self.rank
        while True:
            if order.get(a << 20 | b, limit) < limit:
                ok = False
                break
            ra, rb = rank[a], rank[b]
            if ra < 0 and rb < 0:
                break
            if rb >= ra:  # of equal merges the left one comes first
                limit, b = rb + 1, self.parts[b][0]
            else:
                limit, a = ra, self.parts[a][1]
        if len(self.fits) > 2 * MEMO:
            self.fits.clear()
        self.fits[key] = ok
        return ok

    def alone(self, t: int) -> bool:
        known = self.whole.get(t)
        if known is None:
            known = self.whole[t] = self.by_merges(self.split(self.text[t])) == [t]
        return known

    def encode(self, word: bytes) -> list[int]:
        return next(iter(self.encode_sorted([word])))

    def encode_sorted(self, words: list[bytes]) -> Iterator[list[int]]:
        """Encodings of words in turn; what holds for the prefix shared with the word before is kept, so sorted words are cheapest."""
        goto, accept, fits, joins = self.goto, self.accept, self.fits, self.compatible
        codes: list[int] = []
        last, back = [-1], [0]
        for word in words:
            n, k, most = len(word), 0, min(len(codes), len(word)) - (1 if self.end else 0)
            while k < most and codes[k] == word[k]:
                k += 1
            codes = list(word)
            if self.end and n:
                codes[-1] += 256
            del last[k + 1 :], back[k + 1 :]
            for j in range(k + 1, n + 1):
                at, i, ends = 0, j, []
                while i:
                    at = goto.get(at << 9 | codes[i - 1])
                    if at is None:
                        break
                    i -= 1
                    t = accept.get(at)
                    if t is not None:
                        ends.append((i, t))
                for i, t in reversed(ends):  # one of them fits; the longest most often
                    if not i:
                        ok = self.alone(t)
                    elif (before := last[i]) < 0:
                        ok = False
                    elif (ok := fits.get(before << 20 | t)) is None:
                        ok = joins(before, t)
                    if ok:
                        last.append(t)
                        back.append(i)
                        break
                else:
                    last.append(-1)
                    back.append(0)
            if n and last[n] < 0:
                raise ValueError(f"no encoding of {word!r}")
            out, j = [], n
            while j:
                out.append(last[j])
                j = back[j]
            yield out[::-1]


_ENCODERS: dict[str, PrefixEncoder] = {}
_MEMO: dict[str, dict[bytes, tuple[int, str, str]]] = {}


def encoder(path: str) -> PrefixEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = PrefixEncoder(path)
    return _ENCODERS[path]


def normal(text: str) -> str:
    """The vocabulary's normal form: composed, lower case by single characters."""
    if not unicodedata.is_normalized("NFC", text):
        text = unicodedata.normalize("NFC", text)
    return text.replace("Σ", "σ").lower()


def segments(text: str, special: re.Pattern) -> list[str]:
    return special.split(text) if "<|" in text else [text]


def encode_rows(rows: list[str], path: str) -> Iterator[tuple[list[int], list[str], list[str]]]:
    """For each text: token count per word, id strings per word and token strings per word."""
    enc = encoder(path)
    memo = _MEMO.setdefault(path, {})
    special = re.compile("(" + "|".join(map(re.escape, sorted(enc.special, key=len, reverse=True))) + ")")
    parts = [segments(t, special) for t in rows]
    flat = [normal(s) if k % 2 == 0 else "" for p in parts for k, s in enumerate(p)]
    cp, off = tv.code_points(flat)
    starts = np.flatnonzero(piece_starts(cp, off, keep_space=False))
    ends = np.append(starts[1:], len(cp))
    live = classes()[cp[starts]] != SPACE
    starts, ends = starts[live], ends[live]
    row, _ = tv.spans_of(starts, len(flat), off)
    place = tv.utf8_places(cp)
    data = np.frombuffer("".join(flat).encode("utf-8", "surrogatepass"), np.uint8)
    code, uniq = tv.same_words(tv.words_of(data, place[starts], place[ends]))
    count, ids, toks = np.empty(len(uniq), np.int64), np.empty(len(uniq), object), np.empty(len(uniq), object)
    missing = []
    for k, word in enumerate(uniq.to_pylist()):
        got = memo.get(word)
        if got is None:
            missing.append((word, k))
        else:
            count[k], ids[k], toks[k] = got
    missing.sort()
    if len(memo) + len(missing) > MEMO:
        memo.clear()
    for (word, k), t in zip(missing, enc.encode_sorted([w for w, _ in missing]), strict=True):
        got = count[k], ids[k], toks[k] = len(t), " ".join(map(str, t)), " ".join([enc.text[x] for x in t])
        if len(word) <= 64:
            memo[word] = got
    edge = np.searchsorted(row, np.arange(len(flat) + 1))
    at = 0
    for p in parts:
        n, a, b = [], [], []
        for k, s in enumerate(p):
            if k % 2:
                n, a, b = [*n, 1], [*a, str(enc.special[s])], [*b, s]
            else:
                c = code[edge[at] : edge[at + 1]]
                n.append(int(count[c].sum()))
                a += ids[c].tolist()
                b += toks[c].tolist()
            at += 1
        yield n, a, b


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Token ids of whole texts: (id, ids array<int>). Null text: no ids; repeated rows and null ids stay as they are."""
    docs = docs.select(F.col(id_col).cast("long").alias(id_col), F.col(text_col).alias("text"))

    def run(batches):
        for keys, rows, _ in tv.text_batches(batches):
            ids = [[int(x) for w in a for x in w.split(" ")] for _, a, _ in encode_rows(rows, path)]
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(ids, pa.list_(pa.int32()))], [id_col, "ids"])

    return docs.mapInArrow(run, f"`{id_col}` long, ids array<int>")


def decode(coded: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """Text of token ids as the vocabulary's library gives it without a decoder: tokens joined by one space."""
    coded = coded.select(F.col(id_col).cast("long").alias(id_col), F.col(ids_col).alias("ids"))

    def run(batches):
        enc = encoder(path)
        name = enc.text | {i: t for t, i in enc.special.items()}
        for batch in batches:
            out = [" ".join(name[i] for i in x or ()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], [id_col, "text"])

    return coded.mapInArrow(run, f"`{id_col}` long, text string")


def digests(docs: DataFrame, path: str) -> DataFrame:
    """Encoding and decoding of whole texts as digests; see the contract in ``queries``."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def run(batches):
        sha = lambda x: hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest()
        for keys, rows, _ in tv.text_batches(batches, 1 << 22):
            n, a, b = [], [], []
            for count, ids, toks in encode_rows(rows, path):
                n.append(sum(count))
                a.append(sha(" ".join(ids)))
                b.append(sha(" ".join(toks)))
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(n, pa.int64()), pa.array(a), pa.array(b)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
