"""Toxicity scores from a factorization machine over hashed terms.

Terms are a text's distinct lower-case words and their first four and five letters, hashed.
Training takes a bounded, documented number of labelled documents (`max_labelled`, those whose
id hashes lowest), keeps the terms that tell the labels apart and fits bias, weights and
pairwise factors by adaptive gradient steps; every document is then scored whole.

Defined results: null and empty texts score by the bias alone; repeated rows score alike;
null labels teach nothing and a document's contrary labels each count; without labels every score is 0; extra
columns are ignored; very long texts count each term once.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import WordMemo

SPACE, FACTORS, MAX_LABELLED, MAX_TERMS = 1 << 20, 4, 8_000, 4096
WORD = re.compile(r"\w+")


def word_terms(word: str) -> tuple[int, ...]:
    b = word.encode("utf-8", "surrogatepass")
    out = (zlib.crc32(b) % SPACE,)
    for k in (4, 5):
        if len(word) >= k:
            out += (zlib.crc32(b"%d:" % k + word[:k].encode("utf-8", "surrogatepass")) % SPACE,)
    return out


def text_terms(text: str, memo: WordMemo) -> set[int]:
    words = set(WORD.findall(text.lower()))
    memo.learn(words)
    hit: set[int] = set()
    for t in filter(None, map(memo.__getitem__, words)):
        hit.update(t)
    return hit


class Machine:
    """Bias, weights and factors of the chosen terms."""

    def __init__(self, terms: np.ndarray, bias: float):
        self.place = {int(t): k for k, t in enumerate(terms)}
        self.bias, self.w = bias, np.zeros(len(terms) + 1)  # the last one pads
        self.v = np.random.default_rng(7).normal(0, 0.05, (len(terms) + 1, FACTORS))
        self.v[-1] = 0

    def raw(self, idx: np.ndarray):
        v = self.v[idx]
        s = v.sum(axis=1)
        return self.bias + self.w[idx].sum(axis=1) + 0.5 * (s**2 - (v**2).sum(axis=1)).sum(axis=1), v, s

    def rows(self, sets) -> np.ndarray:
        own = [sorted(self.place[t] for t in s if t in self.place) for s in sets]
        out = np.full((len(own), max(map(len, own), default=0) or 1), len(self.w) - 1)
        for k, x in enumerate(own):
            out[k, : len(x)] = x
        return out

    def score(self, sets) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(self.rows(sets))[0], -40, 40)))


def choose_terms(sets, labels: np.ndarray, least: float = 15.0) -> np.ndarray:
    """Terms by likelihood ratio between the classes."""
    flat = np.fromiter((t for s in sets for t in s), np.int64)
    y = np.repeat(labels, [len(s) for s in sets])
    n1, n0 = labels.sum(), len(labels) - labels.sum()
    a, b = np.bincount(flat[y == 1], minlength=SPACE).astype(float), np.bincount(flat[y == 0], minlength=SPACE).astype(float)
    seen = np.nonzero(a + b >= 3)[0]
    a, b = a[seen], b[seen]
    share = (a + b) / (n1 + n0)
    part = lambda x, e: np.where(x > 0, x * np.log(np.maximum(x, 1e-9) / np.maximum(e, 1e-9)), 0)
    g = 2 * (part(a, n1 * share) + part(b, n0 * share) + part(n1 - a, n1 * (1 - share)) + part(n0 - b, n0 * (1 - share)))
    order = np.lexsort((seen, -g))[:MAX_TERMS]
    return seen[order][g[order] >= least]


def fit(sets, labels: np.ndarray, epochs: int = 25, rate: float = 0.3, penalty: float = 1e-4, pair_rate: float = 0.1) -> Machine:
    labels = np.asarray(labels, float)
    if not len(labels) or labels.min() == labels.max():
        m = Machine(np.arange(0), 0.0)
        m.bias = -40.0 if not len(labels) or labels.max() == 0 else 40.0
        return m
    m = Machine(choose_terms(sets, labels), float(np.log(labels.mean() / (1 - labels.mean()))))
    m_idx, rng = [m.rows([s])[0] for s in sets], np.random.default_rng(11)
    gb, gw, gv = 1e-8, np.full(len(m.w), 1e-8), np.full(m.v.shape, 1e-8)
    for _ in range(epochs):
        order = rng.permutation(len(labels))
        for k in range(0, len(order), 256):
            own = order[k : k + 256]
            idx = np.full((len(own), max(len(m_idx[i]) for i in own)), len(m.w) - 1)
            for r, i in enumerate(own):
                idx[r, : len(m_idx[i])] = m_idx[i]
            raw, v, s = m.raw(idx)
            err = (1 / (1 + np.exp(-np.clip(raw, -40, 40))) - labels[own]) / len(own) * 16
            dw = np.bincount(idx.ravel(), np.repeat(err, idx.shape[1]), len(m.w)) + penalty * m.w
            grad = (err[:, None, None] * (s[:, None, :] - v)).reshape(-1, FACTORS)
            dv = np.stack([np.bincount(idx.ravel(), grad[:, f], len(m.w)) for f in range(FACTORS)], axis=1) + penalty * m.v
            dw[-1], dv[-1] = 0, 0
            gb, gw, gv = gb + err.sum() ** 2, gw + dw**2, gv + dv**2
            m.bias -= rate * err.sum() / np.sqrt(gb)
            m.w -= rate * dw / np.sqrt(gw)
            m.v -= pair_rate * rate * dv / np.sqrt(gv)
    return m


def held_out(id_col):
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % 3 == 1


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "toxic", max_labelled: int = MAX_LABELLED) -> Machine:
    """Learns from at most max_labelled labelled rows outside the held-out third."""
    own = labels.select(F.col(id_col).alias("_i"), F.col(label).cast("int").alias("_y")).where(~held_out("_i")).where("_i is not null and _y in (0, 1)")
    own = own.orderBy(F.xxhash64("_i"), "_i", "_y").limit(max_labelled)
    joined = docs.select(F.col(id_col).alias("_i"), F.col(text).alias("_t")).join(F.broadcast(own), "_i")  # max_labelled rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = WordMemo(lambda ws: [word_terms(w) for w in ws], 200_000)
        for b in batches:
            sets = [sorted(text_terms(t or "", memo)) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([np.array(s, "<u4").tobytes() for s in sets], pa.binary())], ["i", "y", "terms"])

    got = joined.select("_i", "_t", "_y").mapInArrow(run, "i long, y int, terms binary").toPandas().sort_values(["i", "y"], kind="stable")
    return fit([np.frombuffer(x, "<u4") for x in got["terms"]], got["y"].to_numpy())


def score(docs: DataFrame, model: Machine, id_col: str = "doc_id", text: str = "text", threshold: float = 0.7, keep: bool = False) -> DataFrame:
    """(doc_id, score, predicted) of every document; keep: all columns of docs, for those not predicted."""
    names = docs.columns if keep else [id_col]
    d = docs.select(*names, F.col(text).alias("_text_of_score"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = model.place
        memo = WordMemo(lambda ws: [tuple(t for t in word_terms(w) if t in place) for w in ws])
        for b in batches:
            for k in range(0, b.num_rows, 1000):
                r = b.slice(k, 1000)
                p = model.score([text_terms(x.as_py() or "", memo) for x in r.column(len(names))])
                if keep:
                    yield r.select(range(len(names))).filter(pa.array(p < threshold))
                else:
                    yield pa.RecordBatch.from_arrays([r.column(0), pa.array(p), pa.array((p >= threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    if keep:
        return d.mapInArrow(run, docs.schema)
    return d.mapInArrow(run, "doc_id long, score double, predicted int").withColumnRenamed("doc_id", id_col)
