"""Toxicity scores by a factorization machine over hashed terms (operator 2).

Terms are words and the first letters of longer words, hashed into a fixed number of
buckets; a document is the set of its terms.  Logistic loss; besides a linear weight each
term has a short vector, and the inner products of two terms' vectors are weights of their
pair, so an insult next to the mention of a group can count for more than the two alone.

The machine is fitted on at most ``SAMPLE`` labelled documents (a bound, whatever the
corpus); every text is scored whole.  Neither lang, source nor doc_id is an input.

Nulls: null texts are empty, rows with a null label or doc_id teach nothing.  Repeated rows
give repeated results, empty tables an empty result; with no labels all scores are the same.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

BITS, FACTORS, STEM = 20, 8, 5
#: At most so many labelled documents teach; those with the smallest hashes of their ids.
SAMPLE = 16384
#: Terms kept are those in at least MIN_DOCS of them: the most telling ones, and those that tell most among documents
#: with one of the LEADS first of these (by SURE standard errors), as a mention does that is neutral by itself.
MIN_DOCS, TERMS, BESIDE, LEADS, SURE = 4, 1500, 500, 64, 5.0
EPOCHS, BATCH, RATE, DECAY, POSITIVE = 16, 128, 0.15, 1e-6, 3.0
#: A toxic document counts as POSITIVE others while learning, as there are fewer.
#: Share of a document's terms left out each time it is learned from.
DROP = 0.3
CUT = 0.7


def terms(s: K.Slice) -> tuple[np.ndarray, np.ndarray]:
    """The buckets of all terms of a slice and the place of each document's first (with the end)."""
    w = K.words(s, K.ALNUM)
    if not len(w.begin):
        return np.zeros(0, np.uint32), np.zeros(len(s) + 1, np.int64)
    both = np.empty((len(w.begin), 2), np.uint64)
    both[:, 0] = w.hashes()
    both[:, 1] = K.mix(w.spans(w.begin, np.minimum(w.begin + STEM, w.end)))
    return (both.ravel() >> np.uint64(64 - BITS)).astype(np.uint32), w.doc * 2


@dataclass
class Machine:
    """bias, linear weights and vectors of the kept buckets; ``slot`` maps a bucket to its row (the last row is zero)."""

    bias: float
    weights: np.ndarray
    vectors: np.ndarray
    slot: np.ndarray

    def raw(self, rows: np.ndarray, docs: np.ndarray, n: int) -> np.ndarray:
        """Scores before the logistic function; (rows, docs) are distinct (term, document) pairs sorted by document."""
        linear = np.bincount(docs, self.weights[rows], n)
        out = self.bias + linear
        for f in range(self.vectors.shape[1]):
            v = self.vectors[rows, f]
            out += 0.5 * (np.bincount(docs, v, n) ** 2 - np.bincount(docs, v * v, n))
        return out

    def score(self, s: K.Slice) -> np.ndarray:
        found, at = terms(s)
        rows = self.slot[found]
        docs = np.repeat(np.arange(len(s)), np.diff(at))
        keep = rows < len(self.weights) - 1
        pairs = np.unique(docs[keep].astype(np.int64) << 32 | rows[keep])
        return sigmoid(self.raw(pairs & 0xFFFFFFFF, pairs >> 32, len(s)))


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def telling(in_pos: np.ndarray, in_neg: np.ndarray, pos: int, neg: int) -> np.ndarray:
    """How much each bucket tells between documents of both labels, from the numbers of documents that have it."""
    a, b = (in_pos + 0.5) / (pos + 1), (in_neg + 0.5) / (neg + 1)
    return np.abs(a - b) * np.abs(np.log(a / b)) * (in_pos + in_neg >= MIN_DOCS)


def fit(sets: list[np.ndarray], labels: np.ndarray, seed: int = 5) -> Machine:
    """Trains on documents given as arrays of distinct buckets, with labels 0 and 1."""
    rng = np.random.default_rng(seed)
    size, n, pos = 1 << BITS, len(sets), int(labels.sum())
    flat = np.concatenate(sets) if n else np.zeros(0, np.uint32)
    lengths = np.array([len(x) for x in sets], np.int64)
    in_pos = np.bincount(flat[np.repeat(labels == 1, lengths)], minlength=size).astype(float)
    in_neg = np.bincount(flat, minlength=size) - in_pos
    owner = np.repeat(np.arange(n), lengths)
    told = telling(in_pos, in_neg, pos, n - pos)
    best = np.argsort(-told, kind="stable")[: min(TERMS, int((told > 0).sum()))]
    # The same among the documents that have one of the terms that speak most for label 1.
    leads = np.zeros(size, bool)
    leads[[t for t in best.tolist() if in_pos[t] * (n - pos) > in_neg[t] * pos][:LEADS]] = True
    with_lead = np.zeros(n, bool)
    with_lead[owner[leads[flat]]] = True
    own = with_lead[owner]
    pos_in = np.bincount(flat[own & (labels == 1)[owner]], minlength=size).astype(float)
    neg_in = np.bincount(flat[own], minlength=size) - pos_in
    n_pos, n_neg = int((with_lead & (labels == 1)).sum()), int((with_lead & (labels != 1)).sum())
    share = (pos_in + neg_in) / max(n_pos + n_neg, 1)
    spread = np.sqrt(share * (1 - share) * (1 / max(n_pos, 1) + 1 / max(n_neg, 1)))
    sure = np.abs(pos_in / max(n_pos, 1) - neg_in / max(n_neg, 1)) > SURE * spread
    beside = telling(pos_in, neg_in, n_pos, n_neg) * sure
    beside[best] = 0
    more = np.argsort(-beside, kind="stable")[: min(BESIDE, int((beside > 0).sum()))]
    kept = np.sort(np.concatenate([best, more]))
    slot = np.full(size, len(kept), np.int64)
    slot[kept] = np.arange(len(kept))
    rows = slot[flat]
    docs = np.repeat(np.arange(n), lengths)[rows < len(kept)]
    rows = rows[rows < len(kept)]
    at = np.searchsorted(docs, np.arange(n + 1))
    m = Machine(float(np.log((pos + 1) / (n - pos + 1))), np.zeros(len(kept) + 1), np.vstack([rng.normal(0, 0.01, (len(kept), FACTORS)), np.zeros(FACTORS)]), slot)
    seen_w, seen_v, seen_b = np.full(len(kept) + 1, 1e-2), np.full(m.vectors.shape, 1e-2), 1e-2
    for _ in range(EPOCHS if n else 0):
        order = rng.permutation(n)
        for k in range(0, n, BATCH):
            own = order[k : k + BATCH]
            many = at[own + 1] - at[own]
            d = np.repeat(np.arange(len(own)), many)
            r = rows[np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many) + np.repeat(at[own], many)]
            told = rng.random(len(r)) >= DROP  # so that one term can do without those it mostly comes with
            d, r = d[told], r[told]
            sums = np.zeros((len(own), FACTORS))
            v = m.vectors[r]
            np.add.at(sums, d, v)
            squares = np.zeros_like(sums)
            np.add.at(squares, d, v * v)
            out = m.bias + np.bincount(d, m.weights[r], len(own)) + 0.5 * (sums**2 - squares).sum(axis=1)
            g = (sigmoid(out) - labels[own]) * np.where(labels[own] > 0, POSITIVE, 1.0)
            u, back = np.unique(r, return_inverse=True)
            gw = np.bincount(back, g[d], len(u)) / len(own) + DECAY * m.weights[u]
            gv = np.zeros((len(u), FACTORS))
            np.add.at(gv, back, g[d, None] * (sums[d] - v))
            gv = gv / len(own) + DECAY * m.vectors[u]
            seen_w[u] += gw**2
            seen_v[u] += gv**2
            gb = g.mean()
            seen_b += gb**2
            m.weights[u] -= RATE * gw / np.sqrt(seen_w[u])
            m.vectors[u] -= RATE * gv / np.sqrt(seen_v[u])
            m.bias -= RATE * gb / seen_b**0.5
    return m


def sample(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> tuple[list[np.ndarray], np.ndarray]:
    """Term sets and labels of at most ``most`` labelled documents outside the held-out fold."""
    own = (
        labels.where("doc_id IS NOT NULL AND toxic IS NOT NULL")
        .where(K.crc_mod("doc_id", 3) != 1)
        .groupBy(F.col("doc_id").cast("long").alias("doc_id"))
        .agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(most)
    )

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for s in K.slices(b.column(2)):
                found, at = terms(s)
                out += [np.unique(found[at[i] : at[i + 1]]).tobytes() for i in range(len(s))]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.binary())], names=["doc_id", "toxic", "terms"])

    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    rows = texts.join(F.broadcast(own), "doc_id").select("doc_id", "toxic", "text").mapInArrow(sets, "doc_id long, toxic int, terms binary").collect()
    rows.sort(key=lambda r: (r["doc_id"], bytes(r["terms"])))
    return [np.frombuffer(r["terms"], np.uint32) for r in rows], np.array([int(r["toxic"] > 0) for r in rows], float)


def predict(docs: DataFrame, m: Machine) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            score = np.concatenate([np.zeros(0), *(m.score(s) for s in K.slices(b.column(1)))])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score)], names=["doc_id", "score"])

    out = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", (K.crc_mod("doc_id", 3) == 1).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = K.table(spark, sf_dir, "documents")
    return predict(docs, fit(*sample(docs, K.table(spark, sf_dir, "labels"))))
