"""Substring dedup by sliding sentence spans (operator 1).

A text is cut into sentences (at ends of sentences and lines; a sentence of more than
``LONGEST`` words is cut at the least word hash of each ``LONGEST`` words in a row, so copies of
a passage are cut alike after any lead-in).  From each sentence starts, and at each ends, the shortest run of at
least ``MIN_SENTENCES`` sentences and ``MIN_WORDS`` words; the hash of its words is a span.
Spans are joined over all documents, and every sentence in a span that is not the first of its
kind (by doc_id, then place) is removed.

Between documents only (hash, doc_id) counts: repeats inside a document are seen where its
text is.  A span's first document is a minimum with partial aggregation, and common spans are
on the side of a join that can be split, so no key meets in one task.

Nulls: a null text is empty (no sentences); rows without a doc_id come after all others.
Rows of equal doc_id are no repeats of each other.  An empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

MIN_SENTENCES, MIN_WORDS, LONGEST = 2, 16, 16
_END = K.lut(".!?")
_LAST = (1 << 63) - 1


def runs(s: K.Slice) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of a slice: first byte and document of each sentence; of each span its first sentence, the sentence after it, and its hash."""
    w = K.words(s, K.NOT_SPACE)
    n = len(w.begin)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, z, z, np.zeros(0, np.uint64)
    doc = np.repeat(np.arange(len(s)), np.diff(w.doc))
    lines = np.append(0, np.cumsum(s.raw == 10))
    new = np.ones(n, bool)
    new[1:] = _END[s.raw[w.end[:-1] - 1]] | (lines[w.begin[1:]] > lines[w.end[:-1]])
    h = K.mix(w.hashes())
    if n >= LONGEST:
        # Of every LONGEST words in a row of a long sentence, one begins at the word of the smallest hash (the last such).
        sentence = np.cumsum(new)
        inside = np.flatnonzero((sentence[: n - LONGEST + 1] == sentence[LONGEST - 1 :]) & (np.bincount(sentence)[sentence[: n - LONGEST + 1]] > LONGEST))
        least = np.lib.stride_tricks.sliding_window_view(h, LONGEST)[inside, ::-1].argmin(axis=1)
        new[inside + LONGEST - 1 - least] = True
    first = np.flatnonzero(new)
    own = doc[first]
    last = np.append(np.searchsorted(own, np.arange(1, len(s) + 1)), 0)[own]  # the sentence after its document's last
    after = np.maximum(np.searchsorted(first, first + MIN_WORDS), np.arange(len(first)) + MIN_SENTENCES)
    # Sentence j ends where j + 1 begins: from the run's begin, at least MIN_WORDS words.
    ends = np.append(first, n)
    good = (after <= last) & (ends[np.minimum(after, len(first))] - first >= MIN_WORDS)
    j = np.arange(1, len(first) + 1)
    before = np.minimum(np.searchsorted(first, ends[j] - MIN_WORDS, "right") - 1, j - MIN_SENTENCES)
    back = (before >= 0) & (own[np.maximum(before, 0)] == own[j - 1])
    both = np.unique(np.concatenate([np.flatnonzero(good) * (len(first) + 1) + after[good], before[back] * (len(first) + 1) + j[back]]))
    at, to = both // (len(first) + 1), both % (len(first) + 1)
    steps = np.full(n, 0xD6E8FEB86659FD93, np.uint64)
    steps[0] = 1
    powers = np.cumprod(steps)
    sums = np.append(np.uint64(0), np.cumsum(h * powers))
    inverse = np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(n - 1, pow(0xD6E8FEB86659FD93, -1, 1 << 64), np.uint64)]))
    hashes = K.mix((sums[ends[to]] - sums[first[at]]) * inverse[first[at]] + (ends[to] - first[at]).astype(np.uint64))
    return w.begin[first], own, at, to, hashes


def _firsts(doc: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Whether a span is the first of its hash in its document; spans are in order of place."""
    order = np.lexsort((np.arange(len(doc)), hashes, doc))
    same = np.zeros(len(doc), bool)
    same[order[1:]] = (doc[order[1:]] == doc[order[:-1]]) & (hashes[order[1:]] == hashes[order[:-1]])
    return ~same


def spans(docs: DataFrame) -> DataFrame:
    """(_id, _th, hash, place) of each document's distinct spans; place is its number among all of the document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists, places = [], []
            for s in K.slices(b.column(2)):
                _, own, at, _, h = runs(s)
                keep = _firsts(own[at], h)
                cut = np.searchsorted(own[at], np.arange(len(s) + 1))
                for i in range(len(s)):
                    mine = np.flatnonzero(keep[cut[i] : cut[i + 1]])
                    lists.append(h[cut[i] + mine].view(np.int64))
                    places.append(mine.astype(np.int32))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(lists, pa.list_(pa.int64())), pa.array(places, pa.list_(pa.int32()))], names=["_id", "_th", "h", "p"])

    found = docs.select("_id", "_th", "text").mapInArrow(run, "_id long, _th long, h array<long>, p array<int>")
    return found.select("_id", "_th", F.explode(F.arrays_zip("h", "p")).alias("_s")).select("_id", "_th", F.col("_s.h").alias("hash"), F.col("_s.p").alias("place"))


RESULT = "doc_id long, n_sentences long, n_removed long, n_bytes long, n_removed_bytes long, text string"


def dedup(docs: DataFrame) -> DataFrame:
    """One row per document: its text without repeated spans, and counts of sentences and bytes."""
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("_id"), F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("_th"), F.col("doc_id").cast("long"), F.col("text").cast("string"))
    all_spans = spans(rows)
    repeated = all_spans.groupBy("hash").agg(F.min("_id").alias("_first"), F.max("_id").alias("_most")).where("_first < _most").select("hash", "_first")
    later = all_spans.join(repeated, "hash").where("_id > _first")
    gone = later.groupBy("_id", "_th").agg(F.collect_set("place").alias("_places"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            gone_of, out = b.column(2).to_pylist(), []
            ids = b.column(0).to_pylist()
            for s in K.slices(b.column(1)):
                where, own, at, to, h = runs(s)
                local = ~_firsts(own[at], h)
                begin = np.searchsorted(own, np.arange(len(s) + 1))
                cut = np.searchsorted(own[at], np.arange(len(s) + 1))
                for i in range(len(s)):
                    n = int(begin[i + 1] - begin[i])
                    mark = np.zeros(n + 1, np.int64)
                    x, y = at[cut[i] : cut[i + 1]] - begin[i], to[cut[i] : cut[i + 1]] - begin[i]
                    bad = local[cut[i] : cut[i + 1]].copy()
                    if gone_of[s.first + i]:
                        bad[gone_of[s.first + i]] = True
                    np.add.at(mark, x[bad], 1)
                    np.add.at(mark, y[bad], -1)
                    cover = np.cumsum(mark)[:n] > 0
                    text = s.text(i)
                    kept = text
                    if cover.any():
                        edges = np.append(where[begin[i] : begin[i + 1]] - s.at[i], len(text))
                        edges[0] = 0
                        kept = b"".join(text[edges[k] : edges[k + 1]] for k in np.flatnonzero(~cover))
                    out.append((ids[s.first + i], n, int(cover.sum()), len(text), len(text) - len(kept), kept.decode()))
            c = list(zip(*out, strict=True)) if out else [[]] * 6
            yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in c[:5]), pa.array(c[5], pa.string())], names=[f.split(" ")[0] for f in RESULT.split(", ")])

    return rows.join(gone, ["_id", "_th"], "left").select("doc_id", "text", "_places").mapInArrow(run, RESULT)


def op1_sentence_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(K.table(spark, sf_dir, "documents"))
