"""Language identification (operator 8): script ranges, word scores and a Viterbi path.

The script of a word (by the ranges of its bytes) narrows its languages to those seen in
that script.  A word's scores are log-probabilities from counts of byte trigrams, and of the
word itself where it was seen.  A Viterbi path over the words, with a penalty for each
change of language, labels spans; the language that covers most letters is the prediction.

The path needs no search in most texts: if no stretch, each word by the best of the other
languages, gains more over the best single language than a change costs, staying in that language is optimal, which prefix sums show
for all documents of a slice at once.  Other texts get the full recurrence.

A text that is like no language (junk, unlearned languages and scripts) is ``und``: its mean
log-probability of trigrams, each by the language that likes it best, is under a cut between
that of the labelled texts and that of the same texts with their letters shuffled.

Fitted on the texts and languages of at most ``SAMPLE`` documents; every text is read whole.
Nulls: a null text has no letters and is ``und`` with score 0; rows with a null lang or
doc_id teach nothing.  Repeated rows give repeated results, an empty table an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

SAMPLE = 6000
TRI_BITS, WORD_BITS = 16, 18
#: Cost of a change of language, and the most that a word can tell between languages (nats).
SWITCH, MOST = 14.0, 6.0
#: Texts under this score are rejected: those that are like no language that was learned are ``und`` and have 0.
REJECT = 0.1
#: The share of labelled texts that may be less usual than all others when the cut is set.
RARE = 0.001

#: Scripts by the first byte of a character outside ASCII.
_SCRIPT = np.zeros(256, np.int64)
for _lo, _hi, _k in ((0xC3, 0xCB, 0), (0xCD, 0xCF, 1), (0xD0, 0xD3, 2), (0xD6, 0xD7, 3), (0xD8, 0xDB, 4), (0xE0, 0xE0, 5), (0xE1, 0xE1, 6), (0xE3, 0xE3, 7), (0xE4, 0xE9, 8), (0xEA, 0xED, 9)):
    _SCRIPT[_lo : _hi + 1] = _k
SCRIPTS = 10


@dataclass
class Model:
    langs: list[str]
    tri: np.ndarray  # bucket x language
    word: np.ndarray  # bucket x language; a row of zeros for an unseen word
    allowed: np.ndarray  # script x language: 0, or a large negative score
    usual: np.ndarray  # log-probability of a bucket in the language that likes it best
    cut: float  # texts with a lower mean of these are in no language


def _trigrams(s: K.Slice) -> np.ndarray:
    """The bucket of the three bytes around each byte, with spaces for what is not a letter."""
    b = np.where(K.LETTERS[s.raw], K.FOLD[s.raw], 32).astype(np.uint32)
    before, after = np.append(np.uint32(32), b[:-1]), np.append(b[1:], np.uint32(32))
    h = (before * np.uint32(0x9E3779B1)) ^ (b * np.uint32(0x85EBCA77)) ^ (after * np.uint32(0xC2B2AE3D))
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x2C1B3C6D)
    return h >> np.uint32(32 - TRI_BITS)


def _word_rows(w: K.Words) -> np.ndarray:
    return (w.hashes() >> np.uint64(64 - WORD_BITS)).astype(np.int64)


def _scripts(s: K.Slice, w: K.Words) -> np.ndarray:
    """The script of a word: the highest of its bytes' scripts (Latin is 0)."""
    if not len(w.begin):
        return np.zeros(0, np.int64)
    return np.maximum.reduceat(_SCRIPT[s.raw], w.begin)


def fit(texts: list[tuple[str, str]]) -> Model:
    """Trains on (lang, text) pairs."""
    langs = sorted({x[0] for x in texts})
    n = len(langs)
    tri, word, seen = np.zeros((1 << TRI_BITS, n)), np.zeros((1 << WORD_BITS, n)), np.zeros((SCRIPTS, n))
    for k, lang in enumerate(langs):
        for s in K.slices(pa.array([t for x, t in texts if x == lang], pa.large_string())):
            w = K.words(s, K.LETTERS)
            if len(w.begin):
                inside = K.LETTERS[s.raw]
                tri[:, k] += np.bincount(_trigrams(s)[inside], minlength=1 << TRI_BITS)
                word[:, k] += np.bincount(_word_rows(w), minlength=1 << WORD_BITS)
                seen[:, k] += np.bincount(_scripts(s, w), minlength=SCRIPTS)
    logs = np.log((tri + 0.5) / (tri.sum(axis=0) + 0.5 * (1 << 12)))
    usual = logs.max(axis=1, initial=-1e9).astype(np.float32)
    logs -= logs.mean(axis=1, keepdims=True) if n else 0
    own = np.log((word + 0.3) / (word.sum(axis=0) + 1))
    own = (own - (own.mean(axis=1, keepdims=True) if n else 0)) * (word.sum(axis=1, keepdims=True) >= 2)
    share = seen / np.maximum(seen.sum(axis=0), 1)
    allowed = np.where(share >= 0.001, 0.0, -3 * MOST)
    allowed[allowed.max(axis=1, initial=-1e9) < 0] = 0  # a script of none of them rules none out
    return Model(langs, logs.astype(np.float32), own.astype(np.float32), allowed, usual, _cut([t for _, t in texts], usual))


def _means(s: K.Slice, usual: np.ndarray) -> np.ndarray:
    """The mean log-probability of the letters of each document of a slice that has any."""
    inside = K.LETTERS[s.raw]
    sums, n = np.append(0, np.cumsum(np.where(inside, usual[_trigrams(s)], 0), dtype=np.float64)), np.append(0, np.cumsum(inside))
    letters = n[s.to] - n[s.at]
    return ((sums[s.to] - sums[s.at]) / np.maximum(letters, 1))[letters > 0]


def _cut(texts: list[str], usual: np.ndarray, seed: int = 5) -> float:
    """Half way between the least usual labelled texts and the median of the same texts with shuffled letters."""
    r, clean, junk = np.random.default_rng(seed), [np.zeros(0)], [np.zeros(0)]
    for s in K.slices(pa.array(texts, pa.large_string())):
        clean.append(_means(s, usual))
        raw = s.raw.copy()
        for a, b in zip(s.at.tolist(), s.to.tolist(), strict=True):
            at = a + np.flatnonzero(K.LETTERS[raw[a:b]])
            raw[at] = r.permutation(raw[at])
        junk.append(_means(K.Slice(s.first, raw, s.at, s.to), usual))
    clean, junk = np.concatenate(clean), np.concatenate(junk)
    if not len(clean):
        return -np.inf
    low = float(np.quantile(clean, RARE))
    return min(low, (low + float(np.median(junk))) / 2)


def word_scores(s: K.Slice, m: Model) -> tuple[K.Words, np.ndarray, np.ndarray]:
    """The words of a slice, their scores by language, and how usual their letters are."""
    w = K.words(s, K.LETTERS)
    b = _trigrams(s)
    out = np.empty((len(w.begin), len(m.langs)))
    for k in range(len(m.langs)):
        sums = np.append(0, np.cumsum(m.tri[b, k], dtype=np.float64))
        out[:, k] = sums[w.end] - sums[w.begin]
    out += m.word[_word_rows(w)]
    out += m.allowed[_scripts(s, w)]
    out -= out.max(axis=1, keepdims=True, initial=-1e30)
    sums = np.append(0, np.cumsum(m.usual[b], dtype=np.float64))
    return w, np.maximum(out, -MOST), sums[w.end] - sums[w.begin]


def viterbi(scores: np.ndarray, switch: float = SWITCH) -> np.ndarray:
    """The best path of one document."""
    n = len(scores)
    best, back = scores[0].copy(), np.empty(scores.shape, np.int8)
    stay = np.arange(scores.shape[1])
    for t in range(1, n):
        top = int(best.argmax())
        move = best[top] - switch > best
        back[t] = np.where(move, top, stay)
        best = np.where(move, best[top] - switch, best) + scores[t]
    path = np.empty(n, np.int64)
    path[-1] = best.argmax()
    for t in range(n - 1, 0, -1):
        path[t - 1] = back[t, path[t]]
    return path


def label(s: K.Slice, m: Model) -> list[tuple[str, float, list[tuple[int, int, str]]]]:
    """(language, score, spans of words) of each document of a slice."""
    w, scores, usual = word_scores(s, m)
    n, langs = len(s), len(m.langs)
    first, last = w.doc[:-1], w.doc[1:]
    sums = np.vstack([np.zeros(langs), np.cumsum(scores, axis=0)])
    total = sums[last] - sums[first]
    top = total.argmax(axis=1) if langs else np.zeros(n, np.int64)
    # The most that any stretch gains without the top language: of prefix sums of differences, the largest rise.
    gain = np.zeros(n)
    doc = np.repeat(np.arange(n), last - first)
    if langs > 1 and len(doc):
        other, at = scores.copy(), np.arange(len(doc))
        other[at, top[doc]] = -np.inf
        d = np.cumsum(other.max(axis=1) - scores[at, top[doc]])
        before = np.append(0, d)[:-1]
        # Each document's part is moved far below the one before, so a running minimum starts anew in it.
        far = -doc * (np.abs(d).max() * 2 + 1)
        rise = d + far - np.minimum.accumulate(before + far)
        gain[last > first] = np.maximum(0, np.maximum.reduceat(rise, first[last > first]))
    out = []
    size = w.end - w.begin
    sized, usual = np.append(0, np.cumsum(size)), np.append(0, np.cumsum(usual))
    for i in range(n):
        a, b = int(first[i]), int(last[i])
        if a == b or not langs or not _lettered(s, i, w, a, b) or usual[b] - usual[a] < m.cut * (sized[b] - sized[a]):
            out.append(("und", 0.0, []))
            continue
        if gain[i] <= SWITCH:
            k, share, spans = int(top[i]), 1.0, [(0, b - a, m.langs[int(top[i])])]
        else:
            path = viterbi(scores[a:b])
            letters = np.bincount(path, size[a:b], langs)
            k = int(letters.argmax())
            share = letters[k] / (sized[b] - sized[a])
            cut = np.flatnonzero(np.diff(path)) + 1
            ends = [0, *cut.tolist(), b - a]
            spans = [(x, y, m.langs[path[x]]) for x, y in zip(ends, ends[1:], strict=False)]
        other = np.delete(total[i], k).max(initial=-1e30)
        lead = (total[i, k] - other) / np.sqrt(b - a)
        out.append((m.langs[k], float(share / (1 + np.exp(-np.clip(4 * lead, 0, 30)))) if langs > 1 else 1.0, spans))
    return out


def _lettered(s: K.Slice, i: int, w: K.Words, a: int, b: int) -> bool:
    head = s.raw[w.begin[a] : w.end[b - 1]]
    return bool((K.LETTERS[head] & (head < 128)).any()) or any(c.isalpha() for c in s.text(i).decode())


def sample(docs: DataFrame, most: int = SAMPLE) -> list[tuple[str, str]]:
    """(lang, text) of at most ``most`` documents outside the held-out fold: those whose ids have the smallest hashes."""
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang").where("lang IS NOT NULL AND doc_id IS NOT NULL").where(K.crc_mod("doc_id", 5) != 0)
    ids = ids.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string"), F.col("text").cast("string")).join(F.broadcast(ids), "doc_id", "left_semi")
    return sorted((r["lang"], r["text"]) for r in rows.where("lang IS NOT NULL").select("lang", "text").collect() if r["text"])


def identify(docs: DataFrame, m: Model) -> DataFrame:
    """doc_id, held_out, lang_pred, score and the spans of words by language."""
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("lang", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [x for s in K.slices(b.column(1)) for x in label(s, m)]
            spans = [[{"start": x, "end": y, "lang": z} for x, y, z in r[2]] for r in rows]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.float64()), pa.array(spans, kind)], names=["doc_id", "lang_pred", "score", "spans"])

    out = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, lang_pred string, score double, spans array<struct<start:int,end:int,lang:string>>")
    return out.select("doc_id", (K.crc_mod("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score", "spans")


def keep_identified(docs: DataFrame, m: Model, least: float = REJECT) -> DataFrame:
    """The rows, with all their columns, whose text has letters and whose language is told with a score of ``least`` at least."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            good = [x[0] != "und" and x[1] >= least for s in K.slices(b.column(at)) for x in label(s, m)]
            yield b.filter(pa.array(good, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = K.table(spark, sf_dir, "documents")
    return identify(docs, fit(sample(docs)))
