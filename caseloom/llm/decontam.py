"""Benchmark decontamination by latent semantic retrieval (operator 4).

1. Items are cut into passages of words.  Document frequencies of their terms are counted
   over all documents.
2. A randomised SVD of the items' TF-IDF passages, computed over partitions (each returns a
   sketch of fixed size: slots x rank), gives the latent space.
3. Every document is read in overlapping windows.  A window with hardly any weight on the items'
   terms is passed over; the others are compared with all item passages by cosine in the latent
   space: passages have length 1 there, windows are divided by their whole weight.  At a rank far
   below the number of passages that is less than 1 for a verbatim copy, too; so beside this,
   every place that shares ``GRAM`` words in a row with a passage is a candidate.
4. A candidate is verified by the longest common subsequence (LCS) of words with the whole item
   and with the passage.  A share of ``STRONG``, or ``RUN`` words of the passage in a row, tells
   alone.  A share of ``LCS`` needs an answer check: of the item's last words, with which it is
   answered, at least ``ANSWER`` must be near the window.

Items are taken in blocks of ``BLOCK`` passages, each against all documents, so what a task
holds is bounded whatever the benchmark's size.

Nulls: null texts are empty; items without a word and documents without one match nothing;
null ids stay null.  Repeated rows give repeated results, empty tables an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

WINDOW, STRIDE, PASSAGE, PASSAGE_STRIDE = 40, 14, 40, 20
RANK, SLOTS, BLOCK = 256, 1 << 15, 32768
COSINE, LCS, ANSWER, LAST = 0.3, 0.6, 0.5, 8
#: Words in a row that make a candidate; share of the common subsequence, and words in a row, that need no answer check.
GRAM, STRONG, RUN = 4, 0.8, 20
#: Partitions of a block of items for the SVD, each of which sends a sketch to the driver.
SKETCHES = 8


@dataclass
class Items:
    """A block of item passages; ``terms`` are the sorted hashes of their words."""

    ids: list[int | None]
    words: list[np.ndarray]  # hashes of each item's words, in order
    places: list[np.ndarray]  # their places among the terms
    passages: list[tuple[int, int, int]]  # item, first word, word after the last
    terms: np.ndarray
    idf: np.ndarray
    top_idf: float
    basis: np.ndarray  # slots x rank
    latent: np.ndarray  # passages x rank, divided by the passage's weight in this space
    grams: np.ndarray  # sorted hashes of the passages' runs of GRAM words
    owners: np.ndarray  # the passage of each
    bags: np.ndarray  # the terms of each passage, in rows of PASSAGE
    least: np.ndarray  # how many of them must stand near a place

    def slots(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place of each hash among the terms, and whether it is one."""
        at = np.minimum(np.searchsorted(self.terms, h), len(self.terms) - 1)
        return at, self.terms[at] == h


def hashes(texts: list[str | None]) -> list[np.ndarray]:
    out = []
    for s in K.slices(pa.array(texts, pa.large_string())):
        w = K.words(s, K.ALNUM)
        h = w.hashes()
        out += [h[w.doc[i] : w.doc[i + 1]] for i in range(len(s))]
    return out


def frequencies(docs: DataFrame, terms: np.ndarray) -> tuple[np.ndarray, int]:
    """In how many documents each term stands, and the number of documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, n = np.zeros(len(terms), np.int64), 0
        for b in batches:
            n += b.num_rows
            for s in K.slices(b.column(0)):
                w = K.words(s, K.ALNUM)
                h = w.hashes()
                at = np.minimum(np.searchsorted(terms, h), len(terms) - 1)
                hit = np.flatnonzero(terms[at] == h)
                doc = np.searchsorted(w.doc, hit, "right") - 1
                df += np.bincount(np.unique(doc * len(terms) + at[hit]) % len(terms), minlength=len(terms))
        some = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(df[some], n))], names=["term", "df"])

    rows = docs.select(F.col("text").cast("string")).mapInArrow(run, "term long, df long").groupBy("term").agg(F.sum("df").alias("df")).toArrow()
    out, n = np.zeros(len(terms), np.int64), 0
    for t, c in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True):
        if t < 0:
            n = c
        else:
            out[t] = c
    return out, n


def vector(items: Items, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Slots and weights of a bag of words, and its whole weight (words that no item has count as the rarest)."""
    u, tf = np.unique(h, return_counts=True)
    at, known = items.slots(u)
    idf = np.where(known, items.idf[at], items.top_idf)
    weight = np.sqrt(tf) * idf
    return at[known] % min(SLOTS, len(items.terms)), weight[known], float(np.sqrt((weight**2).sum()))


def randomised_svd(spark: SparkSession, rows: list[tuple[np.ndarray, np.ndarray]], slots: int, rank: int, seed: int = 3) -> np.ndarray:
    """Right singular vectors (slots x rank) of sparse rows; the rows are spread, what returns has a fixed size."""
    width = min(rank + 16, slots)
    frame = spark.createDataFrame(pa.table({"s": pa.array([r[0].astype(np.int64).tobytes() for r in rows], pa.binary()), "w": pa.array([r[1].tobytes() for r in rows], pa.binary())}))
    frame = frame.repartition(SKETCHES)

    def over(q: np.ndarray | None) -> np.ndarray:
        sketch = q is None
        size = slots if sketch else width

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            # The random test matrix comes from its seed, so it isn't sent.
            basis = np.random.default_rng(seed).normal(size=(slots, width)) if sketch else q
            out = np.zeros((size, width))
            for b in batches:
                for s, w in zip(b.column(0), b.column(1), strict=True):
                    s, w = np.frombuffer(s.as_py(), np.int64), np.frombuffer(w.as_py())
                    y = w @ basis[s]
                    if sketch:
                        np.add.at(out, s, np.outer(w, y))
                    else:
                        out += np.outer(y, y)
            some = np.flatnonzero(np.abs(out).sum(axis=1))
            yield pa.RecordBatch.from_arrays([pa.array([some.tobytes()], pa.binary()), pa.array([out[some].tobytes()], pa.binary())], names=["rows", "values"])

        total = np.zeros((size, width))
        for r in frame.mapInArrow(run, "rows binary, values binary").toLocalIterator():
            total[np.frombuffer(r["rows"], np.int64)] += np.frombuffer(r["values"]).reshape(-1, width)
        return total

    q, _ = np.linalg.qr(over(None))
    value, turn = np.linalg.eigh(over(q))
    best = np.argsort(-value)[:rank]
    best = best[value[best] > 1e-9 * max(value.max(), 1e-30)]
    return (q @ turn[:, best]).astype(np.float32)


def unit(rows: np.ndarray) -> np.ndarray:
    return (rows / np.maximum(np.linalg.norm(rows, axis=1, keepdims=True), 1e-30)).astype(np.float32)


def prepare(docs: DataFrame, ids: list[int | None], texts: list[str | None]) -> Items | None:
    words = hashes(texts)
    keep = [i for i, w in enumerate(words) if len(w)]
    ids, words = [ids[i] for i in keep], [words[i] for i in keep]
    if not words:
        return None
    passages = []
    for i, w in enumerate(words):
        at = 0
        while True:
            passages.append((i, at, min(at + PASSAGE, len(w))))
            if at + PASSAGE >= len(w):
                break
            at += PASSAGE_STRIDE
    terms = np.unique(np.concatenate(words))
    df, n = frequencies(docs, terms)
    items = Items(ids, words, [np.searchsorted(terms, w) for w in words], passages, terms, np.log((n + 2) / (df + 1)), float(np.log(n + 2)), np.zeros((0, 0)), np.zeros((0, 0)), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.full((len(passages), PASSAGE), len(terms)), np.zeros(len(passages)))
    rows = [vector(items, words[i][a:b]) for i, a, b in passages]
    items.basis = randomised_svd(docs.sparkSession, [r[:2] for r in rows], min(SLOTS, len(terms)), min(RANK, len(rows)))
    items.latent = unit(np.stack([w @ items.basis[s] for s, w, _ in rows]))
    for p, (i, a, b) in enumerate(passages):
        items.bags[p, : b - a] = items.places[i][a:b]
        # Of an item with a share of LCS, one of its half-overlapping passages has two thirds of this at least.
        items.least[p] = min((LCS if b - a == len(words[i]) else LCS * 2 / 3) * (b - a), RUN)
    grams = [np.unique(K.shingles(words[i][a:b], GRAM)) if b - a >= GRAM else np.zeros(0, np.uint64) for i, a, b in passages]
    own, gram = np.repeat(np.arange(len(passages)), [len(g) for g in grams]), np.concatenate(grams)
    order = np.argsort(gram, kind="stable")
    items.grams, items.owners = gram[order], own[order]
    return items


def lcs(a: np.ndarray, b: np.ndarray) -> int:
    """Length of the longest common subsequence, a word of b at a time on bits for the places of a."""
    masks: dict[int, int] = {}
    for i, x in enumerate(a.tolist()):
        masks[x] = masks.get(x, 0) | 1 << i
    full, v = (1 << len(a)) - 1, (1 << len(a)) - 1
    for x in b.tolist():
        m = masks.get(x)
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & full
    return len(a) - v.bit_count()


def longest_run(a: np.ndarray, b: np.ndarray) -> int:
    """The most words in a row that two sequences share."""
    run, most = np.zeros(len(b) + 1, np.int64), 0
    for x in a:
        run[1:] = (run[:-1] + 1) * (b == x)
        most = max(most, int(run.max()))
    return most


def possible(items: Items, passages: np.ndarray, near: np.ndarray, mark: np.ndarray) -> np.ndarray:
    """The passages that can be found near a place: terms that stand there at all bound the common subsequence."""
    mark[near] = True
    mark[-1] = False
    out = passages[mark[items.bags[passages]].sum(axis=1) >= items.least[passages]]
    mark[near] = False
    return out


def verified(items: Items, p: int, t: np.ndarray, first: int, last: int, lo: int, hi: int) -> tuple[float, float] | None:
    """(share, share of the answer) if the item of passage p is found around the words [lo, hi) of a document, the terms [first, last) of t."""
    i, a, b = items.passages[p]
    mine = items.places[i]
    passage = mine[a:b]
    near = t[max(first, lo - PASSAGE - STRIDE) : min(last, hi + PASSAGE + STRIDE)]
    wide = t[max(first, lo - len(mine) - STRIDE) : min(last, hi + len(mine) + STRIDE)]
    most = lcs(passage, near)
    share = max(most / len(passage), lcs(mine, wide) / len(mine) if len(mine) > len(passage) else 0.0)
    if share < LCS and most < RUN:
        return None
    answer = float(np.isin(mine[-LAST:], wide).mean())
    if share >= STRONG or (share >= LCS and answer >= ANSWER) or (most >= RUN and longest_run(passage, near) >= RUN):
        return share, answer
    return None


def gram_places(items: Items, h: np.ndarray, doc: np.ndarray) -> Iterator[tuple[int, int, int, np.ndarray]]:
    """(document, first word, word after the last, passages) of the places that share GRAM words in a row with passages."""
    if len(h) < GRAM or not len(items.grams):
        return
    g = K.shingles(h, GRAM)
    at = np.searchsorted(items.grams, g)
    hit = np.flatnonzero(items.grams[np.minimum(at, len(items.grams) - 1)] == g)
    hit = hit[doc[hit] == doc[hit + GRAM - 1]]
    if not len(hit):
        return
    to = np.searchsorted(items.grams, g[hit], "right")
    cut = np.flatnonzero(np.append(True, (np.diff(doc[hit]) != 0) | (np.diff(hit // WINDOW) != 0)))
    for x, y in zip(cut.tolist(), [*cut[1:].tolist(), len(hit)], strict=True):
        own = np.unique(np.concatenate([items.owners[k:m] for k, m in zip(at[hit[x:y]].tolist(), to[x:y].tolist(), strict=True)]))
        yield int(doc[hit[x]]), int(hit[x]), int(hit[y - 1]) + GRAM, own


def find(s: K.Slice, items: Items) -> list[tuple[int, int, float, float, float]]:
    """(document, item, cosine, common share of the item or passage, share of its answer) of what is verified in a slice."""
    w = K.words(s, K.ALNUM)
    h = w.hashes()
    if not len(h):
        return []
    at, known = items.slots(h)
    weight = np.where(known, items.idf[at], items.top_idf)
    square = np.append(0, np.cumsum(weight**2))
    own = np.append(0, np.cumsum(np.where(known, weight, 0) ** 2))
    many = np.maximum(1, -(-(np.diff(w.doc) - (WINDOW - STRIDE)) // STRIDE)) * (np.diff(w.doc) > 0)
    doc = np.repeat(np.arange(len(s)), many)
    begin = w.doc[doc] + (np.arange(len(doc)) - np.repeat(np.cumsum(many) - many, many)) * STRIDE
    g = np.stack([begin, w.doc[doc + 1], doc], 1)
    end = np.minimum(begin + WINDOW, g[:, 1])
    # Windows need a share of their weight on the items' terms (a term's weight grows as the root of its count).
    g = g[own[end] - own[begin] >= COSINE**2 * (square[end] - square[begin])]

    def latents(places: list[list[int]]) -> np.ndarray:
        out = np.empty((len(places), items.basis.shape[1]), np.float32)
        for k, (a, b) in enumerate(places):
            slot, value, norm = vector(items, h[a:b])
            out[k] = value.astype(np.float32) @ items.basis[slot] / norm
        return out

    # Words that no item has are one more term.
    t, mark = np.where(known, at, len(items.terms)), np.zeros(len(items.terms) + 1, bool)
    found: dict[tuple[int, int], tuple[float, float, float]] = {}

    def look(d: int, lo: int, hi: int, passages: np.ndarray, own: np.ndarray | None) -> None:
        first, last = int(w.doc[d]), int(w.doc[d + 1])
        for p in possible(items, passages, t[max(first, lo - PASSAGE - STRIDE) : min(last, hi + PASSAGE + STRIDE)], mark).tolist():
            i = items.passages[p][0]
            if (d, i) not in found and (v := verified(items, p, t, first, last, lo, hi)):
                found[d, i] = (float((latents([[lo, hi]])[0] if own is None else own) @ items.latent[p]), *v)

    for d, lo, hi, passages in gram_places(items, h, np.repeat(np.arange(len(s)), np.diff(w.doc))):
        look(d, lo, hi, passages, None)
    latent = latents([[a, min(a + WINDOW, b)] for a, b, _ in g.tolist()])
    for k0 in range(0, len(g), 1024):
        near = latent[k0 : k0 + 1024] @ items.latent.T >= COSINE
        for k in np.flatnonzero(near.any(axis=1)).tolist():
            a, b, d = g[k0 + k].tolist()
            look(d, a, min(a + WINDOW, b), np.flatnonzero(near[k]), latent[k0 + k])
    return [(d, i, *v) for (d, i), v in found.items()]


def passages_of(text: str | None) -> int:
    """At most how many passages a text is cut into (words are parted by other bytes than letters and digits)."""
    n = -(-len((text or "").encode()) // 2)
    return 1 + max(0, -(-(n - PASSAGE) // PASSAGE_STRIDE))


def blocks(docs: DataFrame, benchmark: DataFrame) -> Iterator[Items]:
    """Blocks of items of at most ``BLOCK`` passages (a longer item is a block of its own), in order; the driver holds one at a time."""
    ids, texts, size = [], [], 0
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).orderBy("item_id", "text")
    for r in rows.toLocalIterator():
        more = passages_of(r["text"])
        if ids and size + more > BLOCK:
            if items := prepare(docs, ids, texts):
                yield items
            ids, texts, size = [], [], 0
        ids.append(r["item_id"])
        texts.append(r["text"])
        size += more
    if ids and (items := prepare(docs, ids, texts)):
        yield items


RESULT = "doc_id long, item_id long, cosine double, lcs_share double, answer_share double"


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row per document and item found in it."""

    def of(items: Items) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                rows = [(b.column(0)[s.first + d].as_py(), items.ids[i], *v) for s in K.slices(b.column(1)) for d, i, *v in find(s, items)]
                c = list(zip(*rows, strict=True)) if rows else [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), *(pa.array(x, pa.float64()) for x in c[2:])], names=["doc_id", "item_id", "cosine", "lcs_share", "answer_share"])

        return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, RESULT)

    out = docs.sparkSession.createDataFrame([], RESULT)
    for items in blocks(docs, benchmark):
        out = out.unionByName(of(items))
    return out


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows, with all their columns, in whose text no item is found."""
    at = docs.columns.index("text")
    out = docs
    for items in blocks(docs, benchmark):

        def run(batches: Iterator[pa.RecordBatch], items: Items = items) -> Iterator[pa.RecordBatch]:
            for b in batches:
                bad = {s.first + d for s in K.slices(b.column(at)) for d, *_ in find(s, items)}
                yield b.filter(pa.array([i not in bad for i in range(b.num_rows)], pa.bool_()))

        out = out.mapInArrow(run, docs.schema)
    return out


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(K.table(spark, sf_dir, "documents"), K.table(spark, sf_dir, "benchmark"))
