"""Best-fit packing of token sequences with matching of the large items (operator 10).

Documents are cut only when longer than a sequence.  Every piece is one row of a few
numbers; the packing itself needs nothing but the histogram of lengths, which has
``capacity`` entries however large the corpus is:

1. items above a third of the capacity: no bin holds three, so they are matched
   greedily, the largest first, each with the largest partner that still fits;
2. the others go, longest first, to the bin with the smallest gap that takes them.

The result of the plan is a list of allocations (length, first rank, bins, items per bin,
place).  Pieces find theirs by their rank among the pieces of equal length, which is
counted in salted groups, so one very common length does not meet in one task.

Nulls: a null text is an empty one (it still gets its end token); a null doc_id stays null.
Repeated rows are separate documents.  An empty table gives an empty result.
"""

from __future__ import annotations

import bisect
import os
import re
import sys
import threading
import zlib
from array import array
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernels as K

CAPACITY = 2048
SALTS = 128
#: Chunks of text whose ids a worker keeps, in each of two tables.
KEEP = 1 << 19
#: Seconds after its last task in which a worker keeps known chunks; tasks of other stages get the memory then.
IDLE_S = 3.0
#: Documents whose new words are encoded together.
GROUP = 64
#: Whole-text encoding is needed where a chunk's surroundings could matter.
_WHOLE = re.compile("<\\||[\x1c-\x1f]")
#: Marks that make a run of their own after letters (an apostrophe may begin a suffix).
_MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Encoder:
    """Token ids of whole texts.

    The vocabulary's rules never join what white space separates, nor a word's letters and a
    mark after them, and they read capitals as small letters.  So the ids of a text are those
    of its chunks in order, and a new chunk often is made of known parts.  Known chunks are kept
    in two tables of at most about ``keep`` each: when the young one is full it becomes the old
    one, from which chunks that come again are taken over.  A worker process outlives its stage,
    so the tables are emptied when no task has used them for ``IDLE_S`` seconds.
    """

    def __init__(self, path: str, keep: int = KEEP):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model, self.keep = Tokenizer.from_file(path), keep
        self.ids: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.tasks, self.timer, self.lock = 0, None, threading.Lock()
        self.ends = np.array([(self.model.id_to_token(i) or "").endswith("</w>") for i in range(self.model.get_vocab_size())])

    def encode(self, text: str) -> bytes:
        return pack_ids(self.model.encode(text, add_special_tokens=False).ids)

    def parts(self, chunk: str) -> tuple[str, ...]:
        """Chunks with the same ids, in order: letters and the marks after them, in small letters."""
        word = chunk.rstrip(_MARKS)
        if len(word) < len(chunk):
            return (*self.parts(word), chunk[len(word) :]) if word.isalpha() else (chunk,)
        low = chunk.lower()
        return (low,) if low != chunk and max(chunk) < "\u0100" and chunk.isalpha() else (chunk,)

    def encode_words(self, chunks: list[str]) -> Iterator[bytes]:
        """Ids of each chunk.  Other words of letters alone than small ASCII ones are encoded as one text and cut at the ids that end a word."""
        small = {c for c in chunks if c.isascii() and c.isalpha() and c.islower()}
        plain = [c for c in chunks if c.isalpha() and c not in small]
        ids = np.array(self.model.encode_batch_fast([" ".join(plain)], add_special_tokens=False)[0].ids, "<u4")
        cut = np.flatnonzero(self.ends[ids]) + 1
        if len(cut) != len(plain):
            yield from map(self.encode, chunks)
            return
        raw, cut = ids.tobytes(), (cut * 4).tolist()
        of = {c: raw[a:b] for c, a, b in zip(plain, [0, *cut], cut, strict=False)}
        rest = [c for c in chunks if c not in of and c not in small]
        of.update(zip(rest, (pack_ids(e.ids) for e in self.model.encode_batch_fast(rest, add_special_tokens=False)), strict=True))
        tokens = self.model.model.tokenize  # the byte alphabet of small ASCII letters is these letters
        for c in chunks:
            yield pack_ids([t.id for t in tokens(c)]) if c in small else of[c]

    def learn(self, chunks: set[str]) -> None:
        """Puts the ids of chunks that the young table has not into it."""
        known = self.old.keys() & chunks
        self.ids.update((c, self.old[c]) for c in known)
        own = {c: self.parts(c) for c in chunks - known}
        new = list({p for v in own.values() for p in v}.difference(self.ids))
        self.ids.update(zip(new, self.encode_words(new), strict=True))
        self.ids.update((c, b"".join([self.ids[p] for p in v])) for c, v in own.items() if c not in self.ids)

    def __call__(self, texts: list[str]) -> list[bytes]:
        chunks = [None if _WHOLE.search(t) else t.split() for t in texts]
        if len(self.ids) > self.keep:
            self.old, self.ids = self.ids, {}
        if new := set().union(*[c for c in chunks if c]).difference(self.ids):
            self.learn(new)
        of = self.ids.__getitem__
        return [self.encode(t) if c is None else b"".join(map(of, c)) for t, c in zip(texts, chunks, strict=True)]

    def __enter__(self) -> Encoder:
        with self.lock:
            self.tasks += 1
            if self.timer:
                self.timer.cancel()
        return self

    def __exit__(self, *_: object) -> None:
        with self.lock:
            self.tasks -= 1
            self.timer = threading.Timer(IDLE_S, self.forget)
            self.timer.daemon = True
            self.timer.start()

    def forget(self) -> None:
        with self.lock:
            if not self.tasks:
                self.ids, self.old = {}, {}


@cache
def encoder(path: str) -> Encoder:
    """One encoder for all tasks of a worker process."""
    return Encoder(path)


def pack_ids(ids: list[int]) -> bytes:
    out = array("I", ids)
    if sys.byteorder == "big":
        out.byteswap()
    return out.tobytes()


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """One row per piece of each document: its place in the document, its length and the CRC of its ids."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        end = np.array([end_id], "<u4").tobytes()
        with encoder(tokenizer) as of:
            for b in batches:
                ids, rows = b.column(0).to_pylist(), []
                for i in range(0, len(ids), GROUP):
                    for j, own in enumerate(of([t or "" for t in b.column(1).slice(i, GROUP).to_pylist()])):
                        own += end
                        for k, at in enumerate(range(0, len(own), 4 * capacity)):
                            part = own[at : at + 4 * capacity]
                            rows.append((ids[i + j], k, at // 4, len(part) // 4, zlib.crc32(part)))
                if rows:
                    c = list(zip(*rows, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int32()), *(pa.array(x, pa.int64()) for x in c[2:])], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(encode, PIECES)


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Allocations (length, first rank, first sequence, bins, items per bin, offset) and the number of sequences.

    Deterministic: it depends on the counts alone.
    """
    left = {n: c for n, c in counts.items() if c}
    done: dict[int, int] = dict.fromkeys(left, 0)
    out: list[tuple[int, int, int, int, int, int]] = []
    gaps: list[int] = []  # sorted gap sizes
    open_: dict[int, list[tuple[int, int]]] = {}  # gap: ranges of sequences (first, how many)
    used = 0

    def put(length: int, first: int, bins: int, each: int, offset: int) -> None:
        out.append((length, done[length], first, bins, each, offset))
        done[length] += bins * each
        left[length] -= bins * each

    def keep(gap: int, first: int, bins: int) -> None:
        if gap and bins:
            if gap not in open_:
                bisect.insort(gaps, gap)
                open_[gap] = []
            open_[gap].append((first, bins))

    large = sorted(n for n in left if 3 * n > capacity)
    for n in reversed(large):
        while left[n]:
            k = bisect.bisect_right(large, min(capacity - n, n)) - 1
            while k >= 0 and (left[large[k]] == 0 or large[k] == n and left[n] < 2):
                k -= 1
            if k < 0:
                bins = left[n]
                put(n, used, bins, 1, 0)
                keep(capacity - n, used, bins)
            elif (m := large[k]) == n:
                bins = left[n] // 2
                put(n, used, bins, 2, 0)
                keep(capacity - 2 * n, used, bins)
            else:
                bins = min(left[n], left[m])
                put(n, used, bins, 1, 0)
                put(m, used, bins, 1, n)
                keep(capacity - n - m, used, bins)
            used += bins
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        while left[n]:
            k = bisect.bisect_left(gaps, n)
            if k == len(gaps):
                each = min(capacity // n, left[n])
                bins = left[n] // each
                put(n, used, bins, each, 0)
                keep(capacity - each * n, used, bins)
                used += bins
                continue
            gap = gaps[k]
            first, bins = open_[gap].pop()
            if not open_[gap]:
                del open_[gap], gaps[k]
            each = min(gap // n, left[n])
            take = min(bins, left[n] // each)
            put(n, first, take, each, capacity - gap)
            keep(gap - each * n, first, take)
            keep(gap, first + take, bins - take)
    return out, used


def pack(rows: DataFrame, capacity: int = CAPACITY, salts: int = SALTS) -> DataFrame:
    """Adds sequence_id and offset to pieces (doc_id, piece, start, length, ids_crc32)."""
    rows = K.durable(rows.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int")))
    # At most capacity x salts rows, whatever the corpus.
    cells = rows.groupBy("length", "_salt").count().collect()
    before = np.zeros((capacity + 1, salts + 1), np.int64)
    for c in cells:
        before[c["length"], c["_salt"] + 1] = c["count"]
    before = before.cumsum(axis=1)
    allocations, _ = plan({n: int(before[n, -1]) for n in range(1, capacity + 1) if before[n, -1]}, capacity)
    allocations.sort()
    a = np.array(allocations, np.int64).reshape(-1, 6)
    keys = a[:, 0] * (1 << 48) + a[:, 1]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = b.column("length").to_numpy()
            rank = before[n, b.column("_salt").to_numpy()] + b.column("_rank").to_numpy() - 1
            r = a[np.searchsorted(keys, n * (1 << 48) + rank, "right") - 1]
            inside = rank - r[:, 1]
            arrays = [b.column(c) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(r[:, 2] + inside // r[:, 4]), pa.array(r[:, 5] + inside % r[:, 4] * n)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    ranked = rows.withColumn("_rank", F.row_number().over(Window.partitionBy("length", "_salt").orderBy("doc_id", "piece", "ids_crc32")).cast("long"))
    return ranked.mapInArrow(place, PIECES + ", sequence_id long, offset long")


def op10_best_fit_packing(spark: SparkSession, sf_dir: str, tokenizer: str | None = None) -> DataFrame:
    import public_tokenizers

    docs = K.table(spark, sf_dir, "documents")
    return pack(pieces(docs, tokenizer or public_tokenizers.path("word_bpe_49k.json")))
