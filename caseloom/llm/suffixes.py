"""Exact substring dedup over suffix arrays (operator 7).

Every byte in a string of ``length`` bytes that also starts earlier is removed.

Where to look.  Of all grams in a window of ``length`` bytes, the first with the smallest hash
is its anchor (winnowing), so two equal windows have equal anchors at the same place.  The
windows of one anchor lie side by side; their bytes are its context, which is told by a 64-bit
hash.  Of equal contexts, all but the first are removed at once, in each batch before anything
is sent.  An anchor that is left with one context ends the search.

What repeats.  Contexts of equal anchors, the first of each kind only, meet in a task.  They
are concatenated, with a Burrows-Wheeler transform of the suffixes ordered by their first
bytes.  Breadth-first backward extension of intervals yields common prefixes by increasing
length: a boundary reached first from an interval of l bytes has a common prefix of l.  It
stops at ``length``; boundaries still open join windows that agree in ``length`` bytes.  In
each class all but the first window, by (doc_id, start), are removed.

Whole texts that are copies of an earlier one are removed as such.

Nulls: a null text is empty; rows without a doc_id come after all others and, like all rows
of one doc_id, count as one document.  An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

LENGTH, GRAM = 100, 40
_LAST = (1 << 63) - 1
_CHUNK = 1 << 20
#: The lower bits of a hash, in which its place stands while windows choose their anchors.
_PLACE = np.uint64((1 << 31) - 1)


def _sliding(x: np.ndarray, w: int, op: np.ufunc, fill: int) -> np.ndarray:
    """op over x[i : i + w] for every i (beyond the end: fill)."""
    n = len(x)
    m = -(-(n + w) // w) * w
    y = np.full(m, fill, x.dtype)
    y[:n] = x
    blocks = y.reshape(-1, w)
    ahead = op.accumulate(blocks, axis=1).ravel()
    behind = op.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return op(behind[:n], ahead[w - 1 : n + w - 1])


def contexts(s: K.Slice, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(document, begin, end, anchor, key) of the contexts of a slice, in order; equal contexts have equal keys."""
    n, w = len(s.raw), length - gram + 1
    none, nothing = np.zeros(0, np.int64), np.zeros(0, np.uint64)
    to = np.repeat(s.to, s.to - s.at + 1)[:n]  # the end of the document of each byte
    at = np.flatnonzero(np.arange(n) + length <= to)
    if not len(at):
        return none, none, none, nothing, nothing
    sums = K.prefix_sums(s.raw)
    inverse = K._powers(n)[1]
    top = np.uint64(0xFFFFFFFFFFFFFFFF)
    h = np.full(n, top)
    h[: n - gram + 1] = K.mix((sums[gram:] - sums[:-gram]) * inverse[: n - gram + 1])
    # Upper bits of a hash before its place: the least one is the first of the smallest hashes.
    own = (_sliding((h & ~_PLACE) | np.arange(n, dtype=np.uint64), w, np.minimum, int(top)) & _PLACE)[at]
    first = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
    begin, end = at[first], at[np.append(first[1:], len(at)) - 1] + length
    key = K.mix((sums[end] - sums[begin]) * inverse[begin] + (end - begin).astype(np.uint64))
    doc = np.searchsorted(s.at, begin, "right") - 1
    return doc, begin - s.at[doc], end - s.at[doc], h[own[first].astype(np.int64)], key


def merged(i: np.ndarray, b: np.ndarray, e: np.ndarray) -> np.ndarray:
    """Byte ranges (id, begin, end) as rows; ranges of one id that touch are one."""
    if not len(i):
        return np.zeros((0, 3), np.int64)
    order = np.lexsort((e, b, i))
    i, b, e = i[order], b[order], e[order]
    number = np.cumsum(np.append(0, i[1:] != i[:-1]))
    reach = np.maximum.accumulate(number * (1 << 33) + e) - number * (1 << 33)
    head = np.flatnonzero(np.append(True, (i[1:] != i[:-1]) | (b[1:] > reach[:-1])))
    return np.stack([i[head], b[head], reach[np.append(head[1:], len(i)) - 1]], 1)


def _by_bucket(place: np.ndarray, rows: np.ndarray, buckets: int) -> dict[int, bytes]:
    """The columns of rows, packed one after another, of each bucket."""
    order = np.argsort(place, kind="stable")
    cut = np.searchsorted(place[order], np.arange(buckets + 1))
    rows = rows[order]
    return {k: np.ascontiguousarray(rows[cut[k] : cut[k + 1]].T).tobytes() for k in np.flatnonzero(np.diff(cut)).tolist()}


def _unpacked(column: pa.ChunkedArray, width: int) -> np.ndarray:
    return np.concatenate([np.zeros((width, 0), np.int64), *[np.frombuffer(x.as_py(), np.int64).reshape(width, -1) for x in column if len(x.as_py())]], axis=1)


def places(rows: DataFrame, buckets: int, length: int, gram: int) -> DataFrame:
    """(_id, b, e, h): later copies of contexts, with h null; and the first contexts of each kind of the anchors h that have several."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            ids = x.column(0).to_numpy()
            parts = [(ids[s.first + d], *rest) for s in K.slices(x.column(1)) for d, *rest in [contexts(s, length, gram)]]
            if not parts:
                continue
            i, b, e, h, key = (np.concatenate(c) for c in zip(*parts, strict=True))
            order = np.lexsort((b, i, key))
            i, b, e, h, key = i[order], b[order], e[order], h[order], key[order]
            head = np.append(True, key[1:] != key[:-1])[: len(key)]
            sent = _by_bucket((h[head] % np.uint64(buckets)).astype(np.int64), np.stack([i, b, e - b, h.view(np.int64), key.view(np.int64)], 1)[head], buckets)
            gone = merged(i[~head], b[~head], e[~head])
            gone = _by_bucket(gone[:, 0] % buckets, gone, buckets)
            c = [(k, sent.get(k, b""), gone.get(k, b"")) for k in sorted(sent.keys() | gone.keys())]
            c = list(zip(*c, strict=True)) if c else [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int32()), pa.array(c[1], pa.binary()), pa.array(c[2], pa.binary())], names=["bucket", "sent", "gone"])

    def meet(t: pa.Table) -> pa.Table:
        i, b, size, h, key = _unpacked(t.column("sent"), 5)
        order = np.lexsort((b, i, key))
        i, b, e, h, key = i[order], b[order], (b + size)[order], h[order], key[order]
        head = np.append(True, key[1:] != key[:-1])[: len(key)]
        _, back, many = np.unique(h[head], return_inverse=True, return_counts=True)
        some = np.flatnonzero(head)[many[back] > 1]
        done = np.concatenate([_unpacked(t.column("gone"), 3).T, merged(i[~head], b[~head], e[~head])])
        anchor = pa.concat_arrays([pa.array(h[some], pa.int64()), pa.nulls(len(done), pa.int64())])
        return pa.table({"_id": np.append(i[some], done[:, 0]), "b": np.append(b[some], done[:, 1]), "e": np.append(e[some], done[:, 2]), "h": anchor})

    return rows.mapInArrow(run, "bucket int, sent binary, gone binary").groupBy("bucket").applyInArrow(meet, "_id long, b long, e long, h long")


def _radix(key: np.ndarray) -> np.ndarray:
    """A stable order of numbers from 0, by 16 bits at a time."""
    order = np.argsort((key & 0xFFFF).astype(np.uint16), kind="stable")
    most, shift = int(key.max(initial=0)), 16
    while most >> shift:
        order = order[np.argsort((key[order] >> shift & 0xFFFF).astype(np.uint16), kind="stable")]
        shift += 16
    return order


def suffix_order(symbols: np.ndarray, length: int) -> np.ndarray:
    """Suffixes ordered by at least their first ``length`` symbols (prefix doubling from seven packed symbols)."""
    n = len(symbols)
    padded = np.append(symbols.astype(np.int64), np.zeros(8, np.int64))
    key = np.zeros(n, np.int64)
    for k in range(7):
        key = key * 512 + padded[k : k + n]
    done = 7
    while True:
        order = _radix(key)
        sorted_ = key[order]
        if done >= length or n and (sorted_[1:] != sorted_[:-1]).all():
            return order
        rank = np.empty(n + 1, np.int64)
        rank[order] = np.cumsum(np.append(0, sorted_[1:] != sorted_[:-1]))
        rank[n] = -1
        key = rank[:n] * (n + 1) + rank[np.minimum(np.arange(n) + done, n)] + 1
        done *= 2


def common_prefixes(symbols: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """The suffix order, and for each place whether its suffix agrees with the one before in ``length`` symbols.

    Symbol 0 separates texts and is never extended over.
    """
    order = suffix_order(symbols, length)
    n = len(order)
    bwt = symbols[order - 1]
    first = symbols[order]
    lf = np.empty(n, np.int64)
    lf[np.argsort(bwt, kind="stable")] = np.arange(n)
    open_ = np.ones(n + 1, bool)
    open_[[0, n]] = False
    source = np.zeros(n, np.int64)
    mask = np.zeros(n, bool)
    begin, end = np.array([0]), np.array([n])
    for _ in range(length):
        size = end - begin
        if not len(size):
            break
        at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size - begin, size)
        of = np.repeat(np.arange(len(size)), size)
        good = bwt[at] > 0
        place = lf[at[good]]
        source[place] = of[good]
        mask[place] = True
        p = np.flatnonzero(mask)
        mask[place] = False
        if not len(p):
            break
        cut = np.flatnonzero(np.append(True, (np.diff(p) != 1) | (source[p[1:]] != source[p[:-1]]) | (first[p[1:]] != first[p[:-1]])))
        lo, hi = p[cut], p[np.append(cut[1:], len(p)) - 1] + 1
        # The place after an interval is new, or the interval before it in text order is: both ends tell a boundary.
        new = open_[hi] | open_[lo]
        begin, end = lo[new], hi[new]
        open_[begin] = False
        open_[end] = False
    return order, open_[:n]


def later_windows(ids: np.ndarray, starts: np.ndarray, texts: list[bytes], length: int) -> np.ndarray:
    """Removed ranges (id, begin, end) of contexts: windows that occur before, in or between them."""
    if len(texts) < 2:
        return np.zeros((0, 3), np.int64)
    size = np.array([len(t) for t in texts], np.int64)
    raw = np.frombuffer(b"\x00".join(texts) + b"\x00", np.uint8).astype(np.int16) + 1
    ends = np.cumsum(size + 1)
    raw[ends - 1] = 0
    order, same = common_prefixes(raw, length)
    text = np.repeat(np.arange(len(texts)), size + 1)
    offset = np.arange(len(raw)) - np.repeat(ends - size - 1, size + 1)
    valid = (offset + length <= size[text])[order]
    group = np.cumsum(~same)[valid]
    at = order[valid]
    # Only windows that are not alone need an order.
    shared = np.append(False, group[1:] == group[:-1])[: len(group)]
    shared[:-1] |= shared[1:]
    at, group = at[shared], group[shared]
    i, p = ids[text[at]], starts[text[at]] + offset[at]
    o = np.lexsort((p, i, group))
    i, p, group = i[o], p[o], group[o]
    head = np.append(True, group[1:] != group[:-1])[: len(group)]
    lead = np.maximum.accumulate(np.where(head, np.arange(len(group)), 0))
    gone = (i != i[lead]) | (p != p[lead])
    return merged(i[gone], p[gone], p[gone] + length)


_RUNS = "_id long, b long, e long"


def removed_runs(rows: DataFrame, found: DataFrame, buckets: int, length: int) -> DataFrame:
    """(_id, b, e): byte ranges to remove; they may overlap."""
    by_doc = found.groupBy("_id").agg(F.collect_list(F.struct("b", "e", "h")).alias("places"))

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            raw, off = K.buffers(x.column("text"))
            lists = x.column("places")
            flat = lists.flatten()
            row = np.repeat(np.arange(x.num_rows), lists.value_lengths().to_numpy())
            i = x.column("_id").to_numpy()[row]
            b, e = flat.field("b").to_numpy(), flat.field("e").to_numpy()
            known = flat.field("h").is_valid().to_numpy(zero_copy_only=False)
            h = flat.field("h").fill_null(0).to_numpy()[known]
            done = merged(i[~known], b[~known], e[~known])
            begin, end = (off[row] + b)[known].tolist(), (off[row] + e)[known].tolist()
            data = memoryview(np.ascontiguousarray(raw))
            texts = [bytes(data[u:v]) for u, v in zip(begin, end, strict=True)]
            n, m = len(texts), len(done)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.append(h % buckets, done[:, 0] % buckets).astype(np.int32)), pa.concat_arrays([pa.array(h, pa.int64()), pa.nulls(m, pa.int64())]), pa.array(np.append(i[known], done[:, 0])),
                    pa.array(np.append(b[known], done[:, 1])), pa.concat_arrays([pa.nulls(n, pa.int64()), pa.array(done[:, 2])]), pa.concat_arrays([pa.array(texts, pa.binary()), pa.nulls(m, pa.binary())]),
                ],
                names=["bucket", "h", "_id", "b", "e", "t"],
            )

    def meet(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        ready = t.filter(pa.compute.is_valid(t.column("e")))
        t = t.filter(pa.compute.is_null(t.column("e")))
        h, ids, starts = (t.column(c).to_numpy() for c in ("h", "_id", "b"))
        texts = t.column("t").to_pylist()
        keep = np.argsort(h, kind="stable")
        out = [np.stack([ready.column(c).to_numpy() for c in ("_id", "b", "e")], 1)]
        begin, size = 0, 0
        for k in range(len(keep) + 1):
            # Contexts of one anchor stay together.
            if k == len(keep) or size >= _CHUNK and h[keep[k]] != h[keep[k - 1]]:
                own = keep[begin:k]
                out.append(later_windows(ids[own], starts[own], [texts[j] for j in own], length))
                begin, size = k, 0
            if k < len(keep):
                size += len(texts[keep[k]])
        g = np.concatenate(out)
        g = merged(*g.T)
        return pa.table({"_id": g[:, 0], "b": g[:, 1], "e": g[:, 2]})

    joined = rows.join(by_doc, "_id").select("_id", "text", "places")
    return joined.mapInArrow(fetch, "bucket int, h long, _id long, b long, e long, t binary").groupBy("bucket").applyInArrow(meet, _RUNS)


def copies(rows: DataFrame) -> DataFrame:
    """(_id, e): ids whose whole text of e bytes is an earlier row's (ids of several rows are left to the anchors)."""
    one = rows.select("_id", F.md5("text").alias("_h"), F.octet_length("text").cast("long").alias("e")).groupBy("_id").agg(F.count("*").alias("_n"), F.max("_h").alias("_h"), F.max("e").alias("e")).where("_n = 1")
    first = rows.groupBy(F.md5("text").alias("_h")).agg(F.min("_id").alias("_first"), F.count("*").alias("_n")).where("_n > 1").select("_h", "_first")
    return one.join(first, "_h").where("_id > _first").select("_id", "e")


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def cut(text: bytes, runs: list[tuple[int, int]]) -> tuple[bytes, int]:
    """The bytes outside the runs, and the number of maximal runs."""
    kept, last, n = [], 0, 0
    for b, e in sorted(runs):
        if b > last or n == 0:
            kept.append(text[last:b])
            n += 1
        last = max(last, e)
    return b"".join([*kept, text[last:]]), n


def dedup(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """One row per document: its bytes, what is removed, and a digest of what is kept."""
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    buckets = max(64, K.plan_bytes(docs) // (2 << 20))
    later = copies(rows)
    found = places(rows, buckets, length, gram).join(later.select("_id"), "_id", "left_anti")
    runs = removed_runs(rows, found, buckets, length).unionByName(later.where(F.col("e") >= length).select("_id", F.lit(0).cast("long").alias("b"), "e"))
    runs = runs.groupBy("_id").agg(F.collect_set(F.struct("b", "e")).alias("runs"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for i, text, own in zip(*(b.column(c).to_pylist() for c in ("_id", "text", "runs")), strict=True):
                t = text.encode()
                kept, n = cut(t, [(x["b"], x["e"]) for x in own]) if own else (t, 0)
                out.append((None if i == _LAST else i, len(t), len(t) - len(kept), n, hashlib.sha256(kept).hexdigest()))
            c = list(zip(*out, strict=True)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in c[:4]), pa.array(c[4], pa.string())], names=[f.split(" ")[0] for f in RESULT.split(", ")])

    return rows.join(runs, "_id", "left").select("_id", "text", "runs").mapInArrow(run, RESULT)


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(K.table(spark, sf_dir, "documents"))
