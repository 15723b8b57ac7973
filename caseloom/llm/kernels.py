"""Vectorised text kernels shared by the text operators.

Texts are handled as Arrow UTF-8 buffers: one byte array for a slice of documents, a
line feed after each of them, and numpy passes over all its bytes.  Nothing here makes
a Python object for each word.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 1 << 20
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1

FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32
_TABLE = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS = [np.ones(0, np.uint64), np.ones(0, np.uint64)]


def lut(spec: str) -> np.ndarray:
    """A truth table over bytes from character ranges such as ``"a-z0-9"``; ``high`` adds all bytes from 0x80."""
    out = np.zeros(256, bool)
    if spec.startswith("high "):
        out[128:] = True
        spec = spec[5:]
    i = 0
    while i < len(spec):
        lo = hi = ord(spec[i])
        if spec[i + 1 : i + 2] == "-" and i + 2 < len(spec):
            hi = ord(spec[i + 2])
            i += 2
        out[lo : hi + 1] = True
        i += 1
    return out


LETTERS = lut("high A-Za-z")
ALNUM = lut("high a-z0-9A-Z")
#: All but the space, tab, line feed, vertical tab, form feed and carriage return.
NOT_SPACE = ~lut(" \t\n\x0b\x0c\r")


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        size = max(n, SLICE_BYTES * 2)
        for k, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            step = np.full(size, base, np.uint64)
            step[0] = 1
            _POWERS[k] = np.cumprod(step)
    return _POWERS[0][:n], _POWERS[1]


def mix(x: np.ndarray) -> np.ndarray:
    """The 64-bit finaliser of splitmix."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@dataclass
class Slice:
    """Some whole documents: ``raw`` holds their bytes with a line feed after each; document i is raw[at[i]:to[i]]."""

    first: int
    raw: np.ndarray
    at: np.ndarray
    to: np.ndarray

    def __len__(self) -> int:
        return len(self.at)

    def text(self, i: int) -> bytes:
        return self.raw[self.at[i] : self.to[i]].tobytes()


def buffers(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes and offsets of an Arrow string column; a null is an empty text."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    n = len(texts)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + n + 1]
    data = texts.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(texts: pa.Array, limit: int = SLICE_BYTES) -> Iterator[Slice]:
    """Cuts a column into slices of whole documents of about ``limit`` bytes (a longer document is a slice of its own)."""
    raw, off = buffers(texts)
    n, i = len(off) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + limit, "right")) - 1)
        o = off[i : j + 1] - off[i]
        k = j - i
        yield Slice(i, np.insert(raw[off[i] : off[j]], o[1:], 10), o[:-1] + np.arange(k), o[1:] + np.arange(k))
        i = j


@dataclass
class Words:
    """Runs of the bytes of a class: begin, end, and for each document the number of runs before it."""

    begin: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    sums: np.ndarray | None = None

    def spans(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        """64-bit hashes of byte ranges, the same for equal bytes anywhere."""
        inverse = _powers(len(self.sums))[1]
        return mix((self.sums[end] - self.sums[begin]) * inverse[begin] + (end - begin).astype(np.uint64))

    def hashes(self) -> np.ndarray:
        return self.spans(self.begin, self.end)


def prefix_sums(raw: np.ndarray) -> np.ndarray:
    sums = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(_TABLE[raw] * _powers(len(raw))[0], out=sums[1:])
    return sums


def words(s: Slice, inside: np.ndarray, hashed: bool = True, folded: bool = True) -> Words:
    """Maximal runs of bytes of the class ``inside``; the hashes see A-Z in lower case if ``folded``."""
    edge = np.diff(inside[s.raw].view(np.int8), prepend=np.int8(0), append=np.int8(0))
    begin, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    doc = np.append(np.searchsorted(begin, s.at), len(begin))
    return Words(begin, end, doc, prefix_sums(FOLD[s.raw] if folded else s.raw) if hashed else None)


_STEPS = np.array([0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3, 0x1D8E4E27C47D124F, 0xEB44ACCAB455D165, 0x9FB21C651E98DF25], np.uint64)


def shingles(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k words of one document; of the whole sequence if it is shorter, none if it is empty."""
    k = min(k, len(h))
    if k == 0:
        return h
    out = np.full(len(h) - k + 1, k, np.uint64)
    for i in range(k):
        out += h[i : len(h) - k + 1 + i] * _STEPS[i % 8]
        out = mix(out)
    return out


def points(b: bytes, cuts: list[int]) -> list[int]:
    """Code point offsets of byte offsets."""
    if not cuts:
        return []
    starts = np.cumsum((np.frombuffer(b, np.uint8) & 0xC0) != 0x80)
    return [int(starts[c - 1]) if c else 0 for c in cuts]


# --- frames -------------------------------------------------------------------------------------------------------


def durable(df: DataFrame) -> DataFrame:
    """Cuts the lineage with a checkpoint in the shared folder of the session (``spark.checkpoint.dir``)."""
    ready(df.sparkSession)
    return df.checkpoint(eager=True)


def ready(spark: SparkSession) -> None:
    """Uses the session's checkpoint folder; only where none is named, as in local tests, one is made."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None:
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
            import tempfile

            named = tempfile.mkdtemp(prefix="caseloom-")
        sc.setCheckpointDir(named)


def plan_bytes(df: DataFrame) -> int:
    """About how large a frame is, from file sizes, or by its rows where Spark knows none; it only sizes partitions."""
    n = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    return n if n < 1 << 60 else df.count() * 4096


def crc_mod(col: str, n: int) -> Column:
    """crc32 of a number as text, modulo n; null counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(col).cast("string"), F.lit("")).cast("binary")), F.lit(n))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def unsigned(a: np.ndarray) -> np.ndarray:
    return a.view(np.int64) if a.dtype == np.uint64 else a
