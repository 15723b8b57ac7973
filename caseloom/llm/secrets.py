"""Secret scans (operator 9): fixed patterns, and character Markov models compared by log-likelihood ratio.

Two first-order models over the characters of tokens are trained from labelled samples, one
from random strings and one from ordinary identifiers.  A run of token characters whose
log-likelihood ratio is high, in total and per character, is a span of kind ``markov`` if it
has a digit: without one, names as code joins them have as high a ratio as random letters.
The fixed patterns (kinds ``assign``, ``access``, ``hex``) always count; a Markov span that
lies within one of theirs is left out.

Byte passes over whole slices find the documents that can hold a pattern; only those are
matched by regular expressions.  Every text is read whole.

Nulls: a null text is empty; a null doc_id stays null.  Repeated rows give repeated results,
an empty table an empty one.
"""

from __future__ import annotations

import hashlib
import random
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K

# The base patterns, with the least length of what they find.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
ASSIGN_MIN, ACCESS_MIN, HEX_MIN = 12, 18, 16
KINDS = ("assign", "access", "hex", "markov")
_HINTS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
_ALPHABETS = (
    "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789",
    "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/",
    "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789-_",
    "0123456789abcdef",
    "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567",
)

TOKEN = K.lut("A-Za-z0-9+/_=-")
_CLASS = np.cumsum(TOKEN).astype(np.int64) * TOKEN  # 0: outside the token characters
_STATES = int(TOKEN.sum()) + 1
_HEX = K.lut("0-9a-f")
_DIGIT = K.lut("0-9")

#: Least token length, least ratio per character and in total (nats).
MIN_LENGTH, MIN_MEAN, MIN_TOTAL = 20, 0.7, 20.0
#: Documents whose words are the sample of ordinary identifiers.
SAMPLE_DOCS = 2000


def train(random_strings: list[bytes], ordinary: list[bytes]) -> np.ndarray:
    """The table of log-likelihood ratios of transitions, from two labelled samples."""

    def logs(sample: list[bytes]) -> np.ndarray:
        n = np.full((_STATES, _STATES), 0.5)
        for t in sample:
            c = _CLASS[np.frombuffer(t, np.uint8)]
            np.add.at(n, (c[:-1], c[1:]), 1)
        return np.log(n / n.sum(axis=1, keepdims=True))

    out = logs(random_strings) - logs(ordinary)
    out[0], out[:, 0] = 0, 0
    return out


def random_sample(n: int = 4000, seed: int = 11) -> list[bytes]:
    r = random.Random(seed)
    return ["".join(r.choices(_ALPHABETS[i % len(_ALPHABETS)], k=r.randint(20, 64))).encode() for i in range(n)]


def ordinary_sample(texts: list[str], seed: int = 12) -> list[bytes]:
    """Words of texts, alone and joined as identifiers, paths and numbered names."""
    r = random.Random(seed)
    found = sorted({w for t in texts for w in re.findall(r"[A-Za-z]{2,}", t)}) or ["name"]
    r.shuffle(found)
    out = [w.encode() for w in found[:40000]]
    for i in range(20000):
        w = [r.choice(found) for _ in range(r.randint(2, 4))]
        kind = i % 6
        joined = ("_".join(w), "-".join(w), "/".join(w), w[0] + "".join(x.capitalize() for x in w[1:]), "_".join(w).upper(), f"{'-'.join(w[:2])}-{r.randint(1, 2030)}")[kind]
        out.append(joined.encode())
    return out + [b"=" * 40, b"-" * 60, b"_" * 40, b"0" * 30, b"x" * 30] * 20


def sample_docs(docs: DataFrame, n: int) -> DataFrame:
    """A bounded sample of rows: those of the n doc_ids with the smallest hashes."""
    ids = docs.select("doc_id").where("doc_id IS NOT NULL").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
    return docs.join(F.broadcast(ids), "doc_id", "left_semi")


def fit(docs: DataFrame, sample: int = SAMPLE_DOCS) -> np.ndarray:
    """Trains on random strings and on the words of a sample of at most ``sample`` documents."""
    texts = [r[0] for r in sample_docs(docs, sample).select(F.substring(F.col("text").cast("string"), 1, 20000)).collect() if r[0]]
    return train(random_sample(), ordinary_sample(sorted(texts)))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of what the base patterns find, in code points."""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_MIN]
    out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_MIN]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text) if m.end() - m.start() >= HEX_MIN]
    return sorted(out)


def _hits(s: K.Slice, folded: bytes, whole: bytes) -> set[int]:
    """Documents of a slice in which a base pattern may match."""
    at = []
    for b, needles in ((folded, _HINTS), (whole, (b"AKIA",))):
        for needle in needles:
            i = b.find(needle)
            while i >= 0:
                at.append(i)
                i = b.find(needle, i + len(needle))
    w = K.words(s, _HEX, hashed=False)
    at += w.begin[w.end - w.begin >= HEX_MIN].tolist()
    return set((np.searchsorted(s.at, at, "right") - 1).tolist()) if at else set()


def find(s: K.Slice, ratios: np.ndarray) -> dict[int, list[tuple[int, int, int]]]:
    """All spans (start, kind, end; code points, sorted) of the documents of a slice that have any."""
    whole = s.raw.tobytes()
    out = {i: base_spans(s.text(i).decode()) for i in _hits(s, whole.lower(), whole)}
    w = K.words(s, TOKEN, hashed=False)
    long = np.flatnonzero(w.end - w.begin >= MIN_LENGTH)
    if len(long):
        c = _CLASS[s.raw]
        total = np.append(0, np.cumsum(ratios[np.append(0, c[:-1]), c]))
        digits = np.append(0, np.cumsum(_DIGIT[s.raw]))
        begin, end = w.begin[long], w.end[long]
        value = total[end] - total[begin + 1]
        good = (value >= MIN_TOTAL) & (value >= MIN_MEAN * (end - begin)) & (digits[end] > digits[begin])
        for b, e in zip(begin[good].tolist(), end[good].tolist(), strict=True):
            i = int(np.searchsorted(s.at, b, "right")) - 1
            b, e = K.points(s.text(i), [b - int(s.at[i]), e - int(s.at[i])])
            own = out.setdefault(i, [])
            if not any(x <= b and e <= y for x, k, y in own if k < 3):
                own.append((b, 3, e))
    return {i: sorted(v) for i, v in out.items() if v}


def told(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{b}:{e}" for b, k, e in spans)


_NONE = hashlib.sha256(b"").hexdigest()
RESULT = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_markov long"


def scan(docs: DataFrame, ratios: np.ndarray) -> DataFrame:
    """One row per document: counts by kind, a digest of the base spans, and all spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = b.num_rows
            counts = np.zeros((4, n), np.int64)
            digest, spans = [_NONE] * n, [""] * n
            for s in K.slices(b.column(1)):
                for i, found in find(s, ratios).items():
                    i += s.first
                    spans[i] = told(found)
                    digest[i] = hashlib.sha256(told([x for x in found if x[1] < 3]).encode()).hexdigest()
                    for _, k, _ in found:
                        counts[k, i] += 1
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, counts[:3]), pa.array(digest), pa.array(spans), pa.array(counts[3])], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_markov"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, RESULT)


def redact(docs: DataFrame, ratios: np.ndarray, mark: str = "[SECRET]") -> DataFrame:
    """The same rows and columns with every found span replaced by ``mark`` (and n_chars, if there, counted anew)."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(at)
            found = {i + s.first: v for s in K.slices(texts) for i, v in find(s, ratios).items()}
            if found:
                new = texts.to_pylist()
                for i, spans in found.items():
                    parts, last = [], 0
                    for x, _, y in spans:
                        if x >= last:
                            parts += [new[i][last:x], mark]
                        last = max(last, y)
                    new[i] = "".join([*parts, new[i][last:]])
                b = b.set_column(at, b.schema.field(at), pa.array(new, texts.type))
            yield b

    out = docs.mapInArrow(run, docs.schema)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = K.table(spark, sf_dir, "documents")
    return scan(docs, fit(docs))
