"""Document fingerprints by SimHash, in DataFrame expressions only (operator 3).

Terms are pairs of consecutive words, weighted by the letters in them.  Each of the 128 bits
of a term's hash votes with that weight, and the sign of the sum is the fingerprint's bit.
Two votes share a 64-bit sum (32 bits each), so a fingerprint takes 64 sums in generated
code, and partial aggregation leaves one row per text before anything is shuffled.

``within`` finds all pairs of fingerprints and queries within a Hamming radius by permuted block
tables: the bits are cut into blocks; fingerprints that differ in at most r bits agree in all
but r blocks, so each table is keyed by one choice of blocks that agree, and a pair counts in
the first such table only.  The query set is documents whose id is divisible by ``EVERY``
(null ids are none); for each, ``neighbours`` counts the documents within the radius.  Copies
are one fingerprint with a count, and a join that Spark can split takes common keys.

Nulls: a null text is an empty one, whose fingerprint is all zeros; null doc_ids sort first.
Rows with equal doc_ids are ordered by text.
``n_near`` and ``near_id`` are null outside the query set.  An empty table gives an empty result; a single
row is its own next row.  Texts are read whole.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernels as K

BITS = 128
#: Documents of one bucket of ids meet in one task, where each finds the next one.
BUCKET_BITS, SUPER_BITS = 8, 12
_LANES = 0x0000000100000001
#: Hamming radius of near copies, blocks that agree in a table, and the query set: ids divisible by EVERY.
RADIUS, SPARE, EVERY = 4, 2, 100


def votes(terms: DataFrame, keys: list[str], a: Column, b: Column) -> DataFrame:
    """Fingerprints (two longs, ``f0`` and ``f1``) of the rows of terms (a, b), by keys."""
    weight = F.least(F.coalesce(F.length(a), F.lit(0)) + F.coalesce(F.length(b), F.lit(0)), F.lit(24)).cast("long")
    rows = terms.select(*keys, F.xxhash64(a, b).alias("_h0"), F.xxhash64(b, a, F.lit(7)).alias("_h1"), weight.alias("_w"))
    sums = [F.sum(F.shiftright(f"_h{k}", i).bitwiseAND(F.lit(_LANES)) * F.col("_w")).alias(f"_s{k}_{i}") for k in (0, 1) for i in range(32)]
    out = rows.groupBy(*keys).agg(F.sum("_w").alias("_all"), *sums)

    def bits(k: int) -> Column:
        low = [F.when(F.col(f"_s{k}_{i}").bitwiseAND(F.lit(0xFFFFFFFF)) * 2 > F.col("_all"), F.lit(1 << i)).otherwise(F.lit(0)) for i in range(32)]
        high = [F.when(F.shiftrightunsigned(f"_s{k}_{i}", 32) * 2 > F.col("_all"), F.lit(1 << i)).otherwise(F.lit(0)) for i in range(32)]
        or_ = lambda x, y: x.bitwiseOR(y)
        return F.shiftleft(reduce(or_, high).cast("long"), 32).bitwiseOR(reduce(or_, low).cast("long"))

    return out.select(*keys, bits(0).alias("f0"), bits(1).alias("f1"))


def word_pairs(text: Column) -> Column:
    """An array of structs of consecutive words; the last has no partner."""
    w = F.split(text, "\\s+")
    return F.arrays_zip(w, F.slice(w, F.lit(2), F.greatest(F.size(w) - 1, F.lit(0))))


def distance(a0: Column, a1: Column, b0: Column, b1: Column) -> Column:
    return F.bit_count(a0.bitwiseXOR(b0)) + F.bit_count(a1.bitwiseXOR(b1))


def likeness(d: Column) -> Column:
    """The cosine that a Hamming distance stands for, 0 at least."""
    return F.greatest(F.lit(0.0), F.round(F.cos(d * (3.141592653589793 / BITS)), 9))


def told(f0: Column, f1: Column) -> Column:
    return F.lower(F.concat(F.lpad(F.hex(f0), 16, "0"), F.lpad(F.hex(f1), 16, "0")))


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, text, its place (bucket, rn) and the place and text of the next document by doc_id; the first follows the last."""
    bucket = F.coalesce(F.shiftright("doc_id", BUCKET_BITS), F.lit(-(1 << 62)))
    base = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("bucket", bucket)
    buckets = base.select("bucket").distinct().withColumn("_super", F.shiftright("bucket", SUPER_BITS))
    inner = buckets.withColumn("_next", F.lead("bucket").over(Window.partitionBy("_super").orderBy("bucket")))
    supers = buckets.groupBy("_super").agg(F.min("bucket").alias("_first"))
    # One row per BUCKET_BITS + SUPER_BITS bits of ids.
    order = Window.orderBy("_super")
    supers = supers.select("_super", F.coalesce(F.lead("_first").over(order), F.min("_first").over(order)).alias("_follows"))
    following = inner.join(supers, "_super").select(F.col("bucket").alias("_before"), F.coalesce("_next", "_follows").alias("bucket"))
    # One shuffle of the texts; the second use of it is the same exchange.
    ranked = base.withColumns({"rn": F.row_number().over(w := Window.partitionBy("bucket").orderBy(F.col("doc_id").asc_nulls_first(), "text")), "_next_text": F.lead("text").over(w)})
    heads = ranked.where("rn = 1").select("bucket", F.col("text").alias("_head"))
    heads = heads.join(following, "bucket").select(F.col("_before").alias("bucket"), F.col("bucket").alias("_bucket_after"), "_head")
    last = F.col("_next_text").isNull()
    return ranked.join(heads, "bucket").select(
        "doc_id", "text", "bucket", "rn",
        F.when(last, F.col("_bucket_after")).otherwise(F.col("bucket")).alias("next_bucket"),
        F.when(last, F.lit(1)).otherwise(F.col("rn") + 1).alias("next_rn"),
        F.when(last, F.col("_head")).otherwise(F.col("_next_text")).alias("next_text"),
    )


def edited_likeness(docs: DataFrame) -> DataFrame:
    """Fingerprints of documents and of their edited texts, the likeness of each to its edited text and to the next one, and near documents of queries."""
    rows = with_next(docs).withColumn("n_chars", F.length("text").cast("long")).withColumn("_cut", F.floor(F.col("n_chars") / 4).cast("int"))
    rows = rows.withColumn("edited", F.concat(F.substring("text", F.lit(1), F.col("n_chars").cast("int") - F.col("_cut")), F.substring("next_text", F.lit(1), F.col("_cut"))))
    rows = rows.withColumn("edited_sha256", F.sha2(F.col("edited").cast("binary"), 256))
    keys = ["doc_id", "bucket", "rn", "next_bucket", "next_rn", "n_chars", "edited_sha256", "variant"]
    texts = rows.select(*keys[:-1], F.explode(F.array(F.struct(F.lit(0).alias("variant"), F.col("text").alias("t")), F.struct(F.lit(1).alias("variant"), F.col("edited").alias("t")))).alias("_v"))
    terms = texts.select(*keys[:-1], F.col("_v.variant"), F.explode(word_pairs(F.col("_v.t"))).alias("_t"))
    both = votes(terms, keys, F.col("_t.0"), F.col("_t.1"))
    pick = lambda v, f: F.max(F.when(F.col("variant") == v, F.col(f)))
    one = K.durable(both.groupBy(*keys[:-1]).agg(pick(0, "f0").alias("f0"), pick(0, "f1").alias("f1"), pick(1, "f0").alias("e0"), pick(1, "f1").alias("e1")))
    after = one.select(F.col("bucket").alias("next_bucket"), F.col("rn").alias("next_rn"), F.col("f0").alias("n0"), F.col("f1").alias("n1"))
    near = lambda x, y: likeness(distance(F.col("f0"), F.col("f1"), F.col(x), F.col(y)))
    return one.join(after, ["next_bucket", "next_rn"]).join(neighbours(one), ["doc_id", "f0", "f1"], "left").select(
        "doc_id", "n_chars", "edited_sha256", told(F.col("f0"), F.col("f1")).alias("fingerprint"), told(F.col("e0"), F.col("e1")).alias("edited_fingerprint"),
        near("e0", "e1").alias("near_edited"), near("n0", "n1").alias("near_next"), "n_near", "near_id",
    )


def _blocks(x0: Column, x1: Column, blocks: int) -> list[Column]:
    """The bits of two words in blocks, as numbers (a block over both words joins its parts)."""
    bounds, out = [round(k * BITS / blocks) for k in range(blocks + 1)], []
    for lo, hi in zip(bounds, bounds[1:], strict=False):
        parts = []
        for word, x in ((0, x0), (1, x1)):
            a, b = max(lo, 64 * word) - 64 * word, min(hi, 64 * word + 64) - 64 * word
            if a < b:
                parts.append((F.shiftrightunsigned(F.shiftleft(x, 64 - b), 64 - b + a), b - a))
        out.append(parts[0][0] if len(parts) == 1 else F.shiftleft(parts[0][0], parts[1][1]).bitwiseOR(parts[1][0]))
    return out


def _tables(radius: int, spare: int) -> list[tuple[int, ...]]:
    return list(combinations(range(radius + spare), spare))


def keyed(prints: DataFrame, radius: int, spare: int) -> DataFrame:
    """f0, f1 and ``_key``: a row for each permuted table, keyed by a hash of the blocks that must agree in it; its last bits are the table's number."""
    b, tables = _blocks(F.col("f0"), F.col("f1"), radius + spare), _tables(radius, spare)
    low = len(tables).bit_length()
    keys = [F.shiftleft(F.xxhash64(F.lit(t), *[b[k] for k in kept]), low).bitwiseOR(F.lit(t)) for t, kept in enumerate(tables)]
    return prints.select("f0", "f1", F.explode(F.array(*keys)).alias("_key"))


def within(prints: DataFrame, queries: DataFrame, radius: int = RADIUS, spare: int = SPARE) -> DataFrame:
    """All (fingerprint, query) pairs at most ``radius`` bits apart, with their distance; each pair is told once.

    prints and queries have columns f0 and f1, distinct in each.
    """
    p = keyed(prints, radius, spare)
    q = keyed(queries, radius, spare).withColumnsRenamed({"f0": "q0", "f1": "q1"})
    d = distance(F.col("f0"), F.col("f1"), F.col("q0"), F.col("q1"))
    # The first blocks that agree name the table in which the pair counts.
    same = [x == 0 for x in _blocks(F.col("f0").bitwiseXOR(F.col("q0")), F.col("f1").bitwiseXOR(F.col("q1")), radius + spare)]
    first, tables = None, _tables(radius, spare)
    for t, kept in enumerate(tables):
        own = reduce(lambda x, y: x & y, [same[k] if k in kept else ~same[k] for k in range(kept[-1] + 1)])
        first = F.when(own, F.lit(t)) if first is None else first.when(own, F.lit(t))
    table = p["_key"].bitwiseAND(F.lit((1 << len(tables).bit_length()) - 1))
    return p.join(q, (p["_key"] == q["_key"]) & (d <= radius) & (first == table)).drop("_key").withColumn("distance", d)


def neighbours(prints: DataFrame, radius: int = RADIUS, spare: int = SPARE, every: int = EVERY) -> DataFrame:
    """doc_id, f0, f1, n_near (other documents within the radius) and near_id (the smallest id of them, itself included) of the query set."""
    queries = prints.where(F.col("doc_id") % every == 0).select("doc_id", "f0", "f1").distinct()
    all_ = prints.groupBy("f0", "f1").agg(F.count("*").alias("_n"), F.min("doc_id").alias("_least"))
    found = within(all_, queries.select("f0", "f1").distinct(), radius, spare).join(all_, ["f0", "f1"])
    found = found.groupBy("q0", "q1").agg((F.sum("_n") - 1).alias("n_near"), F.min("_least").alias("near_id"))
    return queries.join(found.withColumnsRenamed({"q0": "f0", "q1": "f1"}), ["f0", "f1"])


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_likeness(K.table(spark, sf_dir, "documents"))
