"""Constrained clustering of cases into patients.

Cases of one patient share sex and an age bucket, their ages span at most the bucket's
tolerance, and each case joins through a primary or secondary diagnosis shared with a member.
No case is used twice.  ``cluster`` merges clusters in parallel rounds, each with the best of all its
partners, until none has a partner left; ``cluster_exact`` grows them one case after another inside a
block.  The two may differ; both keep the constraints.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.checkpoint import Packed, drop, durable
from ..sources.tables import TOLERANCE, age_bucket

WIDTH = max(TOLERANCE.values())
#: Rows of cases and their diagnoses from which blocks are clustered in turns, each of so many rows at most or of one block.
SPLIT_FROM = 12_000_000
#: Rows of a task, of a diagnosis that is met in one task, and pairs that a task holds at once.
TASK_ROWS, HUB, PAIRS = 50_000, 4096, 1_000_000


def eligible(cases: DataFrame, case_dx: DataFrame) -> DataFrame:
    """(case_id, sex, age_years, bucket, dx_id) of non-differential diagnoses."""
    return cases.select("case_id", "sex", "age_years", age_bucket().alias("bucket")).join(case_dx.where("role <> 'differential'").select("case_id", "dx_id"), "case_id")


def compatible_pairs(cases: DataFrame, case_dx: DataFrame) -> DataFrame:
    """All compatible pairs of cases with the number of shared diagnoses (the exact baseline, quadratic in a diagnosis of a block; ``case_edges`` is for scale)."""
    c = eligible(cases, case_dx)
    a, b = c.select("sex", "bucket", "dx_id", F.col("case_id").alias("x"), F.col("age_years").alias("ax")), c.select("sex", "bucket", "dx_id", F.col("case_id").alias("y"), F.col("age_years").alias("ay"))
    return a.join(b, ["sex", "bucket", "dx_id"]).where((F.col("x") < F.col("y")) & (F.abs(F.col("ax") - F.col("ay")) <= WIDTH)).groupBy("x", "y").agg(F.count("*").alias("shared"))


def case_edges(cases: DataFrame, case_dx: DataFrame, fanout: int = 8) -> DataFrame:
    """Edges (x, y, shared): within each diagnosis of a block, a case meets the next ``fanout`` in order of age, so a common diagnosis has no quadratic number of pairs."""
    return edges_of(eligible(cases, case_dx), fanout)


def edges_of(rows: DataFrame, fanout: int) -> DataFrame:
    w = Window.partitionBy("sex", "bucket", "dx_id").orderBy("age_years", "case_id")
    steps = F.array(*[F.struct(F.lead("case_id", k).over(w).alias("y"), F.lead("age_years", k).over(w).alias("ay")) for k in range(1, fanout + 1)])
    rows = rows.withColumn("_steps", steps).withColumn("n", F.explode("_steps")).where(F.col("n.y").isNotNull() & (F.col("n.ay") - F.col("age_years") <= WIDTH))
    return rows.groupBy(F.least("case_id", F.col("n.y")).alias("x"), F.greatest("case_id", F.col("n.y")).alias("y")).agg(F.count("*").alias("shared"))


def cluster(cases: DataFrame, case_dx: DataFrame, *, max_cases: int = 5, max_rounds: int | None = None, split_from: int = SPLIT_FROM) -> DataFrame:
    """(case_id, patient_id): rounds in which each cluster proposes to its best partner and mutual proposals merge.

    Partners are all clusters of the block with which a cluster shares a diagnosis, fits in age and stays within
    ``max_cases``.  Their order is symmetric in the pair and different in each round: shared diagnoses (pairs of members
    count each), then a hash of the pair.  Rounds stop when no cluster has a partner; ``max_rounds`` stops them earlier.

    No partner is in another block of sex and age bucket.  From ``split_from`` rows on, the blocks are clustered in turns,
    with the same result, and what a round leaves is cleared, so the disk holds the rounds of one turn at a time.
    A case without sex or age stays alone.
    """
    rows = eligible(cases, case_dx).groupBy("case_id").agg(F.min("sex").alias("sex"), F.min("bucket").alias("bucket"), F.min("age_years").cast("long").alias("lo"), F.max("age_years").cast("long").alias("hi"), F.sort_array(F.collect_set(F.col("dx_id").cast("long"))).alias("dxs"))
    start = Packed(rows.select(F.col("case_id").cast("long").alias("id"), "sex", "bucket", "lo", "hi", F.lit(1).cast("long").alias("n"), "dxs"))
    blocks = {(r["sex"], r["bucket"]): r["rows"] for r in start.df.where("sex IS NOT NULL AND lo IS NOT NULL").groupBy("sex", "bucket").agg(F.sum(F.size("dxs")).alias("rows")).collect()}
    block = F.lit(None).cast("long")
    for i, (sex, bucket) in enumerate(sorted(blocks)):
        block = F.when((F.col("sex") == sex) & (F.col("bucket") == bucket) & F.col("lo").isNotNull(), F.lit(i).cast("long")).otherwise(block)
    known = start.df.withColumn("block", block).where("block IS NOT NULL").select("id", "block", "lo", "hi", "n", "dxs")
    turns, moved = [], []
    for b, key in enumerate(sorted(blocks)):
        if turns and blocks[key] + sum(turns[-1].values()) < split_from:
            turns[-1][b] = blocks[key]
        else:
            turns.append({b: blocks[key]})
    for turn in turns:
        moved += merged(known.where(F.col("block").isin(list(turn))), max_cases, max_rounds)
    to = start.df.select("id", F.col("id").alias("to")).limit(0)
    for m in moved:
        to = to.unionByName(m.df)
    # A cluster has at most max_cases - 1 merges, so so many steps lead to its last id.
    for _ in range(max(0, max_cases - 2).bit_length()):
        to = to.join(to.select(F.col("id").alias("to"), F.col("to").alias("_last")), "to", "left").select("id", F.coalesce("_last", "to").alias("to"))
    out = durable(start.df.select("id").join(to, "id", "left").select(F.col("id").alias("case_id"), F.coalesce("to", "id").alias("patient_id")))
    to = known = None
    drop(start, *moved)
    return out


def merged(clusters: DataFrame, max_cases: int, max_rounds: int | None) -> list[Packed]:
    """The rounds over (id, block, lo, hi, n, dxs), dxs the sorted diagnoses of all members: merges (id, to) of each."""
    now, moved = None, []
    large = Packed(clusters.select("block", F.explode("dxs").alias("dx")).groupBy("block", "dx").agg(F.ceil(F.count("*") / HUB).cast("long").alias("parts")).where("parts > 1"))
    some = not large.df.isEmpty()
    while max_rounds is None or len(moved) < max_rounds:
        best = best_partners(clusters, large.df if some else None, len(moved), max_cases)
        pairs = best.groupBy(F.least("p", "q").alias("x"), F.greatest("p", "q").alias("y")).agg(F.count("*").alias("n"), F.min("p").alias("p"))
        # Of a pair that proposed to each other the larger id goes; the others with a partner wait, and those without one never find one.
        fate = F.when(F.col("n") == 2, F.array(F.struct(F.col("x").alias("id"), F.col("x").alias("to")), F.struct(F.col("y").alias("id"), F.col("x").alias("to")))).otherwise(F.array(F.struct(F.col("p").alias("id"), F.col("p").alias("to"))))
        fate = Packed(pairs.select(F.inline(fate)))
        if fate.df.isEmpty():
            drop(fate)
            break
        moved.append(Packed(fate.df.where("id <> to")))
        after = clusters.join(fate.df, "id").groupBy(F.col("to").alias("id")).agg(F.min("block").alias("block"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("n").alias("n"), F.sort_array(F.flatten(F.collect_list("dxs"))).alias("dxs"))
        after = Packed(after.where(F.col("n") < max_cases))
        clusters = after.df
        best = pairs = None
        drop(fate, *([now] if now else []))
        now = after
    clusters = best = pairs = None
    drop(large, *([now] if now else []))
    return moved


def best_partners(clusters: DataFrame, large: DataFrame | None, k: int, max_cases: int) -> DataFrame:
    """(p, q): the best partner q of each cluster p that has one, in round k.

    Clusters meet in each of their diagnoses, and bring it and their larger ones along.  So all that a pair shares is known
    in the smallest shared diagnosis; elsewhere it counts for less, and the best rank is right.  No pair leaves its task: only the
    best partner of a cluster in a diagnosis does.  A ``large`` diagnosis is met in pairs of parts, in tasks of their own.
    """
    rows = clusters.select("*", F.posexplode("dxs").alias("_at", "dx")).where("_at = 0 OR dxs[_at - 1] <> dx").withColumn("dxs", F.expr("slice(dxs, _at + 1, size(dxs) - _at)"))
    n = clusters.agg(F.sum(F.size("dxs"))).first()[0] or 0
    one = F.pmod(F.xxhash64("block", "dx"), F.lit(max(16, n // TASK_ROWS)))
    if large is None:
        rows = rows.withColumns({"bi": F.lit(0).cast("long"), "bj": F.lit(0).cast("long"), "_part": one})
    else:
        rows = rows.join(large, ["block", "dx"], "left").withColumn("parts", F.coalesce("parts", F.lit(1).cast("long")))
        rows = rows.withColumn("_own", F.pmod(F.xxhash64("id"), "parts")).withColumn("_other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
        rows = rows.withColumns({"bi": F.least("_own", "_other"), "bj": F.greatest("_own", "_other")})
        rows = rows.withColumn("_part", F.when(F.col("parts") == 1, one).otherwise(F.xxhash64("block", "dx", "bi", "bj")))

    def meet(t: pa.Table) -> pa.Table:
        id_, block, lo, hi, n, dx, bi, bj = (t.column(c).to_numpy() for c in ("id", "block", "lo", "hi", "n", "dx", "bi", "bj"))
        lists = t.column("dxs").combine_chunks()
        p, rank, q = best_in_groups(id_, np.stack([block, bi, bj, dx], 1), lo, hi, n, dx, np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy(), k, max_cases)
        return pa.table({"p": p, "rank": rank, "q": q})

    found = rows.select("_part", "id", "block", "bi", "bj", "dx", "lo", "hi", "n", "dxs").groupBy("_part").applyInArrow(meet, "p long, rank long, q long")
    return found.groupBy("p").agg(F.min(F.struct("rank", "q")).alias("best")).select("p", F.col("best.q").alias("q"))


def ranges(begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All whole numbers of each range, one range after another, and the range of each."""
    size = end - begin
    of = np.repeat(np.arange(len(size)), size)
    return np.arange(size.sum()) - np.repeat(np.cumsum(size) - size - begin, size), of


def best_in_groups(id_: np.ndarray, group: np.ndarray, lo: np.ndarray, hi: np.ndarray, n: np.ndarray, dx: np.ndarray, size: np.ndarray, dxs: np.ndarray, k: int, max_cases: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(p, rank, q): of each row that has partners in its group the best one; the least rank counts over all groups.

    A pair's rank has its shared diagnoses (65,535 at most) above 48 bits of its hash.
    """
    # Entries: a diagnosis of a row and its number of members.  Those of one column, a diagnosis in a group, are sorted by age.
    order = np.lexsort(group.T)
    new = np.append(False, (group[order][1:] != group[order][:-1]).any(axis=1))
    g = np.empty(len(order), np.int64)
    g[order] = np.cumsum(new)
    kinds, code = np.unique(np.concatenate([dx, dxs]), return_inverse=True)
    row, times = np.unique(np.repeat(np.arange(len(size)), size) * len(kinds) + code[len(dx) :], return_counts=True)
    row, what = np.divmod(row, len(kinds))
    column = np.unique(g[row] * len(kinds) + what, return_inverse=True)[1]
    base = lo.min() if len(lo) else 0
    span = (lo.max() - base if len(lo) else 0) + 2 * WIDTH + 2
    place = column * span + (lo[row] - base)
    by = np.argsort(place, kind="stable")
    row, times, place, own = row[by], times[by], place[by], what[by] == code[: len(dx)][row[by]]
    begin, end = np.searchsorted(place, place - WIDTH), np.searchsorted(place, place + WIDTH, "right")
    # In order of rows; an entry that meets only itself is no other's.
    use = np.flatnonzero(own | (end - begin > 1))
    use = use[np.argsort(row[use], kind="stable")]
    cost = np.cumsum(np.bincount(row[use], (end - begin)[use], len(size)))
    h = mixed(id_.view(np.uint64) + np.uint64((k + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))
    mine = np.zeros(len(size), np.int64)
    mine[row[own]] = times[own]
    out = []

    def met(e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Rows that fit each other, and what entries e count of their shared diagnoses."""
        other, of = ranges(begin[e], end[e])
        i, j = row[e][of], row[other]
        fit = (i != j) & (n[i] + n[j] <= max_cases) & (np.maximum(hi[i], hi[j]) - np.minimum(lo[i], lo[j]) <= WIDTH)
        return i[fit], j[fit], times[e][of[fit]] * times[other[fit]]

    def best(i: np.ndarray, j: np.ndarray, w: np.ndarray) -> None:
        """Of sorted rows i the partner with the least rank, of equal ones the smallest id."""
        if len(i):
            rank = (np.uint64(0xFFFF) - np.minimum(w, 0xFFFF).astype(np.uint64) << np.uint64(48)) | (mixed(h[i] ^ h[j]) >> np.uint64(16))
            head = np.flatnonzero(np.append(True, i[1:] != i[:-1]))
            least = np.minimum.reduceat(rank, head)
            hit = np.flatnonzero(rank == np.repeat(least, np.diff(np.append(head, len(i)))))
            hit = hit[np.lexsort((id_[j[hit]], i[hit]))]
            hit = hit[np.append(True, i[hit][1:] != i[hit][:-1])]
            out.append((i[hit], rank[hit], j[hit]))

    at, first = 0, np.searchsorted(row[use], np.arange(len(size) + 1))
    while at < len(size):
        stop = max(at + 1, int(np.searchsorted(cost, (cost[at - 1] if at else 0) + PAIRS, "right")))
        e = use[first[at] : first[stop]]
        at = stop
        i, j, w = met(e[own[e]])
        best(i, j, w)
        # Pairs with more than this diagnosis in common rank before what was counted of them.
        x, y, more = met(e[~own[e]])
        if len(x):
            pair, inverse = np.unique(x * len(size) + y, return_inverse=True)
            x, y = np.divmod(pair, len(size))
            best(x, y, np.bincount(inverse, more).astype(np.int64) + mine[x] * mine[y])
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    i, rank, j = (np.concatenate(x) for x in zip(*out, strict=True))
    p, q, rank = id_[i], id_[j], (rank ^ np.uint64(1 << 63)).view(np.int64)
    order = np.lexsort((q, rank, p))
    order = order[np.append(True, p[order][1:] != p[order][:-1])]
    return p[order], rank[order], q[order]


def mixed(x: np.ndarray) -> np.ndarray:
    """A hash of 64 bits."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def invariants(clusters: DataFrame, cases: DataFrame, max_cases: int = 5) -> DataFrame:
    """Counts of broken constraints; all are 0."""
    reused = clusters.groupBy("case_id").count().where("count > 1").agg(F.count("*").alias("reused"))
    per = clusters.join(cases, "case_id").groupBy("patient_id").agg(F.count_distinct("sex").alias("s"), (F.max("age_years") - F.min("age_years")).alias("w"), F.count("*").alias("n"))
    bad = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0))
    return reused.crossJoin(per.agg(bad(F.col("s") > 1).alias("mixed_sex"), bad(F.col("w") > WIDTH).alias("too_wide"), bad(F.col("n") > max_cases).alias("too_large")))


def grow(rows: pd.DataFrame, max_cases: int = 5, width: int = WIDTH) -> pd.DataFrame:
    """Sequential greedy growth over one block's (case_id, age_years, dx_id)."""
    dx = {k: set(v) for k, v in rows.groupby("case_id")["dx_id"]}
    age = rows.drop_duplicates("case_id").set_index("case_id")["age_years"].to_dict()
    by_dx = rows.groupby("dx_id")["case_id"].apply(lambda x: sorted(set(x))).to_dict()
    free, out = dict.fromkeys(sorted(dx)), []
    for seed in list(free):
        if seed not in free:
            continue
        del free[seed]
        members, lo, hi = [seed], age[seed], age[seed]
        while len(members) < max_cases:
            count: dict[int, int] = {}
            for m in members:
                for x in dx[m]:
                    for c in by_dx[x]:
                        if c in free and max(hi, age[c]) - min(lo, age[c]) <= width:
                            count[c] = count.get(c, 0) + 1
            if not count:
                break
            c = min(count, key=lambda c: (-count[c], c))
            del free[c]
            members.append(c)
            lo, hi = min(lo, age[c]), max(hi, age[c])
        out += [(m, seed) for m in members]
    return pd.DataFrame(out, columns=["case_id", "patient_id"])


def cluster_exact(cases: DataFrame, case_dx: DataFrame) -> DataFrame:
    """One case after another, per block of sex and a band of ages (bands bound what a task holds)."""
    band = F.floor(F.col("age_years") / (WIDTH + 1))
    rows = eligible(cases, case_dx).withColumn("band", band)
    return rows.groupBy("sex", "bucket", "band").applyInPandas(lambda p: grow(p[["case_id", "age_years", "dx_id"]]), "case_id long, patient_id long")
