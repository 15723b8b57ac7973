"""Clusters do not depend on whether blocks are clustered together or one after another, and all compatible pairs count."""

import random
from collections import Counter
from itertools import combinations
from pathlib import Path

import numpy as np

from caseloom.functions import patients
from caseloom.plans import checkpoint
from caseloom.sources.tables import Tables

SF = "/root/testdata/sf0.001"


def test_blocks_one_after_another(spark):
    t = Tables(spark, SF)
    few = t.src_case.where("case_id < 200")
    dx = t.case_dx.where("case_id < 200 AND dx_id <= 5").persist()
    few = few.join(dx.where("role <> 'differential'"), "case_id", "left_semi").persist()
    sets = [{(r["case_id"], r["patient_id"]) for r in patients.cluster(few, dx, max_rounds=2, split_from=n).collect()} for n in (0, 1 << 40)]
    assert sets[0] == sets[1] and len({p for _, p in sets[0]}) < len(sets[0]) == few.count()
    assert patients.cluster(few.limit(0), t.case_dx, split_from=0).count() == 0
    assert not list(Path(checkpoint.ready(spark).removeprefix("file:")).glob("packed-*"))


def test_partners_beyond_the_next_in_age_are_found(spark):
    """Cases 1 and 2 share two diagnoses; 12 others stand between them in order of age, in each of both."""
    others = [(10 + i, "F", 51 + i % 5) for i in range(24)]
    cases = spark.createDataFrame([(1, "F", 50), (2, "F", 57), *others], "case_id long, sex string, age_years int")
    dx = [(c, d, "primary") for c in (1, 2) for d in (7, 8)] + [(c, 7 + i % 2, "secondary") for i, (c, _, _) in enumerate(others)]
    of = dict(patients.cluster(cases, spark.createDataFrame(dx, "case_id long, dx_id long, role string"), max_cases=2).collect())
    assert of[1] == of[2] and Counter(Counter(of.values()).values()) == {2: 13}


def test_rounds_over_all_pairs(spark, monkeypatch):
    """The same rounds over all pairs in Python; diagnoses are met in one task or in parts."""
    r = random.Random(5)
    cases = [(i * 3 + 1, r.choice("FM") if i % 40 else None, r.randrange(30, 50) if i % 31 else None) for i in range(160)]
    dx = {c: {r.randrange(40) for _ in range(r.randrange(1, 4))} | ({99} if r.random() < 0.5 else set()) for c, _, _ in cases}
    df = spark.createDataFrame(cases, "case_id long, sex string, age_years int")
    df_dx = spark.createDataFrame([(c, d, "primary") for c, x in dx.items() for d in x] + [(c, None, "secondary") for c in dx if c % 2], "case_id long, dx_id long, role string")
    known = {c: (s, a) for c, s, a in cases if s and a}
    now, k = {c: [c] for c in known}, 0
    while True:
        best = {}
        for x, y in combinations(sorted(now), 2):
            m = now[x] + now[y]
            ages, shared = [known[c][1] for c in m], sum(len(dx[a] & dx[b]) for a in now[x] for b in now[y])
            if shared and len(m) <= 5 and max(ages) - min(ages) <= patients.WIDTH and len({(known[c][0], known[c][1] < 40) for c in m}) == 1:
                hx, hy = patients.mixed(np.array([x, y], np.uint64) + np.uint64((k + 1) * 0x9E3779B97F4A7C15 % (1 << 64)))
                rank = (-shared, int(patients.mixed(np.array([hx ^ hy]))[0]) >> 16)
                for p, q in ((x, y), (y, x)):
                    best[p] = min(best.get(p, (rank, q)), (rank, q))
        if not best:
            break
        for p, (_, q) in best.items():
            if p < q and best[q][1] == p:
                now[p] += now.pop(q)
        k += 1
    want = {c: c for c, _, _ in cases} | {c: p for p, m in now.items() for c in m}
    assert k > 8 > len(Counter(Counter(want.values()).values())) > 3
    assert dict(patients.cluster(df, df_dx).collect()) == want
    monkeypatch.setattr(patients, "HUB", 10)
    assert dict(patients.cluster(df, df_dx).collect()) == want


def test_pairs_a_few_at_a_time(monkeypatch):
    r = np.random.default_rng(1)
    n = r.integers(1, 6, 400)
    dxs = np.concatenate([np.sort(r.integers(0, 30, x)) for x in n])
    dx, lo = dxs[np.cumsum(n) - n], r.integers(40, 60, 400)
    rows = np.arange(400), np.stack([r.integers(0, 2, 400), dx], 1), lo, lo + r.integers(0, 4, 400), n, dx, n, dxs, 0, 5
    whole = patients.best_in_groups(*rows)
    monkeypatch.setattr(patients, "PAIRS", 20)
    assert len(whole[0]) > 100 and all(map(np.array_equal, whole, patients.best_in_groups(*rows)))
