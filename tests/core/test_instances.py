"""Instances are the same in one slice of patients or several, and links by shared findings are exact without counting pairs in a shuffle."""

import random
from collections import Counter

from pyspark.sql import functions as F

from caseloom.functions import instances, links
from caseloom.functions.labels import Labels
from caseloom.sources.tables import Tables

SF = "/root/testdata/sf0.001"


class Given(Tables):
    """Given frames in the place of tables and views."""

    def __init__(self, spark, **frames):
        super().__init__(spark, "")
        self.__dict__.update(frames)


def test_alike_is_exact_in_groups_and_parts(spark):
    r = random.Random(7)
    rows = [(d, f) for d in range(12) for f in range(60) if r.random() < 0.5] + [(d, 1000) for d in range(12)]
    df = spark.createDataFrame([*rows, (None, 3), (4, None)], "dx_id long, finding_id long").persist()
    t = Given(spark, dx_finding=df, lineitem=df)
    have = {d: {f for e, f in rows if e == d} for d in range(12)}
    want = {(a, b) for a in have for b in have if a < b and len(have[a] & have[b]) >= 17}
    assert 5 < len(want) < 60
    for room, groups in ((10**6, 16), (100, 1), (100, 4), (30, 3)):
        assert Counter(tuple(x) for x in links.alike(t, 17, room, groups).collect()) == Counter(want)
    assert links.alike(t, 500, 100, 4).count() == 0


def test_no_pair_of_diagnoses_is_shuffled(spark):
    """The gold of specialties counts no findings for pairs in a shuffle; before, a self-join on findings was aggregated by pair."""
    g = Labels(Tables(spark, SF))
    plan = g.spec_rows._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan or "FlatMapGroupsInArrow" in plan
    assert "AS shared#" not in plan


def test_links_through_category_of_a_doubled_supplier(spark):
    node = spark.createDataFrame([(1, "x"), (1, "y"), (2, "x"), (3, "z")], "dx_id long, category string")
    assert {tuple(r) for r in links.several(Given(spark, dx_node=node)).collect()} == {(1, 2)}


def test_slices_give_the_same_instances(spark):
    t = Tables(spark, SF)
    one, some = (instances.of(t, "public", rows=n).select(F.concat_ws("|", "task", "instance_id", "patient_id", "encounters", "n_gold")).collect() for n in (1 << 40, 3000))
    assert len(one) > 100 and sorted(one) == sorted(some)
