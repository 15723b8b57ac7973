"""Queries that made their rows up read the given tables now, and the literals keep their forms."""

import duckdb
import pytest

from caseloom import fixtures
from caseloom.operators import registry, scoring
from caseloom.sources.tables import NAMES

SF = "/root/testdata/sf0.001"
KEYS = ["q_coverage", "q_published_agent_effects", "q_published_mean_rank", "q_tool_registry", "q_udf_binom"]


def rows(df):
    return sorted(tuple("NULL" if v is None or v != v else f"{v:.6f}" if isinstance(v, float) else str(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("key", KEYS)
def test_reads_a_table_and_is_the_same_as_duckdb(spark, key):
    con = duckdb.connect()
    for n in NAMES:
        con.sql(f"CREATE VIEW {n} AS SELECT * FROM read_parquet('{SF}/{n}.parquet')")
    df = registry.queries()[key](spark, SF)
    assert any(f"{n}.parquet" in f for f in df.inputFiles() for n in NAMES)
    got, want = df.toPandas(), con.sql(registry.oracle_sql()[key]).df()
    assert len(got) and sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)


def test_published_coverage(spark):
    got = {r["capability"]: (r["absent"], r["partial"], r["full"]) for r in scoring.coverage(fixtures.capabilities(spark), "row", fixtures.CAPABILITY_NAMES).collect()}
    for i, name in enumerate(fixtures.CAPABILITY_NAMES):
        assert got[name] == tuple(sum(c[i] == level for c in fixtures.CAPABILITIES) for level in "012")
