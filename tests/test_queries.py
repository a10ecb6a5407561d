"""Every query with SQL gives DuckDB's rows; every other one gives rows."""

import math

import duckdb
import pytest

from edgeblocks.plans.queries import ORACLES, QUERIES
from edgeblocks.sources.tables import TABLES


@pytest.fixture(scope="module")
def duck(small):
    c = duckdb.connect()
    c.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return c


def shown(v):
    return ("nan" if math.isnan(v) else repr(v)) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql_twin(spark, duck, small, name):
    df = QUERIES[name](spark, small)
    cols = sorted(df.columns)
    ours = sorted(tuple(map(shown, r)) for r in df.select(*cols).collect())
    got = duck.execute(ORACLES[name])
    names = [x[0] for x in got.description]
    assert sorted(names) == cols
    theirs = sorted(tuple(shown(r[names.index(c)]) for c in cols) for r in got.fetchall())
    assert ours == theirs


@pytest.mark.parametrize("name", ["random_rf", "load_quantiles_hash", "replication_preview_hash", "window_graph_sliding", "stream_late_edges", "stream_dedup", "graph_knn", "experiment_buffer_sweep", "experiment_messages"])
def test_rows(spark, small, name):
    assert QUERIES[name](spark, small).count() > 0


def test_every_oracle_has_a_query():
    assert not set(ORACLES) - set(QUERIES)


@pytest.mark.parametrize("name", ["alpha_static", "alpha_vertex", "best_of_published", "block_cap", "coarsest_sizes", "fennel_gain_grid", "improvement_published", "model_none", "performance_profile_large_k", "performance_profile_published", "pivot_published", "relative_published"])
def test_spark_reads_a_table(spark, small, name):
    """No rows made on the driver, no empty plan."""
    df = QUERIES[name](spark, small)
    assert df.inputFiles() and df.count() > 0


def test_bounds_of_every_graph(duck):
    """batch_bounds leaves out no graph, and no mode in four lanes."""
    from edgeblocks.plans.graphs import NAMES

    rows = duck.execute(ORACLES["batch_bounds"]).fetchall()
    assert {r[:3] for r in rows} == {(n, mode, lanes) for n in NAMES for mode in ("minimal", "subset", "maximal") for lanes in (1, 4)}
