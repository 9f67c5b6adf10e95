"""Queries against their SQL on the smallest tables."""

import collections

import duckdb
import pytest

from graphpart.queries import ORACLE, QUERIES
from graphpart.sources.tables import TABLES
from tests.conftest import SF

NAMES = ["graph_web", "sym_weighted_events", "best_label", "migration_prob", "blp_t3", "blp_t5_directed_events", "adapt_t3_all", "elastic_add_t3", "wcc", "quality_row", "flow_matrix", "load_history", "load_distance", "load_decay", "overflow_frequency", "within_slack", "event_windows_sliding", "href_extract", "sym_multiplicity_lines", "adapt_t3_affected", "stream_assign", "messages", "savings", "app_messages_hash_vs_blp", "quality_cube", "patience_window"]


def value(x):
    return round(float(x), 6) if isinstance(x, float) or type(x).__name__ == "Decimal" else x


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    rel = con.sql(ORACLE[name])
    assert sorted(rel.columns) == cols
    got = collections.Counter(tuple(map(value, r)) for r in df.select(cols).collect())
    assert got == collections.Counter(tuple(map(value, r)) for r in rel.select(*(f'"{c}"' for c in cols)).fetchall())
