"""A part of the driver's comparison with DuckDB, at the smallest size."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = ["canon_parts", "degree_all", "degree_pairs", "cust_neighbours_k2", "cust_types_t2", "hub_stop_d100", "part_features_k3", "page_features", "mode_support_only", "filter_pg", "mine_m_matrix", "ladder_part_k4_t1", "ladder_doc", "full_neighbourhood_chain", "seed_composition", "generalisation_counts", "feature_counts", "merged_predicates", "predicate_hierarchy", "literals_mined", "merged_predicates_mined", "predicate_hierarchy_mined", "extent_cut", "full_to_k4", "transitive_next"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_oracle(spark, duck, name):
    a, b = entry.queries()[name](spark, SF).toPandas(), duck.sql(entry.oracle_sql()[name]).df()
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    rows = lambda x: sorted(map(str, x[cols].astype(object).where(x[cols].notna(), None).values.tolist()))
    assert rows(a) == rows(b)


def test_entry_and_names(spark):
    assert entry.entry(spark).limit(1).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())
