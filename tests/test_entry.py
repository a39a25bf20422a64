"""Each reference query answers like its operator, on the smallest tables."""

import os

import duckdb
import pytest

from inverse_engine import queries

SF = "/root/testdata/sf0.001"
SMALL = ["eps_inverse_joint", "eps_bichromatic", "eps_validate_empty", "knn_inverse_joint", "knn_incl_q", "knn_forward", "knn_hull_count_2d", "sky_inverse_joint", "sky_static", "sky_dynamic", "topk_inverse", "excluded_members_knn", "query_sampler", "asof_last_profile"]


def rows(columns, found):
    place = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(round(r[i], 7) if isinstance(r[i], float) else r[i] for i in place) for r in found), key=repr)


@pytest.mark.parametrize("name", SMALL)
def test_against_reference(spark, name):
    run, sql = queries.CASES[name]
    base = duckdb.connect()
    for f in os.listdir(SF):
        base.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{SF}/{f}')")
    want, got = base.sql(sql), run(spark, SF)
    assert sorted(want.columns) == sorted(got.columns)
    assert rows(want.columns, want.fetchall()) == rows(got.columns, got.collect())
