"""Queries whose boxes come from a given table: they match their SQL, and cannot do without the table."""

import pytest

import __spark_entry__ as e

NAMES = (
    "coalesce_pieces",
    "cover_published",
    "cover_published_one_bits",
    "cover_widened",
    "envelope_boxes",
    "face_costs",
    "leap_in_table",
    "leap_out_published",
    "leap_out_table",
    "monotone_keys",
    "piece_intersect",
    "refine_counters",
)


@pytest.mark.parametrize("name", NAMES)
def test_reads_its_table_and_matches_sql(spark, sf, name, tmp_path):
    import duckdb

    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        e.queries()[name](spark, str(tmp_path)).collect()
    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    rel = con.execute(e.oracle_sql()[name])
    cols = [d[0] for d in rel.description]
    got = e.queries()[name](spark, sf).select(*cols).collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, rel.fetchall())) and got
