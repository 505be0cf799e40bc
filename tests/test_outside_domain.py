"""Values beyond a domain, and beyond a long, against the SQL and plain arithmetic."""

from decimal import Decimal

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as e
from zbox.box import Box
from zbox.functions import curve
from zbox.sources import ztable as Z
from zbox.spec import DimSpec, ZSpec, quantize


def by_sql(name, **tables):
    import duckdb

    con = duckdb.connect()
    for t, path in tables.items():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}/*.parquet'")
    rel = con.execute(e.oracle_sql()[name])
    return [d[0] for d in rel.description], rel.fetchall()


def orders_at(spark, path, keys):
    df = spark.createDataFrame([(k, i % 700) for i, k in enumerate(keys)], "o_orderkey bigint, o_custkey bigint")
    df.write.parquet(f"{path}/orders.parquet")
    return str(path)


def test_far_orders_beyond_a_long_are_no_error(spark, tmp_path):
    sf = orders_at(spark, tmp_path, [5, 900, 6000, (1 << 20) + 3, 9_000_000])
    got = sorted((r.box_id, r.o_orderkey) for r in e.queries()["box_query_wide_domain"](spark, sf).collect())
    assert got == [(0, 5), (0, 900), (1, 5), (1, 900), (2, 5), (2, 900), (2, 6000), (3, 5), (3, 900), (3, 6000)]


def test_keys_of_far_orders_wrap_as_in_sql(spark, tmp_path):
    sf = orders_at(spark, tmp_path, [0, 7, 524_287, 524_288, 900_000, (1 << 20) - 2])
    _, want = by_sql("z_encode_wide_domain", orders=f"{sf}/orders.parquet")
    got = e.queries()["z_encode_wide_domain"](spark, sf).select("o_orderkey", "z").collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_extracted_counts_of_conversations_outside_the_grid(spark, tmp_path):
    df = spark.range(0, 3000).select(F.col("id").alias("conv_id"), (F.col("id") % 8).alias("turn"))
    df.write.parquet(f"{tmp_path}/conversations.parquet")
    cols, want = by_sql("extracted_counts", conversations=f"{tmp_path}/conversations.parquet")
    got = e.queries()["extracted_counts"](spark, str(tmp_path)).select(*cols).collect()
    assert sorted(map(tuple, got)) == sorted(want)


@pytest.mark.parametrize("d", [DimSpec("v", -3, 8, 2, overflow="wrap"), DimSpec("v", -5, (1 << 62) - 7, 20, overflow="wrap"), DimSpec("v", -5, (1 << 62) - 7, 20), DimSpec("v", 0, 99)])
def test_cells_of_values_beyond_a_long(spark, d):
    values = [*range(-30, 30), (1 << 62) - 7, (1 << 62) - 6, 1 << 63, 9_000_000 << 43, -(9_000_000 << 43)]
    df = spark.createDataFrame([(Decimal(v),) for v in values], "v decimal(38,0)")
    got = {int(r.v): r.c for r in df.select("v", quantize(F.col("v"), d).alias("c")).collect()}
    assert got == {v: d.quantize_value(v) for v in values}


def test_boxes_on_a_wrapped_domain(spark):
    df = spark.createDataFrame([(v, v) for v in range(-200, 300, 7)], "v bigint, k bigint")
    spec = ZSpec((DimSpec("v", 0, 99, 5, overflow="wrap"),))
    for box in (Box((10,), (60,)), Box((150,), (250,)), Box((None,), (20,)), Box((-50,), (50,))):
        for strategy in ("prefix_join", "array_search", "pushed_or"):
            got = sorted(r.k for r in Z.ZTable.of(df, spec).query(box, strategy=strategy).collect())
            assert got == [v for v in range(-200, 300, 7) if (box.lo[0] is None or v >= box.lo[0]) and v <= box.hi[0]]
    assert df.select(curve.z_of(spec)).distinct().count() <= 32
    with pytest.raises(ValueError):
        DimSpec("v", 0, 1, integer=False, overflow="wrap")
