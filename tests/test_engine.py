"""Columns, operators, tables, strategies, baselines and streams on small tables."""

import re

import pytest
from pyspark.sql import functions as F

from zbox import workload as W
from zbox.baselines.indices import IndependentIndex, MedianSplitIndex, MultiColumnIndex, PackedRectIndex, full_scan
from zbox.box import Box
from zbox.functions import curve
from zbox.operators import boxes as B
from zbox.operators.joins import level_of, level_of_table, opened_at, pieces_join
from zbox.plans.strategy import STRATEGIES, choose, choose_threshold
from zbox.refine import refine
from zbox.sources import ztable as Z
from zbox.spec import DimSpec, ZSpec, quantize


@pytest.mark.parametrize(("m", "bits"), [(1, 20), (2, 31), (3, 7), (5, 12), (6, 10)])
def test_encoding_columns(spark, m, bits):
    spec = ZSpec.grid(m, bits)
    rows = [tuple((i * 7919 + d * 104729) % (1 << bits) for d in range(m)) for i in range(50)] + [((1 << bits) - 1,) * m, (0,) * m]
    df = spark.createDataFrame(rows, ", ".join(f"c{d + 1} bigint" for d in range(m)))
    z = curve.z_encode([F.col(f"c{d + 1}") for d in range(m)], bits)
    back = curve.z_decode(F.col("z"), m, bits)
    wide = curve.z_encode_wide([F.col(f"c{d + 1}") for d in range(m)], bits)
    for r in df.withColumn("z", z).withColumn("w", wide).select("*", F.array(*back).alias("b")).collect():
        coords = tuple(r[:m])
        assert r.z == spec.interleave(coords) == int.from_bytes(bytes(r.w), "big") and tuple(r.b) == coords


def test_quantize_matches_value(spark):
    dims = [DimSpec("v", -512, 512), DimSpec("v", -10, 10, 6, overflow="null"), DimSpec("v", -600.0, 600.0, 9, integer=False), DimSpec("v", -(1 << 40), 1 << 40, 12)]
    df = spark.createDataFrame([(v,) for v in (-9999, -512, -511, -10, -1, 0, 1, 10, 11, 512, 9999, None)], "v bigint")
    for d in dims:
        for r in df.select("v", quantize(F.col("v"), d).alias("q")).collect():
            assert r.q == d.quantize_value(r.v), (d, r)
    with pytest.raises(Exception, match="outside"):
        df.select(quantize(F.col("v"), DimSpec("v", 0, 1, overflow="error"))).collect()


@pytest.mark.parametrize("top", [20, 52, 53, 58, 61, 62])
@pytest.mark.parametrize("bits", [1, 10, 31, 62])
def test_rows_and_box_ends_fall_in_the_same_cell(spark, top, bits):
    """At any width: row by row, the column's cell is the box end's."""
    import random

    r = random.Random(top * 100 + bits)
    lo, hi = -r.randrange(1 << top), r.randrange(1 << (top - 1), 1 << top)
    d = DimSpec("v", lo, hi, bits)
    values = [lo, hi, lo - 1, hi + 1, 0, lo + 1, hi - 1, -(1 << 63), (1 << 63) - 1, *(r.randint(lo, hi) for _ in range(60))]
    edge = hi - lo + 1
    values += [lo + (k * edge >> min(bits, 20)) + e for k in range(0, 1 << min(bits, 20), max(1, (1 << min(bits, 20)) // 30)) for e in (-1, 0)]
    df = spark.createDataFrame([(v,) for v in values], "v bigint")
    got = {x.v: x.c for x in df.select("v", quantize(F.col("v"), d).alias("c")).collect()}
    assert got == {v: d.quantize_value(v) for v in values}


def test_wide_domain_and_keyless_rows(spark):
    """Every strategy returns what the scan returns."""
    rows = [(1 << 52, 1), ((1 << 52) + 1, 2), (50, 3), (150, 4), (None, 5), (-3, 6)]
    df = spark.createDataFrame(rows, "v bigint, k bigint")
    for d, box, want in (
        (DimSpec("v", 0, 1 << 53), Box((0,), (1 << 52,)), {1, 3, 4}),
        (DimSpec("v", 0, 1 << 61), Box((0,), (1 << 52,)), {1, 3, 4}),
        (DimSpec("v", 0, 100, overflow="null"), Box((0,), (200,)), {3, 4}),
        (DimSpec("v", 0, 100, overflow="null"), Box((None,), (60,)), {3, 6}),
        (DimSpec("v", 0, 100, overflow="null"), Box((101,), (1 << 60,)), {1, 2, 4}),
        (DimSpec("v", 0, 100, overflow="null"), Box((0,), (100,)), {3}),
    ):
        for strategy in STRATEGIES:
            assert {r.k for r in Z.ZTable.of(df, ZSpec((d,))).query(box, strategy=strategy).collect()} == want, (d, strategy)


def test_too_wide_for_a_long():
    with pytest.raises(ValueError):
        curve.z_encode([None] * 7, 10)


def test_refine_boxes_empty_and_null(spark):
    boxes = spark.createDataFrame([(1, [2, 2], [5, 5]), (2, [5, 5], [2, 2]), (3, None, None)], "box_id bigint, lo array<bigint>, hi array<bigint>")
    got = B.refine_boxes(boxes, ZSpec.grid(2, 3), "exact").orderBy("piece").collect()
    assert [(r.box_id, r.z_lo, r.z_hi) for r in got] == [(1, 12, 15), (1, 24, 27), (1, 36, 39), (1, 48, 51)]
    assert B.refine_boxes(boxes.limit(0), ZSpec.grid(2, 3)).count() == 0
    coarse = B.refine_prefix_tree(boxes.filter("box_id = 1"), ZSpec.grid(2, 3), 1).collect()
    assert [(r.z_lo, r.z_hi) for r in coarse] == [(0, 63)]


def test_levels_agree(spark):
    pieces = [(0, 0), (5, 300), (1000, 1 << 40), ((1 << 62), (1 << 62) + 70_000)]
    df = spark.createDataFrame([(0, k, a, b) for k, (a, b) in enumerate(pieces)], B.PIECES)
    level, n = level_of(pieces)
    assert level_of_table(df) == (level, n) and opened_at(df, level).count() == n <= max(16 * len(pieces), 4096)
    assert level_of_table(df.limit(0)) is None


def test_join_plans(spark):
    rows = spark.range(4096).withColumnRenamed("id", "z")
    p = refine(Box((3, 5), (40, 50)), ZSpec.grid(2, 6), "exact").pieces
    pieces = spark.createDataFrame([(0, k, a, b) for k, (a, b) in enumerate(p)], B.PIECES)
    plan = pieces_join(rows, pieces, known=p)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "NestedLoop" not in plan
    for hint in ("broadcast", "merge", "shuffle_hash", "nested", None):
        assert pieces_join(rows, pieces, hint=hint).count() == 38 * 46
    assert pieces_join(rows, pieces.limit(0)).count() == 0


@pytest.fixture(scope="module")
def stored(spark, sf, tmp_path_factory):
    df, spec = W.points(spark, sf, "lineitem", 3)
    path = str(tmp_path_factory.mktemp("z") / "t")
    Z.write_z_table(df, spec, path, 8, key=["l_orderkey"])
    return df, spec, Z.ZTable.open(spark, path)


def test_every_strategy_and_method_gives_the_scan(stored):
    df, spec, table = stored
    key = list(W.FIXTURES["lineitem"].key)
    box = W.value_box(spec, 2, 300)
    want = sorted(map(tuple, full_scan(df, [d.column for d in spec.dims], box).select(*key).collect()))
    assert want
    for strategy in STRATEGIES:
        assert sorted(map(tuple, table.query(box, "widened", strategy, key, threshold=60).collect())) == want, strategy
    for method in ("none", "exact", "published", "published_one_bits"):
        assert sorted(map(tuple, table.query(box, method, columns=key).collect())) == want, method
    assert table.query(Box((1, 1, 1), (0, 0, 0))).count() == 0


def test_refining_extracts_less(stored):
    _, spec, table = stored
    n = {m: sum(table.extracted(W.value_box(spec, i, 200), m, "prefix_join")[0].count() for i in range(3)) for m in ("none", "widened", "exact")}
    assert n["none"] > 3 * n["widened"] and n["widened"] >= n["exact"]


def test_pushdown_and_no_shuffle(stored):
    _, spec, table = stored
    q = table.query(W.value_box(spec, 2, 60), columns=["l_orderkey"])
    plan = q._jdf.queryExecution().executedPlan().toString()  # long lists are cut short in it
    assert re.search(r"PushedFilters: \[\w*(?:Or|GreaterThanOrEqual|And|IsNotNull)\(", plan)
    assert "Exchange hashpartitioning" not in plan and "NestedLoop" not in plan
    few = table.files_for(refine(W.value_box(spec, 2, 20).cells(spec), spec, "exact").pieces)
    assert 0 < len(few) < len(table.manifest())


def test_baselines_give_the_scan(spark, sf, tmp_path):
    df, spec = W.points(spark, sf, "lineitem", 3)
    cols, key = [d.column for d in spec.dims], list(W.FIXTURES["lineitem"].key)
    indices = [
        IndependentIndex.build(df, cols, key, path=str(tmp_path / "i")), MultiColumnIndex.build(df, cols, path=str(tmp_path / "m")),
        PackedRectIndex.build(df, cols, 300, path=str(tmp_path / "r")), MedianSplitIndex.build(df, cols, 4, path=str(tmp_path / "k")),
    ]
    for box in (W.value_box(spec, 1, 400), W.value_box(spec, 1, 400).drop(0), W.value_box(spec, 1, 400).drop(2)):
        want = sorted(map(tuple, full_scan(df, cols, box).select(*key).collect()))
        for index in indices:
            assert sorted(map(tuple, index.query(box, key).collect())) == want
    leaves = indices[2].leaves(W.value_box(spec, 1, 100)).count()
    assert leaves < indices[2].directory.count()


def test_dropped_dimension(spark, tmp_path):
    """Without its first column a sorted layout skips nothing; key order does not depend on which is dropped."""
    df, spec = W.points(spark, "/root/testdata/sf0.01", "lineitem", 6)
    cols, box = [d.column for d in spec.dims], W.value_box(spec, 3, 300)
    MultiColumnIndex.build(df, cols, 64, str(tmp_path / "m"))
    Z.write_z_table(df, spec, str(tmp_path / "z"), 64)
    table = Z.ZTable.open(spark, str(tmp_path / "z"))
    by_z = [len(table.files_for(refine(b.cells(spec), spec, "widened").pieces)) for b in (box.drop(0), box.drop(5))]
    by_sort = [Z.files_by_statistics(spark, str(tmp_path / "m"), cols, b)[0] for b in (box.drop(0), box.drop(5))]
    assert by_sort[0] > 2.5 * by_sort[1] and max(by_z) <= 2 * min(by_z) and by_z[0] < by_sort[0]


def test_stream_drops_late_rows_and_appends_to_a_table(spark, tmp_path):
    import time

    from zbox.streaming import stream as S

    schema, spec = "box_id bigint, c1 bigint, c2 bigint, ts timestamp", ZSpec.grid(2, 6)
    for k, rows in enumerate(([(0, 1, 2, "2024-01-01 00:05:00"), (0, 3, 4, "2024-01-01 05:00:00")], [(0, 7, 8, "2024-01-01 09:00:00")], [(0, 5, 6, "2024-01-01 00:06:00")], [(0, 9, 9, "2024-01-01 23:00:00")])):
        df = spark.createDataFrame([(a, b, c, t) for a, b, c, t in rows], "box_id bigint, c1 bigint, c2 bigint, t string")
        df.select("box_id", "c1", "c2", F.to_timestamp("t").alias("ts")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(1.1)  # files are taken in order of time
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    hits = S.run_once(S.windowed_hits(stream, "ts", "1 hour", delay="1 hour")).collect()
    assert {(r.start.hour, r.hits) for r in hits} == {(0, 1), (5, 1), (9, 1)}  # 00:06 came after its window had closed; Spark sifts late rows by the watermark of the batch before
    S.append_to_z_table(stream.drop("ts"), spec, str(tmp_path / "z"), str(tmp_path / "c")).awaitTermination()
    table = Z.ZTable.open(spark, str(tmp_path / "z"))
    assert sorted(r.c1 for r in table.query(Box((3, 0), (7, 63))).collect()) == [3, 5, 7]


def test_choosing():
    spec = ZSpec.grid(2, 3)
    assert choose(refine(Box((0, 0), (7, 7)), spec, "exact"), spec, True) == "scan"
    assert choose(refine(Box((0, 0), (1, 0)), spec, "exact"), spec, True) == "manifest"
    assert choose(refine(Box((0, 0), (1, 0)), spec, "exact"), spec, False) == "scan"
    with pytest.raises(ValueError):
        choose(refine(None, spec), spec, False, "guess")
    assert choose_threshold(1_000_000, 10) == 64 and choose_threshold(1000, 10_000_000_000) == 5000


def test_readers_want_a_schema(spark):
    with pytest.raises(ValueError):
        Z.read(spark, "x", "csv")
    with pytest.raises(ValueError):
        Z.read(spark, "x", "xls")


def test_selected_queries_match_sql(spark):
    """A few registered queries on the smallest tables; the driver compares them all."""
    import duckdb

    import __spark_entry__ as e

    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("lineitem", "orders", "events", "conversations", "part", "customer", "nation"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    queries, sql = e.queries(), e.oracle_sql()
    for name in ("z_encode_3d", "refine_exact_3d", "refine_prefix_tree_2d", "widen_boxes", "face_costs", "box_query_4d", "partial_first", "extracted_counts", "box_join_many", "ev_stream_equals_batch", "coalesce_pieces"):
        df = queries[name](spark, sf)
        cols = sorted(df.columns)
        got = sorted(map(str, (tuple(r[c] for c in cols) for r in df.collect())))
        rel = con.execute(sql[name])
        at = [[d[0] for d in rel.description].index(c) for c in cols]
        assert got == sorted(map(str, (tuple(r[i] for i in at) for r in rel.fetchall()))), name
    assert e.entry(spark).columns == ["o_orderkey", "box_id"]
