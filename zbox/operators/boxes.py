"""Boxes and pieces as DataFrames.

A box table has box_id, lo and hi (arrays of cell coordinates). Refining many boxes is work per box,
not per row of data: boxes are spread over the cluster and refined there."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from zbox.box import Box
from zbox.functions.curve import z_encode
from zbox.leaps import inside
from zbox.refine import refine
from zbox.spec import ZSpec
from zbox.widen import face_costs, widen

PIECES = "box_id bigint, piece int, z_lo bigint, z_hi bigint"
COSTS = "box_id bigint, visits bigint, leaps bigint, pieces bigint, covered bigint, steps int"


def make_boxes(spark: SparkSession, n: int, m: int, side: int, bits: int = 10, first: int = 0) -> DataFrame:
    """Boxes of equal sides with corners from integer arithmetic, the same in any engine."""
    room = (1 << bits) - side + 1
    corner = [F.pmod(F.lit(7919).cast("bigint") * F.col("id") + 104729 * d, F.lit(room)) for d in range(m)]
    return spark.range(first, first + n).select(F.col("id").alias("box_id"), F.array(*corner).alias("lo"), F.array(*(c + (side - 1) for c in corner)).alias("hi"))


def corner(i: int, d: int, side: int, bits: int = 10) -> int:
    return (7919 * i + 104729 * d) % ((1 << bits) - side + 1)


def box_of(i: int, m: int, side: int, bits: int = 10) -> Box:
    lo = tuple(corner(i, d, side, bits) for d in range(m))
    return Box(lo, tuple(x + side - 1 for x in lo))


def envelopes(boxes: DataFrame, spec: ZSpec) -> DataFrame:
    """box_id, zs, ze: two encodings, no Python."""
    z = lambda c: z_encode([F.get(F.col(c), F.lit(d)) for d in range(spec.m)], spec.bits)
    return boxes.select("box_id", z("lo").alias("zs"), z("hi").alias("ze"))


def _per_box(boxes: DataFrame, schema: str, make) -> DataFrame:
    """``make(Box) -> list of tuples``, on executors; null boxes and empty boxes give nothing."""
    names = [f.split()[0] for f in schema.split(", ")]

    def run(batches):
        for batch in batches:
            rows: list[tuple] = []
            ids, los, his = (batch.column(i).to_pylist() for i in range(3))
            for i, lo, hi in zip(ids, los, his, strict=True):
                if lo is None or hi is None or any(a is None or b is None or a > b for a, b in zip(lo, hi, strict=True)):
                    continue
                rows += [(i, *r) for r in make(Box(tuple(lo), tuple(hi)))]
            columns = list(zip(*rows, strict=True)) or [()] * len(names)
            yield pa.RecordBatch.from_pydict(dict(zip(names, columns, strict=True)), schema=target)

    target = pa.schema([(f.split()[0], {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string()}[f.split()[1]]) for f in schema.split(", ")])
    spark = boxes.sparkSession
    return boxes.select("box_id", "lo", "hi").repartition(spark.sparkContext.defaultParallelism, "box_id").mapInArrow(run, schema)


def refine_boxes(boxes: DataFrame, spec: ZSpec, method: str = "widened", **options) -> DataFrame:
    """(box_id, piece, z_lo, z_hi): pieces from 0, ascending."""
    return _per_box(boxes, PIECES, lambda b: [(k, *p) for k, p in enumerate(refine(b, spec, method, **options).pieces)])


def refine_costs(boxes: DataFrame, spec: ZSpec, method: str = "widened", **options) -> DataFrame:
    """The counters of a refinement of every box."""

    def make(b: Box):
        r = refine(b, spec, method, **options)
        return [(r.visits, r.leaps, len(r.pieces), r.covered, r.steps)]

    return _per_box(boxes, COSTS, make)


def face_cost_table(boxes: DataFrame, spec: ZSpec) -> DataFrame:
    """(box_id, dim, side, face_num, shift): cost = face_num / 2**shift; dim from 1."""
    return _per_box(boxes, "box_id bigint, dim int, side string, face_num bigint, shift int", lambda b: [(c.dim + 1, c.side, c.num, c.shift) for c in face_costs(b, spec)])


def leap_table(boxes: DataFrame, spec: ZSpec, leaps: list, col: str) -> DataFrame:
    """(box_id, z, col0, ...): every key of the grid outside the box (of ``leap_in``), or inside it before its
    last (of ``leap_out``), and what each function gives for it. For small grids."""

    def make(b: Box):
        zs, ze = b.envelope(spec)
        keys = range(spec.full + 1) if col == "leap_in" else range(zs, ze)
        return [(z, *(f(z, zs, ze, spec) for f in leaps)) for z in keys if inside(z, zs, ze, spec) == (col == "leap_out")]

    return _per_box(boxes, ", ".join(["box_id bigint", "z bigint", *(f"{col}{k} bigint" for k in range(len(leaps)))]), make)


def widen_boxes(boxes: DataFrame, spec: ZSpec, threshold: float = 500) -> DataFrame:
    """(box_id, lo, hi, steps, total): every box widened under the threshold."""
    flat = ", ".join(["box_id bigint"] + [f"{e}{d} bigint" for e in ("lo", "hi") for d in range(spec.m)] + ["steps int", "total double"])

    def make(b: Box):
        w = widen(b, spec, threshold)
        return [(*w.box.lo, *w.box.hi, w.steps, float(w.total))]

    out = _per_box(boxes, flat, make)
    return out.select("box_id", F.array(*(f"lo{d}" for d in range(spec.m))).alias("lo"), F.array(*(f"hi{d}" for d in range(spec.m))).alias("hi"), "steps", "total")


def box_measures(boxes: DataFrame, m: int) -> DataFrame:
    """(box_id, volume, surface), in columns."""
    side = [F.get(F.col("hi"), F.lit(d)) - F.get(F.col("lo"), F.lit(d)) + 1 for d in range(m)]
    product = lambda xs: _product(xs)
    return boxes.select("box_id", product(side).alias("volume"), (2 * sum((product(side[:d] + side[d + 1 :]) for d in range(m)), F.lit(0).cast("bigint"))).alias("surface"))


def _product(xs: list[Column]) -> Column:
    out = F.lit(1).cast("bigint")
    for x in xs:
        out = out * x
    return out


def merge_pieces(pieces: DataFrame) -> DataFrame:
    """Adjoining or overlapping pieces of a box become one; numbered anew."""
    by = Window.partitionBy("box_id").orderBy("z_lo", "z_hi")
    before = F.max("z_hi").over(by.rowsBetween(Window.unboundedPreceding, -1))
    starts = pieces.withColumn("starts", (before.isNull() | (F.col("z_lo") > before + 1)).cast("int"))
    runs = starts.withColumn("run", F.sum("starts").over(by)).groupBy("box_id", "run").agg(F.min("z_lo").alias("z_lo"), F.max("z_hi").alias("z_hi"))
    return runs.select("box_id", (F.col("run") - 1).cast("int").alias("piece"), "z_lo", "z_hi")


def intersect_pieces(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """(key, z_lo, z_hi): what two tables of pieces share. Pieces of one key and side are disjoint, so a sweep
    over the ends tells where both are open; no pairs are made."""
    ends = None
    for side in (a, b):
        for at in (side.select(key, F.col("z_lo").alias("at"), F.lit(1).alias("step")), side.select(key, (F.col("z_hi") + 1).alias("at"), F.lit(-1).alias("step"))):
            ends = at if ends is None else ends.unionByName(at)
    ends = ends.groupBy(key, "at").agg(F.sum("step").alias("step"))
    along = Window.partitionBy(key).orderBy("at")
    open_ = F.sum("step").over(along.rowsBetween(Window.unboundedPreceding, 0))
    swept = ends.withColumns({"open": open_, "next": F.lead("at").over(along)})
    both = swept.filter("open = 2").select(key, F.col("at").alias("z_lo"), (F.col("next") - 1).alias("z_hi"))
    return both


def refine_prefix_tree(boxes: DataFrame, spec: ZSpec, max_depth: int | None = None) -> DataFrame:
    """Pieces by splitting cells level by level in DataFrame operations: cells within the box are kept,
    cells across its border split in 2**m, others dropped. Stopping at ``max_depth`` keeps border cells
    whole, which covers more than the box. An independent check of the leaps."""
    depth = spec.bits if max_depth is None else min(max_depth, spec.bits)
    env = envelopes(boxes, spec)
    level = env.select("box_id", "zs", "ze", F.lit(0).cast("bigint").alias("z"))
    kept = []
    for k in range(depth + 1):
        size = spec.key_bits - k * spec.m  # bits below a cell of this level
        low, high = F.col("z"), F.col("z").bitwiseOR(F.lit((1 << size) - 1).cast("bigint"))
        masks = [F.lit(x).cast("bigint") for x in spec.masks]
        cut = lambda c, x: c.bitwiseAND(x)
        meets = within = F.lit(True)
        for x in masks:
            meets = meets & (cut(high, x) >= cut(F.col("zs"), x)) & (cut(low, x) <= cut(F.col("ze"), x))
            within = within & (cut(low, x) >= cut(F.col("zs"), x)) & (cut(high, x) <= cut(F.col("ze"), x))
        state = level.filter(meets).withColumn("within", within)
        last = k == depth
        kept.append(state.filter(F.lit(last) | F.col("within")).select("box_id", F.lit(0).alias("piece"), F.col("z").alias("z_lo"), high.alias("z_hi")))
        if not last:
            step = 1 << (size - spec.m)
            child = F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit((1 << spec.m) - 1).cast("bigint")))
            level = state.filter(~F.col("within")).withColumn("child", child).select("box_id", "zs", "ze", (F.col("z") + F.col("child") * step).alias("z"))
    all_ = kept[0]
    for x in kept[1:]:
        all_ = all_.unionByName(x)
    return merge_pieces(all_)


def coalesce_piece_table(pieces: DataFrame, k: int) -> DataFrame:
    """At most k pieces a box by closing its smallest gaps, the earlier of equal ones first."""
    by = Window.partitionBy("box_id").orderBy("z_lo")
    p = pieces.select("box_id", "z_lo", "z_hi", (F.col("z_lo") - F.lag("z_hi").over(by)).alias("gap"), F.count("*").over(Window.partitionBy("box_id")).alias("n"))
    rank = F.row_number().over(Window.partitionBy("box_id").orderBy(F.col("gap").asc_nulls_last(), "z_lo"))
    p = p.withColumn("starts", (F.col("gap").isNull() | (rank > F.col("n") - k)).cast("int"))
    runs = p.withColumn("run", F.sum("starts").over(by)).groupBy("box_id", "run").agg(F.min("z_lo").alias("z_lo"), F.max("z_hi").alias("z_hi"))
    return runs.select("box_id", (F.col("run") - 1).cast("int").alias("piece"), "z_lo", "z_hi")


def register_udtf(spark: SparkSession, name: str = "refine_box") -> None:
    """SQL: ``SELECT * FROM boxes, LATERAL refine_box(lo, hi, bits, method)``."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="piece int, z_lo bigint, z_hi bigint")
    class RefineBox:
        def eval(self, lo, hi, bits, method):
            if lo is None or hi is None or any(a > b for a, b in zip(lo, hi, strict=True)):
                return
            spec = ZSpec.grid(len(lo), bits)
            for k, (a, b) in enumerate(refine(Box(tuple(lo), tuple(hi)), spec, method).pieces):
                yield k, a, b

    spark.udtf.register(name, RefineBox)
