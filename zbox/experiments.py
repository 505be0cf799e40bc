"""The published experiments on uniform rows, or on any point table: layouts side by side.

``uniform`` makes the rows by integer arithmetic, so any engine can make the same. ``compare`` writes every
layout, asks each the same boxes at every selectivity, with one dimension dropped too, and reports mean
seconds a box, rows, files and bytes that a scan cannot skip."""

from __future__ import annotations

from statistics import mean
from time import perf_counter

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zbox import workload as W
from zbox.baselines.indices import IndependentIndex, MedianSplitIndex, MultiColumnIndex, PackedRectIndex, full_scan
from zbox.box import Box
from zbox.refine import refine
from zbox.sources import ztable as Z
from zbox.sources.scratch import scratch
from zbox.spec import DimSpec, ZSpec

SELECTIVITIES = (1e-4, 1e-3, 1e-2, 1e-1)
LOW, HIGH = -512, 512


def uniform(spark: SparkSession, rows: int, m: int) -> tuple[DataFrame, ZSpec]:
    """A key and m columns of whole numbers from LOW to HIGH, without value columns."""
    cols = [(F.pmod(F.xxhash64("id", F.lit(d)), F.lit(HIGH - LOW + 1)) + LOW).alias(f"c{d + 1}") for d in range(m)]
    return spark.range(rows).select("id", *cols), ZSpec(tuple(DimSpec(f"c{d + 1}", LOW, HIGH) for d in range(m)))


def _bytes_of(spark: SparkSession, paths: list[str]) -> int:
    conf, hadoop = spark.sparkContext._jsc.hadoopConfiguration(), spark.sparkContext._jvm.org.apache.hadoop.fs
    at = [hadoop.Path(p) for p in paths]
    return sum(p.getFileSystem(conf).getFileStatus(p).getLen() for p in at)


def build(spark: SparkSession, df: DataFrame, spec: ZSpec, key: list[str], files: int, kinds: tuple[str, ...]) -> tuple[dict, dict]:
    """(layouts by name, seconds of building)."""
    cols, made, seconds = [d.column for d in spec.dims], {}, {}

    def z_table():
        path = scratch(spark, "z")
        Z.write_z_table(df, spec, path, files)
        return Z.ZTable.open(spark, path)

    ways = {
        "z": z_table,
        "multicolumn": lambda: MultiColumnIndex.build(df, cols, files, scratch(spark, "sorted")),
        "independent": lambda: IndependentIndex.build(df, cols, key, files, scratch(spark, "sides")),
        "rect": lambda: PackedRectIndex.build(df, cols, path=scratch(spark, "rect"), files=files),
        "median": lambda: MedianSplitIndex.build(df, cols, path=scratch(spark, "median"), files=files),
    }
    for name in kinds:
        began = perf_counter()
        made[name] = ways[name]()
        seconds[name] = round(perf_counter() - began, 3)
    return made, seconds


def ask(made: dict, spec: ZSpec, key: list[str], boxes: list[Box]) -> dict:
    """Mean seconds a box and rows of all boxes, by layout; the full scan reads the z-table's files."""
    cols = [d.column for d in spec.dims]
    plain = made["z"].df
    ways = {"scan": lambda b: full_scan(plain, cols, b).select(*key), "z": lambda b: made["z"].query(b, columns=key)}
    ways |= {name: (lambda b, i=i: i.query(b, key)) for name, i in made.items() if name != "z"}
    out, found = {}, set()
    for name, way in ways.items():
        way(boxes[0]).count()
        spans, rows = [], 0
        for b in boxes:
            began = perf_counter()
            rows += way(b).count()
            spans.append(perf_counter() - began)
        out[name] = round(mean(spans), 4)
        found.add(rows)
    if len(found) != 1:
        raise RuntimeError(f"layouts disagree: {found}")
    return out | {"rows": found.pop()}


def compare(spark: SparkSession, df: DataFrame, spec: ZSpec, key: list[str], files: int = 32, n: int = 5, kinds: tuple[str, ...] = ("z", "multicolumn", "independent", "rect", "median"), along_drop: int = 400) -> dict:
    """Everything of one point table."""
    m = spec.m
    made, seconds = build(spark, df, spec, key, files, kinds)
    z, cols = made["z"], [d.column for d in spec.dims]
    total = z.df.count()
    manifest = z.manifest()
    all_bytes = _bytes_of(spark, [r["path"] for r in manifest])
    out: dict = {"rows": total, "files": len(manifest), "mb": round(all_bytes / 1e6, 1), "build": seconds, "by_selectivity": {}, "partial": {}}

    def layout(boxes: list[Box]) -> dict:
        picked = [z.files_for(refine(b.cells(spec), spec, "widened").pieces) for b in boxes]
        skipped = {"z_files": round(mean(map(len, picked)), 1), "z_mb": round(mean(_bytes_of(spark, p) for p in picked) / 1e6, 2)}
        sorted_files = [Z.files_by_statistics(spark, made["multicolumn"].path, cols, b)[0] for b in boxes[:2]]
        return skipped | {"multicolumn_files": round(mean(sorted_files), 1)}

    for s in SELECTIVITIES:
        boxes = [W.value_box(spec, i, W.side_for(s, m)) for i in range(n)]
        got = ask(made, spec, key, boxes)
        out["by_selectivity"][f"{s:g}"] = got | layout(boxes) | {"selectivity": got["rows"] / total / n}
    for label, d in (("none", None), ("first", 0), ("last", m - 1)):
        boxes = [W.value_box(spec, i, along_drop) for i in range(n)]
        boxes = boxes if d is None else [b.drop(d) for b in boxes]
        some = {k: v for k, v in made.items() if k in ("z", "multicolumn")}
        out["partial"][label] = ask(some, spec, key, boxes) | layout(boxes)
    return out


def main() -> None:
    """``python -m zbox.experiments ROWS FILES BOXES``: uniform rows in 3 and 6 dimensions, as JSON."""
    import json
    import sys

    rows, files, n = (int(x) for x in (*sys.argv[1:], *("10000000", "128", "5")[len(sys.argv) - 1 :]))
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "32").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for m in (3, 6):
        df, spec = uniform(spark, rows, m)
        kinds = ("z", "multicolumn", "independent", "rect", "median") if m == 3 else ("z", "multicolumn", "independent")
        print(json.dumps({"m": m, **compare(spark, df, spec, ["id"], files, n, kinds)}), flush=True)


if __name__ == "__main__":
    main()
