"""Headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line.

Box queries are means over five boxes, warm, on stored layouts whose building is timed by itself, at every
selectivity and with a dimension dropped; refinement is the mean milliseconds of a box, on the driver."""

from __future__ import annotations

import contextlib
import json
import os
import sys
import time
from pathlib import Path
from statistics import mean

sys.path.insert(0, str(Path(__file__).resolve().parent))


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from zbox import experiments as X
    from zbox import workload as W
    from zbox.operators.boxes import box_of
    from zbox.queries import within_guard
    from zbox.refine import refine
    from zbox.sources import ztable as Z
    from zbox.sources.scratch import scratch
    from zbox.spec import ZSpec

    out: dict[str, float] = {}

    # refinement: every method by dimension at side 128 (widened) and by side; null where its guard trips
    refine_ms: dict[str, float | None] = {}
    for m in range(2, 7):
        spec = ZSpec.grid(m, 10)
        for side in (16, 32, 64, 128, 256):
            for method in ("scan", "exact", "published", "widened"):
                if not within_guard(method, m, side):
                    refine_ms[f"{method}_{m}d_{side}"] = None
                    continue
                spans = []
                for i in range(100 if method == "widened" else 20):
                    box = box_of(i, m, side)
                    began = time.perf_counter()
                    refine(box, spec, method)
                    spans.append(time.perf_counter() - began)
                refine_ms[f"{method}_{m}d_{side}"] = round(1000 * mean(spans), 3)
    key, extracted, layouts = list(W.FIXTURES["lineitem"].key), {}, {}
    for m in (3, 6):
        df, spec = W.points(spark, sf_dir, "lineitem", m)
        df = df.cache()
        df.count()
        kinds = ("z", "multicolumn", "independent", "rect", "median") if m == 3 else ("z", "multicolumn", "independent")
        got = X.compare(spark, df, spec, key, 32, 5, kinds)
        layouts[f"{m}d"] = got
        out |= {f"build_{k}_{m}d": v for k, v in got["build"].items()}
        names = ("scan", *kinds)
        out |= {f"{k}_{m}d_{s}": r[k] for s, r in got["by_selectivity"].items() for k in names}
        out |= {f"partial_{k}_{m}d_{label}": r[k] for label, r in got["partial"].items() for k in ("z", "multicolumn", "scan")}
        path = scratch(spark, "bench")
        Z.write_z_table(df, spec, path, 32)
        table = Z.ZTable.open(spark, path)
        for method in ("none", "widened", "exact") if m == 3 else ("none", "widened"):
            extracted[f"{method}_{m}d"] = sum(table.extracted(W.value_box(spec, i, W.side_for(1e-2, m)), method, "prefix_join")[0].count() for i in range(2))
        df.unpersist()
    with contextlib.suppress(ImportError):
        from zbox.llm import queries as L

        for name, q in L.queries().items():
            if name != "pipeline":
                began = time.perf_counter()
                q(spark, sf_dir).write.format("noop").mode("overwrite").save()
                out[name] = round(time.perf_counter() - began, 4)
    engine = sum(v for k, v in out.items() if not k.startswith("op"))
    print(json.dumps({"metric": "box queries, index baselines and layouts, total", "value": round(engine, 3), "unit": "sec", "queries": out, "refine_ms": refine_ms, "extracted_rows": extracted, "layouts": layouts, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
