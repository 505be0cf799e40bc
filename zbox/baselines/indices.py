"""The layouts that box queries are compared with. All give the same rows as a full scan."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zbox.box import Box
from zbox.functions.curve import in_box
from zbox.sources.scratch import scratch


def full_scan(df: DataFrame, cols: list[str], box: Box) -> DataFrame:
    return df.filter(in_box(box, [F.col(c) for c in cols]))


@dataclass
class IndependentIndex:
    """One sidecar per column, sorted by it, holding the key; answers intersect the sidecars' keys."""

    df: DataFrame
    cols: list[str]
    key: list[str]
    sides: dict[str, DataFrame]

    @classmethod
    def build(cls, df: DataFrame, cols: list[str], key: list[str], files: int = 8, path: str | None = None) -> IndependentIndex:
        sides = {}
        for i, c in enumerate(cols):
            # position first: a selection column may be part of the key
            side = df.select(F.col(c).alias("__v"), *key).repartitionByRange(files, "__v").sortWithinPartitions("__v")
            if path:
                side.write.mode("overwrite").parquet(f"{path}/{i}")
                side = df.sparkSession.read.parquet(f"{path}/{i}")
            sides[c] = side
        return cls(df, cols, key, sides)

    def query(self, box: Box, columns: list[str] | None = None) -> DataFrame:
        hits = None
        for c, a, b in zip(self.cols, box.lo, box.hi, strict=True):
            if a is None and b is None:
                continue
            side = self.sides[c].filter(in_box(Box((a,), (b,)), [F.col("__v")])).select(*self.key)
            hits = side if hits is None else hits.join(side, self.key, "left_semi")
        out = self.df if hits is None else self.df.join(hits, self.key, "left_semi")
        return out.select(*columns) if columns else out


@dataclass
class MultiColumnIndex:
    """Sorted by the columns in turn: scans skip by the first one above all."""

    df: DataFrame
    cols: list[str]
    path: str | None = None

    @classmethod
    def build(cls, df: DataFrame, cols: list[str], files: int = 8, path: str | None = None) -> MultiColumnIndex:
        out = df.repartitionByRange(files, *cols).sortWithinPartitions(*cols)
        if path:
            out.write.mode("overwrite").parquet(path)
            out = df.sparkSession.read.parquet(path)
        return cls(out, cols, path)

    def query(self, box: Box, columns: list[str] | None = None) -> DataFrame:
        out = full_scan(self.df, self.cols, box)
        return out.select(*columns) if columns else out


@dataclass
class LeafIndex:
    """Rows in leaves, and a directory of the leaves' rectangles. The directory has a row per leaf; a
    query keeps the leaves that meet the box and reads these alone."""

    df: DataFrame
    cols: list[str]
    directory: DataFrame
    path: str | None = None

    def leaves(self, box: Box) -> DataFrame:
        meets = F.lit(True)
        for i, (a, b) in enumerate(zip(box.lo, box.hi, strict=True)):
            if a is not None:
                meets = meets & (F.get("hi", F.lit(i)) >= a)
            if b is not None:
                meets = meets & (F.get("lo", F.lit(i)) <= b)
        return self.directory.filter(meets).select("leaf")

    def query(self, box: Box, columns: list[str] | None = None) -> DataFrame:
        out = full_scan(self.df.join(self.leaves(box), "leaf", "left_semi"), self.cols, box).drop("leaf")
        return out.select(*columns) if columns else out

    @classmethod
    def _of(cls, leafed: DataFrame, cols: list[str], path: str, files: int) -> LeafIndex:
        spark = leafed.sparkSession
        leafed.repartitionByRange(files, "leaf").sortWithinPartitions("leaf").write.mode("overwrite").parquet(f"{path}/rows")
        leafed = spark.read.parquet(f"{path}/rows")
        ends = lambda f: F.array(*(f(c).cast("bigint") for c in cols))
        directory = leafed.groupBy("leaf").agg(ends(F.min).alias("lo"), ends(F.max).alias("hi"), F.count("*").alias("rows"))
        directory.coalesce(1).write.mode("overwrite").parquet(f"{path}/directory")
        return cls(leafed, cols, spark.read.parquet(f"{path}/directory"), path)


class PackedRectIndex(LeafIndex):
    """A packed tree of rectangles: tiles by quantiles of the first column, within each by the second,
    and so on. Only quantile bounds are shuffled, never all rows to one task."""

    @classmethod
    def build(cls, df: DataFrame, cols: list[str], leaf_rows: int = 5_000, path: str | None = None, files: int = 8) -> LeafIndex:
        path = path or scratch(df.sparkSession, "rect")
        parts = max(1, round((df.count() / leaf_rows) ** (1 / len(cols))))
        out = df.withColumn("leaf", F.lit(0).cast("bigint"))
        for level, c in enumerate(cols):
            out = _split_by_quantiles(out, c, parts, parts**level, f"{path}/level{level}")
        return cls._of(out, cols, path, files)


class MedianSplitIndex(LeafIndex):
    """Halves at the median of one column after another."""

    @classmethod
    def build(cls, df: DataFrame, cols: list[str], depth: int = 6, path: str | None = None, files: int = 8) -> LeafIndex:
        path = path or scratch(df.sparkSession, "median")
        out = df.withColumn("leaf", F.lit(0).cast("bigint"))
        for level in range(depth):
            out = _split_by_quantiles(out, cols[level % len(cols)], 2, 2**level, f"{path}/level{level}")
        return cls._of(out, cols, path, files)


MAX_BROADCAST_LEAVES = 100_000


def _split_by_quantiles(df: DataFrame, c: str, parts: int, leaves: int, path: str) -> DataFrame:
    """leaf * parts + the number of that leaf's quantiles of c that lie below the row. The cuts, a row for
    each of at most ``leaves`` leaves, are written, so that rows are read once more and joined to them
    without being shuffled."""
    if parts == 1:
        return df
    at = [k / parts for k in range(1, parts)]
    df.groupBy("leaf").agg(F.percentile_approx(c, at, 10_000).alias("__q")).coalesce(1).write.mode("overwrite").parquet(path)
    cuts = df.sparkSession.read.parquet(path)
    joined = df.join(F.broadcast(cuts) if leaves <= MAX_BROADCAST_LEAVES else cuts, "leaf")
    below = F.aggregate("__q", F.lit(0).cast("bigint"), lambda a, q: a + F.when(F.col(c) > q, 1).otherwise(0))
    return joined.withColumn("leaf", F.col("leaf") * parts + F.coalesce(below, F.lit(0))).drop("__q")
