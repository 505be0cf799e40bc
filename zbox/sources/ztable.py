"""Tables laid out in key order, their manifests, and queries on them.

A z-table is Parquet whose files hold disjoint spans of the key; the manifest (path, least and largest
key, rows) stands for the one-dimensional index. It is written beside the files when they are, has a row
a file, and is read in part: only the rows that meet the query's envelope come to the driver. A box query
refines its key interval on the driver, picks files by the manifest, lets the scan skip row groups by a few coarse ranges, keeps rows by the
exact pieces, and applies the original condition last, so the answer is exact whatever the pieces
cover."""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zbox.box import Box
from zbox.functions.curve import in_box, in_ranges, z_of
from zbox.operators.joins import pieces_join
from zbox.plans.strategy import PUSHED, choose
from zbox.refine import Refined, coalesce_pieces, refine
from zbox.spec import ZSpec

READERS = ("parquet", "orc", "json", "csv")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """A source by format; the schema is given, never inferred, where the format holds none."""
    if fmt not in READERS:
        raise ValueError(f"format {fmt} is not one of {READERS}")
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    elif fmt in ("json", "csv"):
        raise ValueError(f"{fmt} needs a schema")
    return reader.format(fmt).load(path)


def add_key(df: DataFrame, spec: ZSpec, z: str = "z") -> DataFrame:
    """df and its key column, which carries the specification in its metadata."""
    return df.withColumn(z, z_of(spec)).withMetadata(z, {"zspec": spec.to_json()})


def spec_of(df: DataFrame, z: str = "z") -> ZSpec:
    return ZSpec.from_json(df.schema[z].metadata["zspec"])


def write_z_table(df: DataFrame, spec: ZSpec, path: str, files: int, key: list[str] | None = None, prefix_bits: int | None = None, mode: str = "overwrite") -> None:
    """Clusters by key and writes. ``key``: columns that split a very common key over files.
    ``prefix_bits``: also partition folders by the key's highest bits."""
    keyed = add_key(df, spec)
    order = ["z", *(key or [])]
    out = keyed.repartitionByRange(files, *order).sortWithinPartitions(*order)
    if prefix_bits:
        out = out.withColumn("z_prefix", F.shiftrightunsigned("z", spec.key_bits - prefix_bits))
        out.write.mode(mode).partitionBy("z_prefix").parquet(path)
    else:
        out.write.mode(mode).parquet(path)
    update_manifest(df.sparkSession, path)


#: Beside the files of a table; names that begin with an underscore are no rows of it.
MANIFEST = "_z_manifest"
KEPT = 50_000  # rows of a manifest that a driver holds
MANIFEST_COLUMNS = "path string, z_min bigint, z_max bigint, rows bigint"


def stored_manifest(spark: SparkSession, path: str) -> DataFrame | None:
    """The manifest as it was written; None if the table has none."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/{MANIFEST}")
    if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
        return None
    return spark.read.schema(MANIFEST_COLUMNS).parquet(f"{path}/{MANIFEST}")


def update_manifest(spark: SparkSession, path: str) -> None:
    """Adds the files that the manifest does not list yet; only their keys are read."""
    known = stored_manifest(spark, path)
    files = build_manifest(spark, path, known)
    files.coalesce(1).write.mode("append").parquet(f"{path}/{MANIFEST}")


def build_manifest(spark: SparkSession, path: str, known: DataFrame | None = None) -> DataFrame:
    """(path, z_min, z_max, rows): one row a file, from the key column alone; of files not ``known``."""
    table = spark.read.parquet(path)
    if known is not None:
        bare = lambda f: f.split(":", 1)[-1].lstrip("/")  # noqa: E731  one file may be written file:/a or file:///a
        old = {bare(r["path"]) for r in known.select("path").collect()}  # a row a file
        new = [f for f in table.inputFiles() if bare(f) not in old]
        if not new:
            return spark.createDataFrame([], MANIFEST_COLUMNS)
        table = spark.read.schema(table.schema).parquet(*new)
    f = table.select("z", F.col("_metadata.file_path").alias("path"))
    return f.groupBy("path").agg(F.min("z").alias("z_min"), F.max("z").alias("z_max"), F.count("*").alias("rows"))


def files_by_statistics(spark: SparkSession, path: str, cols: list[str], box: Box) -> tuple[int, int]:
    """(files, all files): those that least and largest values of the columns cannot rule out for the
    box; what any layout lets a scan skip, measured without reading rows twice."""
    f = spark.read.parquet(path).select(*cols, F.col("_metadata.file_path").alias("__path"))
    ends = f.groupBy("__path").agg(*(g(c).alias(f"{k}{i}") for i, c in enumerate(cols) for k, g in (("lo", F.min), ("hi", F.max))))
    meets = F.lit(True)
    for i, (a, b) in enumerate(zip(box.lo, box.hi, strict=True)):
        meets = meets & (F.lit(True) if a is None else F.col(f"hi{i}") >= a) & (F.lit(True) if b is None else F.col(f"lo{i}") <= b)
    return tuple(ends.agg(F.count_if(meets), F.count("*")).first())


def append_z(df: DataFrame, spec: ZSpec, path: str, files: int) -> None:
    """A new batch, clustered by itself; spans may overlap older files until :func:`compact`."""
    write_z_table(df, spec, path, files, mode="append")


def compact(spark: SparkSession, path: str, to: str, files: int) -> None:
    """The table anew, clustered as one, in another place."""
    df = spark.read.parquet(path)
    spec = spec_of(df)
    df.repartitionByRange(files, "z").sortWithinPartitions("z").withMetadata("z", {"zspec": spec.to_json()}).write.mode("overwrite").parquet(to)
    update_manifest(spark, to)


def piece_table(spark: SparkSession, pieces: list[tuple[int, int]], box_id: int = 0) -> DataFrame:
    """Pieces at hand as a table: one literal that the planner takes apart, no Python behind it."""
    text = json.dumps([{"piece": k, "z_lo": a, "z_hi": b} for k, (a, b) in enumerate(pieces)])
    rows = F.from_json(F.lit(text), "array<struct<piece:int,z_lo:bigint,z_hi:bigint>>")
    return spark.range(1).select(F.lit(box_id).cast("bigint").alias("box_id"), F.inline(rows))


def _ranges_of(z: str, pieces: list[tuple[int, int]]):
    """:func:`in_ranges` on a plain column, parsed from one text: far fewer calls to the JVM."""

    def tree(p) -> str:
        if len(p) == 1:
            return f"(`{z}` >= {p[0][0]} AND `{z}` <= {p[0][1]})"
        return f"({tree(p[: len(p) // 2])} OR {tree(p[len(p) // 2 :])})"

    return F.expr(tree(pieces))


def _once(z, test):
    """``test(z)`` with a computed key worked out once a row, not once a range."""
    return F.get(F.transform(F.array(z), lambda v: test(v)), F.lit(0))


@dataclass
class ZTable:
    """Rows with a key column, and how to ask them for boxes."""

    df: DataFrame
    spec: ZSpec
    path: str | None = None
    z: str = "z"
    _manifest: list | None = field(default=None, repr=False)
    _stored: DataFrame | None = field(default=None, repr=False)

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> ZTable:
        df = spark.read.parquet(path)
        return cls(df, spec_of(df), path)

    @classmethod
    def of(cls, df: DataFrame, spec: ZSpec) -> ZTable:
        return cls(add_key(df, spec), spec)

    def manifest(self, z_lo: int | None = None, z_hi: int | None = None) -> list:
        """Rows of the files that meet the interval (or of all). A manifest of at most KEPT files is kept after
        the first use; of a larger one each query reads its part."""
        if not self.path:
            return []
        if self._manifest is not None:
            return self._manifest
        spark = self.df.sparkSession
        if self._stored is None:
            self._stored = stored_manifest(spark, self.path)
            if self._stored is None:
                self._stored = build_manifest(spark, self.path)
            first = self._stored.limit(KEPT + 1).collect()
            if len(first) <= KEPT:
                self._manifest = first
                return first
        if z_lo is not None:
            return self._stored.filter((F.col("z_max") >= z_lo) & (F.col("z_min") <= z_hi)).collect()
        return self._stored.collect()

    def files_for(self, pieces: list[tuple[int, int]]) -> list[str]:
        """Files whose span meets a piece: both sides in order, one sweep."""
        out, i = [], 0
        near = self.manifest(pieces[0][0], pieces[-1][1]) if pieces else []
        for r in sorted((r for r in near if r["z_min"] is not None), key=lambda r: r["z_min"]):
            while i < len(pieces) and pieces[i][1] < r["z_min"]:
                i += 1
            if any(a <= r["z_max"] and b >= r["z_min"] for a, b in pieces[i : i + 1]):
                out.append(r["path"])
        return out

    def extracted(self, box: Box, method: str = "widened", strategy: str = "auto", exact: bool = True, **options) -> tuple[DataFrame, Refined]:
        """Rows whose key lies in the pieces, before the original condition. ``exact`` False: perhaps
        more rows; what files and row groups can be skipped is skipped, and rows are not told apart by
        key, which is dearer than by the original condition that follows."""
        r = refine(box.cells(self.spec), self.spec, method, **options)
        if not box.beyond(self.spec):
            return self._of_pieces(r, strategy, exact), r
        # rows outside a dimension's range have no key, and this box reaches there
        keyless = self.df.filter(F.col(self.z).isNull())
        keyed = self._of_pieces(r, strategy, exact).filter(F.col(self.z).isNotNull())
        return keyed.unionByName(keyless), r

    def _of_pieces(self, r: Refined, strategy: str, exact: bool) -> DataFrame:
        if not r.pieces:
            return self.df.limit(0)
        df, z = self.df, F.col(self.z)
        strategy = choose(r, self.spec, bool(self.path), strategy)
        if strategy == "manifest" or (strategy == "auto" and self.path):
            files = self.files_for(r.pieces)
            if not files:
                return df.limit(0)
            df = df.sparkSession.read.schema(df.schema).parquet(*files)
        if strategy == "scan":
            return df
        if strategy == "pushed_or":
            few = coalesce_pieces(r.pieces, PUSHED)
            return df.filter(_ranges_of(self.z, few) if self.path else _once(z, lambda v: in_ranges(v, few)))
        if strategy == "array_search":
            spans = F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a, b in r.pieces))
            return df.filter(_once(z, lambda v: F.exists(spans, lambda s: (v >= s["a"]) & (v <= s["b"]))))
        if strategy == "range_join":
            return pieces_join(df, piece_table(df.sparkSession, r.pieces), self.z, "nested").select(*df.columns)
        # coarse ranges go to the scan of a stored key, the exact pieces are joined; a key that is worked
        # out on the way has no statistics to skip by
        if self.path:
            df = df.filter(_ranges_of(self.z, coalesce_pieces(r.pieces, PUSHED)))
        if exact and (not self.path or len(r.pieces) > PUSHED):
            df = pieces_join(df, piece_table(df.sparkSession, r.pieces), self.z, known=r.pieces).select(*df.columns)
        return df

    def query(self, box: Box, method: str = "widened", strategy: str = "auto", columns: list[str] | None = None, **options) -> DataFrame:
        """Rows in the box."""
        test = in_box(box, [F.col(d.column) for d in self.spec.dims])
        # a key that is worked out on the way is worked out for rows of the box only
        table = self if self.path else replace(self, df=self.df.filter(test))
        df, _ = table.extracted(box, method, strategy, strategy not in ("auto", "manifest"), **options)
        out = df.filter(test)
        return out.select(*columns) if columns else out.drop(self.z)

