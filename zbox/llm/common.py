"""What the operators share: the word rule, shared-folder tables, sizes.

Every operator here reads whole texts. Intermediate results that are read more than once are
written as Parquet below ``spark.checkpoint.dir`` (a folder that all executors share), so that a
lost executor costs a re-read and not a recomputation, and so that row order and hashes cannot
differ between two reads.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word: a longest run of characters that are not ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share. Only where the session names none (tests on one machine)
    a temporary one is made, and removed at exit."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    own = getattr(spark.sparkContext, "_zbox_shared_dir", None)
    if own is None:
        own = tempfile.mkdtemp(prefix="zbox-shared-")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        spark.sparkContext._zbox_shared_dir = own
        own = spark.sparkContext._zbox_shared_dir
    return f"file://{own}"


def materialize(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder and return the reading of it: cuts lineage, survives a
    lost executor, and keeps the columnar pruning that ``checkpoint()`` gives up."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/zbox-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Remove a table written by :func:`materialize` that no later plan reads."""
    spark = df.sparkSession
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/zbox-" in name:
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def words(text: Column) -> Column:
    """All words of a text, null as none."""
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))


def word_count(text: Column) -> Column:
    """Number of words of a text, null as 0."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z and nothing else, null as empty."""
    return F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def fold_bucket(doc_id: Column, n: int) -> Column:
    """crc32 of the id written as text, modulo n; a null id counts as empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(n))


def free_name(df: DataFrame, name: str) -> str:
    """``name`` with as many leading underscores as make it new among the columns of ``df``."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name
