"""Joining rows to the pieces of many boxes.

All pieces are opened into the prefixes they touch at one level, and rows are joined by their prefix at that
level, then checked by range: an equi-join that makes no row twice before the join, whose work does not
grow with the number of pieces. The level is the finest at which the opened pieces stay few. The piece side
is broadcast only if it is counted and found small; else it is shuffled."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STEP = 3
LEVELS = tuple(range(0, 63, STEP))
MAX_BROADCAST_PREFIXES = 1_000_000


def opened_at(pieces: DataFrame, level: int) -> DataFrame:
    """pieces with prefix: a row per prefix of ``level`` that a piece touches."""
    return pieces.withColumn("prefix", F.explode(F.sequence(F.shiftrightunsigned("z_lo", level), F.shiftrightunsigned("z_hi", level))))


def finest_level(opened: list[int], pieces: int) -> tuple[int, int]:
    """(level, prefixes): the finest level at which ``pieces`` open into 16 prefixes each on average at most
    (or 4,096 in all). ``opened``: prefixes by level."""
    most = max(16 * pieces, 4096)
    return next((k, n) for k, n in zip(LEVELS, opened, strict=True) if n <= most or k == LEVELS[-1])


def level_of(pieces: list[tuple[int, int]]) -> tuple[int, int]:
    """The same of pieces at hand."""
    return finest_level([sum((b >> k) - (a >> k) + 1 for a, b in pieces) for k in LEVELS], len(pieces))


def level_of_table(pieces: DataFrame) -> tuple[int, int] | None:
    """The same of a table, by one aggregate; None without pieces."""
    n = [F.sum((F.shiftrightunsigned("z_hi", k) - F.shiftrightunsigned("z_lo", k) + 1).cast("decimal(38,0)")) for k in LEVELS]
    got = pieces.agg(F.count("*"), *n).first()
    return finest_level([int(x) for x in got[1:]], got[0]) if got[0] else None


def pieces_join(rows: DataFrame, pieces: DataFrame, z: str = "z", hint: str | None = None, known: list[tuple[int, int]] | None = None) -> DataFrame:
    """rows x pieces where z lies in the piece. Pieces of one box are disjoint: a row meets a box once.

    ``hint``: broadcast, merge, shuffle_hash, or 'nested' for the plain range join; by default
    broadcast if the opened pieces are few enough. ``known``: the pieces themselves, where the driver has
    them; it saves a job that counts them."""
    within = (F.col(z) >= F.col("z_lo")) & (F.col(z) <= F.col("z_hi"))
    if hint == "nested":
        return rows.join(pieces, within)
    at = (level_of(known) if known else None) if known is not None else level_of_table(pieces)
    if at is None:
        return rows.join(pieces.limit(0), F.col(z) == F.col("z_lo"))
    level, n = at
    hint = hint or ("broadcast" if n <= MAX_BROADCAST_PREFIXES else "merge")
    own = rows.withColumn("prefix", F.shiftrightunsigned(F.col(z), level))
    return own.join(opened_at(pieces, level).hint(hint), "prefix").filter(within).drop("prefix")


def asof_join(left: DataFrame, right: DataFrame, on: list[str], time: str, value: list[str], suffix: str = "_prev") -> DataFrame:
    """Every left row with the latest right row of the same key not after it: one shuffle by the key
    over the union of both, no pairs."""
    from pyspark.sql.window import Window

    a = left.select("*", F.lit(1).alias("__side"), *(F.lit(None).cast(dict(right.dtypes)[v]).alias(f"{v}{suffix}") for v in value))
    b = right.select(*on, time, *(F.col(v).alias(f"{v}{suffix}") for v in value), F.lit(0).alias("__side"))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(*on).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0)
    packed = F.last(F.when(F.col("__side") == 0, F.struct(*(f"{v}{suffix}" for v in value))), ignorenulls=True).over(w)
    out = both.withColumn("__p", packed).filter(F.col("__side") == 1)
    return out.select(*left.columns, *(F.col(f"__p.{v}{suffix}").alias(f"{v}{suffix}") for v in value))


def interval_pairs(rows: DataFrame, key: str, time: str, ident: str, width: int) -> DataFrame:
    """Pairs (a before b) of one key within ``width`` units of an integer time: equi-join on time
    buckets, each row in its own and the one before."""
    b = rows.select(key, F.col(ident).alias("b"), F.col(time).alias("t_b"), F.explode(F.array(F.floor(F.col(time) / width), F.floor(F.col(time) / width) - 1)).alias("bucket"))
    a = rows.select(key, F.col(ident).alias("a"), F.col(time).alias("t_a"), F.floor(F.col(time) / width).alias("bucket"))
    near = (F.col("t_b") - F.col("t_a") <= width) & ((F.col("t_a") < F.col("t_b")) | ((F.col("t_a") == F.col("t_b")) & (F.col("a") < F.col("b"))))
    return a.join(b, [key, "bucket"]).filter(near).drop("bucket")
