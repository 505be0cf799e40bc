"""The experiment workloads on the given tables: point tables in whole units, boxes from integer
arithmetic, and the same in DuckDB's SQL."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zbox.box import Box
from zbox.operators.boxes import corner
from zbox.spec import DimSpec, ZSpec


@dataclass(frozen=True)
class Dim:
    name: str
    spark: str
    duck: str


def _cents(c: str) -> tuple[str, str]:
    e = f"CAST(floor({c} * 100 + 0.5) AS BIGINT)"
    return e, e


def _day(c: str) -> tuple[str, str]:
    return f"CAST(datediff(CAST({c} AS DATE), DATE'1995-01-01') AS BIGINT)", f"CAST(date_diff('day', DATE '1995-01-01', CAST({c} AS DATE)) AS BIGINT)"


def _since(c: str, micros: int) -> tuple[str, str]:
    return f"((unix_micros(CAST({c} AS TIMESTAMP)) - 1704067200000000) div {micros})", f"((epoch_us({c}) - 1704067200000000) // {micros})"


def _same(c: str) -> tuple[str, str]:
    return f"CAST({c} AS BIGINT)", f"CAST({c} AS BIGINT)"


@dataclass(frozen=True)
class Fixture:
    table: str
    key: tuple[str, ...]
    dims: tuple[Dim, ...]

    def first(self, m: int) -> Fixture:
        return Fixture(self.table, self.key, self.dims[:m])


def _dims(**named) -> tuple[Dim, ...]:
    return tuple(Dim(k, *v) for k, v in named.items())


FIXTURES = {
    "lineitem": Fixture("lineitem", ("l_orderkey", "l_linenumber", "l_extendedprice"), _dims(ship_day=_day("l_shipdate"), price_cents=_cents("l_extendedprice"), partkey=_same("l_partkey"), suppkey=_same("l_suppkey"), quantity=_same("l_quantity"), orderkey=_same("l_orderkey"))),
    "orders": Fixture("orders", ("o_orderkey",), _dims(custkey=_same("o_custkey"), price_cents=_cents("o_totalprice"), order_day=_day("o_orderdate"))),
    "events": Fixture("events", ("event_id",), _dims(ts_minute=_since("ts", 60_000_000), user=_same("user_id"), value_cents=_cents("value"))),
    "events_near_diagonal": Fixture("events", ("event_id",), _dims(event=_same("event_id"), ts_second=_since("ts", 1_000_000), user=_same("user_id"))),
    "part": Fixture("part", ("p_partkey",), _dims(size=_same("p_size"), price_dimes=("CAST(floor(p_retailprice * 10 + 0.5) AS BIGINT)",) * 2)),
    "customer": Fixture("customer", ("c_custkey",), _dims(nation=_same("c_nationkey"), acctbal_cents=_cents("c_acctbal"))),
    "customer_3d": Fixture("customer", ("c_custkey",), _dims(nation=_same("c_nationkey"), acctbal_cents=_cents("c_acctbal"), custkey=_same("c_custkey"))),
    "supplier": Fixture("supplier", ("s_suppkey",), _dims(nation=_same("s_nationkey"), acctbal_cents=_cents("s_acctbal"))),
    "documents": Fixture("documents", ("doc_id",), _dims(chars=_same("n_chars"), words=("CAST(regexp_count(coalesce(text, ''), '[^ ]+') AS BIGINT)", "CAST(len(regexp_extract_all(coalesce(text, ''), '[^ ]+')) AS BIGINT)"))),
    "pages": Fixture("pages", ("page_id",), _dims(url_chars=("CAST(length(url) AS BIGINT)",) * 2, html_chars=("CAST(length(html) AS BIGINT)",) * 2)),
    "conversations": Fixture("conversations", ("conv_id", "turn"), _dims(conv=_same("conv_id"), turn_no=_same("turn"))),
    "embeddings": Fixture("embeddings", ("vec_id",), tuple(Dim(f"e{i}", f"CAST(floor((embedding[{i}] + 0.6) * 10000) AS BIGINT)", f"CAST(floor((CAST(embedding[{i + 1}] AS FLOAT) + 0.6) * 10000) AS BIGINT)") for i in range(6))),
}
BITS = 10


def points(spark: SparkSession, sf_dir: str, name: str, m: int | None = None, extra: tuple[str, ...] = ()) -> tuple[DataFrame, ZSpec]:
    """Key, selection columns in whole units, ``extra`` columns; and the specification, its ranges read
    from the table's ends (one small aggregate)."""
    f = FIXTURES[name].first(m or 6)
    df = spark.read.parquet(f"{sf_dir}/{f.table}.parquet")
    df = df.select(*f.key, *(F.expr(d.spark).alias(d.name) for d in f.dims), *extra)
    ends = df.agg(*(g(d.name).alias(f"{k}{i}") for i, d in enumerate(f.dims) for k, g in (("lo", F.min), ("hi", F.max)))).first()
    dims = tuple(DimSpec(d.name, ends[f"lo{i}"] or 0, ends[f"hi{i}"] or 0, BITS) for i, d in enumerate(f.dims))
    return df, ZSpec(dims, BITS)


def row_boxes(spark: SparkSession, sf_dir: str, name: str, m: int, side: int, bits: int) -> DataFrame:
    """(box_id, lo, hi): boxes of ``side`` cells around the rows of a table, each once. A row's values are dealt
    over the corners that a box can have on the grid; box_id numbers the corners of the grid."""
    df, spec = points(spark, sf_dir, name, m)
    room, at = (1 << bits) - side + 1, []
    for d in spec.dims:
        at.append(F.expr(f"CAST((({d.column} - {int(d.lo)}) * {room}) div {int(d.hi) - int(d.lo) + 1} AS BIGINT)").alias(d.column))
    corner = [F.col(d.column) for d in spec.dims]
    box_id = sum((c * room**d for d, c in enumerate(corner)), F.lit(0).cast("bigint"))
    found = df.select(*at).dropna().distinct()
    return found.select(box_id.alias("box_id"), F.array(*corner).alias("lo"), F.array(*(c + (side - 1) for c in corner)).alias("hi"))


def row_boxes_sql(name: str, m: int, side: int, bits: int) -> str:
    """CTEs p, r and g: box_id and a<d>, z<d>, the ends in cells."""
    room, names = (1 << bits) - side + 1, [d.name for d in FIXTURES[name].dims[:m]]
    corner = ", ".join(f"(({n} - lo{d}) * {room}) // (hi{d} - lo{d} + 1) AS a{d}" for d, n in enumerate(names))
    box_id = " + ".join(f"a{d} * {room**d}" for d in range(m))
    some = " AND ".join(f"{n} IS NOT NULL" for n in names)
    return f"{points_sql(name, m)}, k AS (SELECT DISTINCT {corner} FROM p, r WHERE {some}), g AS (SELECT {box_id} AS box_id, *, {', '.join(f'a{d} + {side - 1} AS z{d}' for d in range(m))} FROM k)"


def value_box(spec: ZSpec, i: int, side: int, along: int = 1) -> Box:
    """Box i, ``side`` cells of 1024 wide in every dimension, in the columns' units. The first ``along``
    dimensions share their corner: boxes on the diagonal, where columns that go together have their rows."""
    lo, hi = [], []
    for d, x in enumerate(spec.dims):
        width, c = int(x.hi) - int(x.lo) + 1, corner(i, d if d >= along else 0, side)
        lo.append(int(x.lo) + c * width // 1024)
        hi.append(int(x.lo) + (c + side) * width // 1024 - 1)
    return Box(tuple(lo), tuple(hi))


def side_for(selectivity: float, m: int) -> int:
    """Equal sides of a box that holds this share of a uniform domain."""
    return max(1, ceil(selectivity ** (1 / m) * 1024))


# --- the same in SQL ------------------------------------------------------------------------------


def points_sql(name: str, m: int | None = None, extra: tuple[str, ...] = ()) -> str:
    """CTEs p (points) and r (ends of every dimension)."""
    f = FIXTURES[name].first(m or 6)
    cols = ", ".join([*f.key, *(f"{d.duck} AS {d.name}" for d in f.dims), *extra])
    ends = ", ".join(f"min({d.name}) AS lo{i}, max({d.name}) AS hi{i}" for i, d in enumerate(f.dims))
    return f"p AS (SELECT {cols} FROM {f.table}), r AS (SELECT {ends} FROM p)"


def boxes_sql(m: int, side: int, n: int, first: int = 0, along: int = 1) -> str:
    """CTE b: box_id and a<d>, z<d>, the ends in units."""
    ends = []
    for d in range(m):
        c = f"((7919 * i + {104729 * (d if d >= along else 0)}) % {1024 - side + 1})"
        ends.append(f"lo{d} + ({c} * (hi{d} - lo{d} + 1)) // 1024 AS a{d}, lo{d} + (({c} + {side}) * (hi{d} - lo{d} + 1)) // 1024 - 1 AS z{d}")
    return f"b AS (SELECT i AS box_id, {', '.join(ends)} FROM range({first}, {first + n}) t(i), r)"


def within_sql(name: str, m: int, drop: tuple[int, ...] = ()) -> str:
    f = FIXTURES[name]
    return " AND ".join(f"p.{f.dims[d].name} BETWEEN b.a{d} AND b.z{d}" for d in range(m) if d not in drop)


def cell_sql(name: str, d: int) -> str:
    c = FIXTURES[name].dims[d].name
    return f"least(1023, greatest(0, (({c} - lo{d}) * 1024) // (hi{d} - lo{d} + 1)))"


def encode_sql(coords: list[str], bits: int) -> str:
    """Interleaving spelled out bit by bit."""
    m = len(coords)
    return "(" + " + ".join(f"((({c} >> {b}) & 1) << {b * m + d})" for d, c in enumerate(coords) for b in range(bits)) + ")"


def decode_sql(z: str, d: int, m: int, bits: int) -> str:
    return "(" + " + ".join(f"((({z} >> {b * m + d}) & 1) << {b})" for b in range(bits)) + ")"
