"""Mixing sources to target weights by entropy balancing, in DataFrame functions only.

A document may be taken 0, 1 or 2 times. Of all rates that give each source its target number of
words, entropy balancing picks those nearest in entropy to taking everything once; with rates bounded
by ``max_copies`` = m the dual solution tilts each document exponentially in its size x,

    rate = m e / (e + m - 1),   e = exp(lambda * x),

with one multiplier lambda per source, found by Newton's method on the convex dual. The sums a step
needs are taken in Spark over the table of (source, size) cells with their counts, which is as exact
as over documents and far smaller. Sums are of scaled integers, so that reruns agree to the last bit.

Newton starts from the solution on a histogram: sizes in bins of 4 %, at most ``_BINS`` numbers a source,
solved in one expression. From there one or two steps over all cells settle it, a job each.

Rates become copies cell by cell: running totals are rounded, then the words still missing (or too
many) are settled greedily from the largest size that fits down to the smallest. Inside a cell the
documents of least hash get the odd copies; the rank within a cell is made of a bucket's rank and the
running total of bucket counts, so a cell that holds a third of all documents is never sorted in one
task."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import discard, free_name, materialize, word_count

_UNIT = 1_000_000  # rates are summed as integers of this fraction
_EXACT = "decimal(38,0)"
_BINS = 1024  # of sizes, 16 to a doubling
_FAR = 1e6


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, max_copies: int = 2) -> DataFrame:
    """``sizes``: a row per source with source, source_size. Adds weight and target.

    Sources in code point order, null last, get the weights in turn. They divide ``share`` times all
    words by weight; a target stops at ``max_copies`` times its source and what is above goes to the
    others by weight, until none is above. Sources fill up in the order of top / weight, so the level at
    which the rest stands follows from running totals. The two orders need one task, over sources only."""
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    given = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.pmod(place, F.lit(len(weights))) + 1).cast("int"))
    at = sizes.withColumn("weight", given).withColumn("top", F.col("source_size") * float(max_copies))
    fills = Window.orderBy(F.col("top") / F.col("weight"), F.col("source").asc_nulls_last())
    before, every = fills.rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    full, used = F.coalesce(F.sum("top").over(before), F.lit(0.0)), F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    at = at.withColumns({"full": full, "open": F.sum("weight").over(every) - used, "words": F.sum("source_size").over(every)})
    at = at.withColumn("level", (F.col("words") * float(share) - F.col("full")) / F.col("open"))
    # the first source that the level of those not yet full does not fill, and all after it, stand at that level
    stands = F.when(F.col("weight") * F.col("level") < F.col("top"), F.col("level"))
    level = F.first(stands, ignorenulls=True).over(fills.rowsBetween(Window.unboundedPreceding, 0))
    at = at.withColumn("target", F.coalesce(F.least(F.col("top"), F.col("weight") * level), F.col("top")))
    return at.drop("top", "full", "open", "words", "level")


def _tilted(lam, x, m: int):
    """m e / (e + m - 1) without overflow."""
    t = F.greatest(F.lit(-700.0), F.least(F.lit(700.0), lam * x))
    return F.lit(float(m)) / (1 + (m - 1) * F.exp(-t))


def _amounts(lam, x, amount, m: int):
    """Words taken at ``lam`` of ``amount`` words in texts of scaled size x, and the slope of that in lam."""
    rate = _tilted(lam, x, m)
    return amount * rate, amount * x * rate * (1 - rate / m)


def _moved(lam, low, high, taken, slope, target):
    """(lambda, low, high) after a Newton step that stays within the bracket; a halving otherwise."""
    off = taken - target
    low, high = F.when(off < 0, lam).otherwise(low), F.when(off > 0, lam).otherwise(high)
    step = lam - off / slope
    # half way between the ends in size, so that far ends are reached in few halvings
    mid = F.when(low * high > 0, F.signum(low) * F.sqrt(low * high)).otherwise(F.when(off < 0, F.greatest(lam * 8, F.lit(1.0))).otherwise(F.least(lam * 8, F.lit(-1.0))))
    mid = F.when((mid > low) & (mid < high), mid).otherwise((low + high) / 2)
    return F.when(off == 0, lam).when((slope > 0) & (step > low) & (step < high), step).otherwise(mid), low, high


def _start(bins, target, m: int, steps: int = 60):
    """lambda of a histogram: ``bins`` is an array of (x, amount) of a source."""
    zero = F.struct(F.lit(0.0).alias("lambda"), F.lit(-_FAR).alias("low"), F.lit(_FAR).alias("high"))

    def step(at, _):
        def add(sums, b):
            taken, slope = _amounts(at["lambda"], b["x"], b["amount"], m)
            return F.struct((sums["taken"] + taken).alias("taken"), (sums["slope"] + slope).alias("slope"))

        sums = F.aggregate(bins, F.struct(F.lit(0.0).alias("taken"), F.lit(0.0).alias("slope")), add)

        def move(got):
            lam, low, high = _moved(at["lambda"], at["low"], at["high"], got["taken"], got["slope"], target)
            return F.struct(lam.alias("lambda"), low.alias("low"), high.alias("high"))

        return F.get(F.transform(F.array(sums), move), F.lit(0))

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), zero, step, lambda at: at["lambda"])


def balance(cells: DataFrame, sources: DataFrame, max_copies: int = 2, tolerance: float = 1e-8, least: float = 0.01, max_steps: int = 40) -> DataFrame:
    """The dual's solution. ``cells``: (skey, size, n); ``sources``: (skey, source_size, docs, target).
    Returns sources with lambda and scale (the mean size).

    A source is done when its words are within ``tolerance`` of the target, or within ``least`` words, or
    the bracket around lambda cannot be narrowed; a source without words, or one taken in full, has lambda
    0. What is left then is settled in whole copies by :func:`round_cells`."""
    m = float(max_copies)
    worded = cells.filter("size > 0")
    size_bin = F.least(F.floor(F.log2("size") * 16), F.lit(_BINS - 1)).cast("int")
    binned = worded.groupBy("skey", size_bin.alias("bin")).agg(F.sum("n").alias("k"), F.sum(F.col("n") * F.col("size")).alias("amount"))
    # at most _BINS entries a source
    binned = binned.groupBy("skey").agg(F.array_sort(F.collect_list(F.struct("bin", "k", "amount"))).alias("bins"))
    state = sources.join(binned, "skey", "left").withColumn("scale", F.col("source_size") / F.greatest(F.col("docs"), F.lit(1)))
    bins = F.transform("bins", lambda b: F.struct((b["amount"] / b["k"] / F.col("scale")).alias("x"), b["amount"].cast("double").alias("amount")))
    fixed = (F.col("source_size") == 0) | (F.col("target") >= F.col("source_size") * m)  # no words, or all of them
    state = state.withColumns({"bins": bins, "done": fixed})
    start = F.when(F.col("done"), 0.0).otherwise(_start(F.col("bins"), F.col("target"), max_copies))
    state = state.withColumns({"lambda": start, "low": F.lit(-_FAR), "high": F.lit(_FAR)}).drop("bins")
    state = materialize(state)
    for _ in range(max_steps):
        at = worded.join(state.filter("not done").select("skey", "lambda", "scale"), "skey")
        taken, slope = _amounts(F.col("lambda"), F.col("size") / F.col("scale"), F.col("n") * F.col("size"), max_copies)
        exact = lambda c: (F.sum(F.round(c * _UNIT).cast(_EXACT)) / _UNIT).cast("double")
        sums = at.groupBy("skey").agg(exact(taken).alias("taken"), exact(slope).alias("slope"))
        lam, low, high = _moved(F.col("lambda"), F.col("low"), F.col("high"), F.col("taken"), F.col("slope"), F.col("target"))
        near = F.abs(F.col("taken") - F.col("target")) <= F.greatest(F.lit(least), F.col("target") * tolerance)
        ends = near | (high - low <= F.abs(F.col("lambda")) * 1e-14)
        done = F.col("done") | F.coalesce(ends, F.lit(True))
        kept = [c for c in state.columns if c not in ("lambda", "low", "high", "done")]
        moved = state.join(sums, "skey", "left").select(*kept, F.when(done, F.col("lambda")).otherwise(lam).alias("lambda"), low.alias("low"), high.alias("high"), done.alias("done"))
        new = materialize(moved)
        discard(state)
        state = new
        if state.filter("not done").isEmpty():
            break
    return state.select(*sources.columns, "lambda", "scale")


def round_cells(cells: DataFrame, state: DataFrame, max_copies: int = 2) -> DataFrame:
    """Copies per cell: (skey, size, n, copies, source_size, target).

    Running totals of the rates are rounded, from the largest size down; that leaves a source about half
    a text from its target. One greedy pass over its sizes, largest first, then takes (or gives back) as
    many texts of each size as still fit, so that no single text of the source could bring it nearer from
    that side. The pass holds one number per distinct size no longer than what is missing."""
    m = F.lit(max_copies).cast("bigint")
    full = F.col("target") >= F.col("source_size") * float(max_copies)
    df = cells.join(state.select("skey", "source_size", "target", "lambda", "scale"), "skey")
    rate = F.when(F.col("size") == 0, 1.0).when(full, float(max_copies)).otherwise(_tilted(F.col("lambda"), F.col("size") / F.col("scale"), max_copies))
    df = df.withColumn("wish", F.round(F.col("n") * rate * _UNIT).cast(_EXACT))
    down, whole = Window.partitionBy("skey").orderBy(F.col("size").desc()), Window.partitionBy("skey")
    total = F.sum("wish").over(down)
    to_copies = lambda c: F.floor((c + _UNIT // 2) / _UNIT).cast("bigint")
    df = df.withColumn("copies", F.least(F.col("n") * m, to_copies(total) - to_copies(total - F.col("wish"))))
    df = df.withColumn("missing", F.round(F.col("target")).cast("bigint") - F.sum(F.col("copies") * F.col("size")).over(whole))
    df = materialize(df.select("skey", "size", "n", "copies", "missing", "source_size", "target"))
    free = F.when(F.col("missing") > 0, F.col("n") * m - F.col("copies")).otherwise(F.col("copies"))
    useful = df.withColumn("free", free).filter((F.col("size") > 0) & (F.col("size") <= F.abs("missing")) & (F.col("free") > 0))
    each = useful.groupBy("skey").agg(F.first("missing").alias("missing"), F.sort_array(F.collect_list(F.struct("size", "free")), asc=False).alias("cells"))
    none = F.array().cast("array<struct<size:bigint,change:bigint>>")

    def settle(at, c):
        q = F.least(c["free"], F.floor(at["left"] / c["size"])).cast("bigint")
        got = F.when(q > 0, F.concat(at["got"], F.array(F.struct(c["size"].alias("size"), q.alias("change"))))).otherwise(at["got"])
        return F.struct((at["left"] - q * c["size"]).alias("left"), got.alias("got"))

    got = F.aggregate("cells", F.struct(F.abs("missing").alias("left"), none.alias("got")), settle, lambda at: at["got"])
    changes = each.select("skey", F.signum("missing").cast("bigint").alias("sign"), F.explode(got).alias("g")).select("skey", F.col("g.size").alias("size"), (F.col("sign") * F.col("g.change")).alias("change"))
    df = df.join(changes, ["skey", "size"], "left")
    return df.select("skey", "size", "n", (F.col("copies") + F.coalesce("change", F.lit(0))).cast("bigint").alias("copies"), "source_size", "target")


def mix(docs: DataFrame, id_col: str = "doc_id", source: str = "source", text: str = "text", carry: tuple[str, ...] = (), weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, max_copies: int = 2, bucket_rows: int = 2_000) -> DataFrame:
    """A row per row of ``docs``: id_col, carried columns, size, source_size, target, copies, taken.

    size: words of the whole text (null: 0). copies: 0 to ``max_copies``; taken: copies * size. A null
    source is a source of its own. Texts without words have copies 1 and take none. Null ids are
    carried. Rows equal in id and text are interchangeable. Carried columns by the names of these figures,
    in any case, are replaced by them. An empty table gives an empty result."""
    names = [id_col, *(c for c in carry if c != id_col)]
    skey, size, h = F.coalesce(F.concat(F.lit("="), F.col(f"`{source}`").cast("string")), F.lit("")), word_count(F.col(f"`{text}`")), F.xxhash64(F.col(f"`{text}`"))
    narrow = docs.select(F.col(f"`{id_col}`").alias("id"), skey.alias("skey"), F.col(f"`{source}`").cast("string").alias("source"), size.alias("size"), h.alias("h"))
    narrow = materialize(narrow)
    cells = materialize(narrow.groupBy("skey", "source", "size").agg(F.count("*").alias("n")))
    sources = cells.groupBy("skey", "source").agg(F.sum(F.col("n") * F.col("size")).alias("source_size"), F.sum("n").alias("docs"))
    sources = materialize(source_targets(sources, weights, share, max_copies))
    cells = materialize(round_cells(cells.drop("source"), balance(cells.drop("source"), sources, max_copies), max_copies))
    buckets = max(1, math.ceil((sources.agg(F.sum("docs")).first()[0] or 0) / bucket_rows))
    place = lambda i, t: F.pmod(F.xxhash64(i, t, F.lit("place")), F.lit(buckets))
    per = narrow.groupBy("skey", "size", place(F.col("id"), F.col("h")).alias("bucket")).agg(F.count("*").alias("k"))
    before = F.sum("k").over(Window.partitionBy("skey", "size").orderBy("bucket")) - F.col("k")
    per = per.withColumn("before", before).drop("k").join(cells, ["skey", "size"])
    if names == [id_col]:
        rows = narrow.select(F.col("id").alias(id_col), F.struct("skey", "size", "h", F.col("id")).alias("__k"))
    else:
        rows = docs.select(*(F.col(f"`{c}`") for c in names), F.struct(skey.alias("skey"), size.alias("size"), h.alias("h"), F.col(f"`{id_col}`").alias("id")).alias("__k"))
    k = free_name(rows, "_k")
    rows = rows.withColumnRenamed("__k", k)
    key = lambda c: F.col(f"{k}.{c}")
    rows = rows.withColumns({f"{k}s": key("skey"), f"{k}z": key("size"), f"{k}b": place(key("id"), key("h")), f"{k}o": F.xxhash64(key("id"))})
    order = Window.partitionBy(f"{k}s", f"{k}z", f"{k}b").orderBy(f"{k}o", key("id"), key("h"))
    rows = rows.withColumn(f"{k}r", F.row_number().over(order))
    renamed = {"skey": f"{k}s", "size": f"{k}z", "bucket": f"{k}b", **{c: f"{k}_{c}" for c in ("before", "n", "copies", "source_size", "target")}}
    per = per.select(*(F.col(a).alias(b) for a, b in renamed.items()))
    rows = rows.join(per, [f"{k}s", f"{k}z", f"{k}b"])
    n, copies = F.col(f"{k}_n"), F.col(f"{k}_copies")
    odd = (F.col(f"{k}_before") + F.col(f"{k}r") <= F.pmod(copies, n)).cast("bigint")
    got = F.floor(copies / n).cast("bigint") + odd
    size = F.col(f"{k}z")
    made = {"size": size, "source_size": F.col(f"{k}_source_size"), "target": F.col(f"{k}_target"), "copies": got, "taken": got * size}
    return rows.select(*(F.col(f"`{c}`") for c in names if c.lower() not in made), *(v.alias(c) for c, v in made.items()))


def take(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with each row repeated as often as the mix takes it, all columns kept. Columns named
    like the mix's own figures are passed through untouched."""
    clash = {c: free_name(docs, f"__in_{c}") for c in docs.columns if c.lower() in ("size", "source_size", "target", "copies", "taken")}
    given = docs.withColumnsRenamed(clash)
    mixed = mix(given, carry=tuple(given.columns), **options)
    each = free_name(mixed, "each")
    mixed = mixed.filter("copies > 0").withColumn(each, F.explode_outer(F.sequence(F.lit(1).cast("bigint"), F.col("copies"))))
    back = {v: k for k, v in clash.items()}
    return mixed.select(*(F.col(f"`{c}`").alias(back.get(c, c)) for c in given.columns))
