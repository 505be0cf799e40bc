"""Near copies by similarity of word shingles: candidates from SimHash and from banded minima, the sets
themselves decide.

A text is the set of its runs of ``SHINGLE`` words. Its SimHash fingerprint goes through the positional index
of :mod:`.simhash`, whose links at two bits or fewer are candidates. At the similarity asked for that is not
enough: two sets of similarity 0.8 differ in about ten of 64 bits, where no positional byte need be shared
and the index guarantees nothing. So banded minima find candidates too. For 72 hash functions the least hash over the set
is kept; two texts agree in one minimum with the probability of their Jaccard similarity. Four minima
make a band, and texts that share one of the 18 bands are candidates: of pairs at similarity 0.8 all but
1 in 13,000 are, at 0.9 practically all. Each candidate pair is then verified on its two whole texts, so no link is
below the bound.

Equal texts never multiply: bands are posted once per distinct text. A posting of at most ``list_cap``
texts is paired in full. A longer one (a heap of near copies) is tied to several members of it, another
choice in each band, so that links grow with its size and not with the square. Likewise texts of one
fingerprint are tied to the least of them, and its links stand for theirs.

What these ties leave open is decided exactly (:func:`rest_pairs`). Where a long posting, or texts whose
fingerprints are linked, do not come out as one component, their texts are joined once more, by prefixes:
two sets of similarity t share an element among the |x| - ceil(t |x|) + 1 first of each, in one order of all
elements, here the rarest first. No pair that is similar is missed, and no posting is capped."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import simhash
from .common import materialize
from .components import connected_components

SEED, SHINGLE, BANDS, ROWS = 42, 5, 18, 4
#: Texts of a posting that is paired in full.
LIST_CAP = 64
_R = np.random.default_rng(SEED)
_FLIP, _ODD = (_R.integers(0, 1 << 64, BANDS * ROWS, dtype=np.uint64) for _ in range(2))
_ODD |= np.uint64(1)
_MIX = _R.integers(0, 1 << 64, (BANDS, ROWS), dtype=np.uint64) | np.uint64(1)


def shingles(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Hashes of the distinct shingles of a text, sorted. A text of fewer words is one shingle, a text
    without words has none."""
    w = ("" if text is None else text).encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return np.empty(0, dtype=np.uint64)
    grams = zip(*(w[i:] for i in range(shingle))) if len(w) >= shingle else [w]
    join, digest = b" ".join, xxhash.xxh64_intdigest
    return np.unique(np.array([digest(join(g), SEED) for g in grams], dtype=np.uint64))


def bands(of: np.ndarray) -> np.ndarray:
    """The ``BANDS`` band keys of a set of hashes."""
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, dtype=np.uint64)
    for at in range(0, len(of), 512):  # a very long text in bounded steps
        np.minimum(least, ((of[at : at + 512, None] ^ _FLIP) * _ODD).min(0), out=least)
    return ((least.reshape(BANDS, ROWS) >> np.uint64(7)) * _MIX).sum(1, dtype=np.uint64)


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Whether two sets have a Jaccard similarity of ``percent`` hundredths or more; empty sets are equal."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def add_marks(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """(keep..., bands array<bigint>, fp bigint) for every row: its band keys and its SimHash fingerprint."""
    part = docs.select(*keep, F.col(f"`{text}`").alias("__text"))
    schema = part.drop("__text").withColumn("bands", F.lit(None).cast("array<bigint>")).withColumn("fp", F.lit(0).cast("bigint")).schema

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                some = batch.slice(at, 256)
                sets = [shingles(x.as_py()) for x in some.column(some.num_columns - 1)]
                flat = np.concatenate([bands(x) for x in sets]).view(np.int64)
                fps = np.array([simhash.majority(x) for x in sets], dtype=np.uint64).view(np.int64)
                lists = pa.ListArray.from_arrays(np.arange(0, len(flat) + 1, BANDS, dtype=np.int32), pa.array(flat))
                yield pa.RecordBatch.from_arrays([*some.columns[:-1], lists, pa.array(fps)], names=[*some.schema.names[:-1], "bands", "fp"])

    return part.mapInArrow(run, schema)


def band_postings(distinct: DataFrame) -> DataFrame:
    """(band, node, n): the postings of two nodes or more of ``distinct`` (node bigint, bands), with their lengths."""
    posts = distinct.select("node", F.explode("bands").alias("band"))
    sizes = posts.groupBy("band").agg(F.count("*").alias("n")).filter("n > 1")
    return materialize(posts.join(sizes, "band"))


def candidates(distinct: DataFrame, list_cap: int = LIST_CAP, centres: int = 4, listed: DataFrame | None = None) -> DataFrame:
    """(u, v), u > v: pairs of nodes of ``distinct`` (node bigint, bands) that share a band; some repeatedly.
    ``listed``: their postings, where they are at hand."""
    listed = band_postings(distinct) if listed is None else listed
    light = listed.filter(F.col("n") <= list_cap)
    a, b = (light.select("band", F.col("node").alias(x)) for x in "uv")
    pairs = a.join(b, "band").filter("u > v").select("u", "v")
    dense = listed.filter(F.col("n") > list_cap).select("node", "band")
    # another order of nodes in each posting, so that the centres of a heap differ between its postings
    chosen = dense.groupBy("band").agg(*(F.min_by("node", F.xxhash64("node", "band", F.lit(k))).alias(f"c{k}") for k in range(centres)))
    ties = dense.join(chosen, "band").select("node", F.explode(F.array(*(f"c{k}" for k in range(centres)))).alias("c")).filter("node != c")
    return pairs.unionByName(ties.select(F.greatest("node", "c").alias("u"), F.least("node", "c").alias("v")))


def simhash_candidates(distinct: DataFrame, near: DataFrame | None = None) -> DataFrame:
    """(u, v), u > v: pairs of nodes of ``distinct`` (node, fp) whose fingerprints are equal or linked. Of the
    nodes of one fingerprint each is paired with the least. ``near``: the links of the fingerprints."""
    reps = materialize(distinct.groupBy("fp").agg(F.min("node").alias("rep")))
    same = distinct.join(reps, "fp").filter("node != rep").select(F.col("node").alias("u"), F.col("rep").alias("v"))
    of = lambda c: reps.select(F.col("fp").alias(c), F.col("rep").alias(f"{c}r"))
    near = simhash.link_fingerprints(reps.select("fp")) if near is None else near
    near = near.join(of("u"), "u").join(of("v"), "v")
    near = near.select(F.greatest("ur", "vr").alias("u"), F.least("ur", "vr").alias("v"))
    return same.unionByName(near)


def open_nodes(distinct: DataFrame, listed: DataFrame, near: DataFrame, found: DataFrame, list_cap: int = LIST_CAP) -> DataFrame:
    """(node, root): the nodes of groups that were tied and not paired in full, long postings and texts of linked
    fingerprints, where the links ``found`` leave the group in several components; root is the node's."""
    roots = connected_components(found)
    of = connected_components(near)
    prints = distinct.select("node", "fp").join(of.select(F.col("node").alias("fp"), F.col("root").alias("to")), "fp", "left")
    groups = prints.select(F.lit("fp").alias("kind"), F.coalesce("to", "fp").alias("group"), "node")
    groups = groups.unionByName(listed.filter(F.col("n") > list_cap).select(F.lit("band").alias("kind"), F.col("band").alias("group"), "node"))
    rooted = materialize(groups.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")))
    several = rooted.groupBy("kind", "group").agg(F.min("root").alias("a"), F.max("root").alias("z")).filter("a != z").select("kind", "group")
    return materialize(rooted.join(several, ["kind", "group"], "left_semi").select("node", "root").distinct())


def rest_pairs(nodes: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """(u, v), u > v: every pair of ``nodes`` (node, root) of different roots that may be similar by ``percent``
    hundredths, by prefixes; no posting is capped. ``texts``: (node, text)."""
    own = texts.join(nodes, "node", "left_semi").groupBy("node").agg(F.first("text").alias("text"))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                h = shingles(batch.column(1)[i].as_py())
                size, h = len(h), h if len(h) else np.zeros(1, dtype=np.uint64)  # sets without elements are equal
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(x, len(h))) for x in (batch.column(0)[i].as_py(), size)] + [pa.array(h.view(np.int64))], names=["node", "size", "h"])

    sets = materialize(own.mapInArrow(run, "node bigint, size bigint, h bigint"))
    common = sets.groupBy("h").agg(F.count("*").alias("n"))
    order = Window.partitionBy("node").orderBy("n", "h")
    posts = sets.join(common, "h").withColumn("at", F.row_number().over(order) - 1)
    posts = posts.filter((F.col("n") > 1) & (F.col("at") <= F.col("size") - F.expr(f"(size * {percent} + 99) div 100")))
    posts = materialize(posts.join(nodes, "node").select("h", "node", "root", "size", "at"))
    # a posting within one component has nothing left to decide
    several = posts.groupBy("h").agg(F.min("root").alias("a"), F.max("root").alias("z")).filter("a != z").select("h")
    posts = posts.join(several, "h", "left_semi")
    a, b = (posts.select("h", *(F.col(c).alias(f"{c}_{x}") for c in ("node", "root", "size", "at"))) for x in "uv")
    # from their first common element on, both must hold as many as the similarity asks for
    most = F.least(F.col("size_u") - F.col("at_u"), F.col("size_v") - F.col("at_v"))
    enough = (100 + percent) * most >= percent * (F.col("size_u") + F.col("size_v"))
    pairs = a.join(b, "h").filter((F.col("node_u") > F.col("node_v")) & (F.col("root_u") != F.col("root_v")) & enough)
    return pairs.select(F.col("node_u").alias("u"), F.col("node_v").alias("v")).distinct()


def verified(pairs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) whose texts (node, text) are similar by ``percent`` hundredths or more."""
    pairs = materialize(pairs)
    nodes = pairs.select(F.col("u").alias("node")).unionByName(pairs.select(F.col("v").alias("node"))).distinct()
    found = materialize(texts.join(nodes, "node", "left_semi").groupBy("node").agg(F.first("text").alias("text")))
    both = pairs.join(found.select(F.col("node").alias("u"), F.col("text").alias("a")), "u").join(found.select(F.col("node").alias("v"), F.col("text").alias("b")), "v")

    def run(batches):
        for batch in batches:
            u, last = None, None
            keep = []
            for i in range(batch.num_rows):
                if (x := batch.column(0)[i].as_py()) != u:
                    u, last = x, shingles(batch.column(2)[i].as_py())
                keep.append(similar(last, shingles(batch.column(3)[i].as_py()), percent))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"]).filter(pa.array(keep, pa.bool_()))

    return both.select("u", "v", "a", "b").mapInArrow(run, "u bigint, v bigint")


def links(docs: DataFrame, distinct: DataFrame, text: str = "text", percent: int = 80) -> DataFrame:
    """(u, v): verified links between nodes (node, bands, fp), a node being the xxhash64 of a text."""
    texts = docs.select(F.xxhash64(f"`{text}`").alias("node"), F.col(f"`{text}`").alias("text"))
    listed, prints = band_postings(distinct), distinct.select("node", "fp")
    near = materialize(simhash.link_fingerprints(prints.select("fp").distinct()))
    pairs = candidates(distinct, listed=listed).unionByName(simhash_candidates(prints, near)).distinct()
    found = materialize(verified(pairs, texts, percent))
    rest = open_nodes(prints, listed, near, found)
    return found.unionByName(verified(rest_pairs(rest, texts, percent), texts, percent))
