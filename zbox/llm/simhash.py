"""SimHash near-duplicates by a byte-position inverted index with count filtering.

A 64-bit fingerprint is eight positional bytes. Two fingerprints that differ in at most d bits
differ in at most d bytes, so they share at least 8 - d positional bytes: the guaranteed minimum.
Postings of single bytes would be 2,048 whatever the corpus, and their pairs its square; so the index
posts every *distinct* fingerprint under blocks of four positional bytes. The 14 blocks are the
4-subsets of the positions 0 to 7 that XOR to zero. Of them 14, 7, 3 lie within 8, 7, 6 shared
bytes, and at most one within 5 or fewer: a pair's tally of shared blocks tells exactly whether it
shares the guaranteed bytes. Pairs that reach the minimum are verified by counting bits.

Copies never multiply: fingerprints are made distinct before the index. A posting list longer than
``list_cap`` (a dense heap of near copies) is not paired at all; its members are linked by midpoints
instead: fingerprints within two bits of each other are exactly those that share a point at one bit
or less from both, so every member is posted under itself and its 64 one-bit neighbours and tied to
the least member of each point. That is exact, linear, and a point has at most 65 members. A pair
that shares a long posting has both ends among these members; one that shares none is tallied whole."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .components import connected_components

SEED = 42
#: Blocks of positional bytes, by their rule.
BLOCKS = tuple(x for x in combinations(range(8), 4) if x[0] ^ x[1] ^ x[2] ^ x[3] == 0)
#: Blocks that a pair shares at least, by the bits it may differ in.
MINIMUM = (14, 7, 3)


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """SimHash of one text as an unsigned integer; 0 where there is no word."""
    w = ("" if text is None else text).encode("utf-8", "surrogatepass").lower().split()
    if not w:
        return 0
    grams = zip(*(w[i:] for i in range(shingle))) if len(w) >= shingle else [w]
    join, digest = b" ".join, xxhash.xxh64_intdigest
    return majority(np.array([digest(join(g), SEED) for g in grams], dtype=np.uint64))


def majority(h: np.ndarray) -> int:
    """The bits that are set in over half of the hashes; 0 of none."""
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(h), 65536):  # a very long text in bounded steps
        ones += np.unpackbits(h[at : at + 65536].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(h)).tobytes(), "big")


def add_fingerprints(docs: DataFrame, text: str, keep: list[str], shingle: int = 3) -> DataFrame:
    """(keep..., fp bigint): the fingerprint's 64 bits as a signed long."""
    part = docs.select(*(F.col(f"`{c}`") for c in keep), F.col(text).alias("__text"))
    schema = part.drop("__text").withColumn("fp", F.lit(0).cast("bigint")).schema

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                piece = batch.slice(at, 256)
                fps = np.array([fingerprint(x.as_py(), shingle) for x in piece.column(piece.num_columns - 1)], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([*piece.columns[:-1], pa.array(fps)], names=[*piece.schema.names[:-1], "fp"])

    return part.mapInArrow(run, schema)


def _bytes_key(fp: Column, positions: tuple[int, ...]) -> Column:
    mask = sum(0xFF << (8 * p) for p in positions)
    return fp.bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask).cast("bigint"))


def postings(distinct: DataFrame) -> DataFrame:
    """(fp, slot, bytes): each fingerprint under its blocks."""
    entry = F.array(*(F.struct(F.lit(k).alias("slot"), _bytes_key(F.col("fp"), pos).alias("bytes")) for k, pos in enumerate(BLOCKS)))
    return distinct.select("fp", F.explode(entry).alias("e")).select("fp", F.col("e.slot").alias("slot"), F.col("e.bytes").alias("bytes"))


def tallied_pairs(light: DataFrame, max_bits: int) -> DataFrame:
    """(u, v, shared), u > v: pairs of the postings with their tally of shared blocks, the guaranteed
    minimum or more. Not yet verified."""
    a, b = light.select("slot", "bytes", F.col("fp").alias("u")), light.select("slot", "bytes", F.col("fp").alias("v"))
    pairs = a.join(b, ["slot", "bytes"]).filter(F.col("u") > F.col("v"))
    return pairs.groupBy("u", "v").agg(F.count("*").alias("shared")).filter(F.col("shared") >= MINIMUM[max_bits])


def link_fingerprints(distinct: DataFrame, max_bits: int = 2, list_cap: int = 64) -> DataFrame:
    """(u, v): links between distinct fingerprints (column fp) at ``max_bits`` (0 to 2) or fewer
    differing bits, enough of them to connect whatever the full set of links connects. All links of
    postings up to ``list_cap`` are there; a longer posting gives links to the least member of each
    midpoint."""
    if not 0 <= max_bits <= 2:
        raise ValueError("midpoints are exact for 0 to 2 bits")
    posts = postings(distinct)
    sizes = posts.groupBy("slot", "bytes").agg(F.count("*").alias("n")).filter(F.col("n") > 1)
    listed = materialize(posts.join(sizes, ["slot", "bytes"]))
    pairs = tallied_pairs(listed.filter(F.col("n") <= list_cap), max_bits)
    pairs = pairs.filter(F.bit_count(F.col("u").bitwiseXOR(F.col("v"))) <= max_bits).select("u", "v")
    dense = listed.filter(F.col("n") > list_cap).select("fp").distinct()
    near = [F.lit(0)] + [F.lit(1 << i if i < 63 else -(1 << 63)) for i in range(64)]
    near = near[:1] if max_bits == 0 else near
    points = dense.select("fp", F.explode(F.array(*(m.cast("bigint") for m in near))).alias("m")).select("fp", F.col("fp").bitwiseXOR(F.col("m")).alias("p"))
    if max_bits == 1:  # a shared point that is one of the two members
        points = points.join(dense.select(F.col("fp").alias("p")), "p", "left_semi").select("fp", "p")
        ties = points.filter(F.col("fp") != F.col("p")).select(F.col("fp").alias("u"), F.col("p").alias("v"))
    else:
        centre = points.groupBy("p").agg(F.min("fp").alias("v"), F.count("*").alias("k")).filter("k > 1").select("p", "v")
        ties = points.join(centre, "p").filter(F.col("fp") != F.col("v")).select(F.col("fp").alias("u"), "v")
    return pairs.unionByName(ties)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", max_bits: int = 2, shingle: int = 3, list_cap: int = 64) -> DataFrame:
    """One row per row of ``docs``: (id_col, fp bigint, component_id), component_id being the least
    id reachable over links of ``max_bits`` or fewer differing bits, the row's own included.

    Null and empty texts have fingerprint zero and link like any other. Whole texts are read, long ones
    in bounded steps. Null ids are carried; they never become a component's id unless it has no other.
    Repeated rows stay repeated. Columns beside id and text are not read, whatever their names. An empty
    table gives an empty result."""
    prints = materialize(add_fingerprints(docs, text, [id_col], shingle))
    classes = materialize(prints.groupBy("fp").agg(F.min(id_col).alias("least")))
    roots = connected_components(link_fingerprints(classes.select("fp"), max_bits, list_cap))
    rooted = classes.join(roots, classes["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    best = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = materialize(rooted.join(best, "root").select("fp", "component_id"))
    return prints.join(named, "fp").select(id_col, "fp", "component_id")


def hex_digits(fp: Column) -> Column:
    """16 lower-case hex digits of a long's 64 bits."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
