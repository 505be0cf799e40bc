"""Best-fit packing of documents into sequences, planned on the length histogram.

Documents are tokenized and cut once; what is planned is not documents but counts per length (at
most ``capacity`` numbers, whatever the corpus). Best fit decreasing over the counts handles all
pieces of one length together: a group of equal bins takes them in one step, so the plan is a list of
slot runs whose number depends on the capacity alone. Pieces then take slots by an equi-join on
(length, rank within length).

A rank within a length is made of two parts so that no length is ever sorted in one task: the rank
within (length, hash bucket) and the running total of the bucket counts."""

from __future__ import annotations

import math
import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialize

#: Characters on which every Unicode version agrees; other texts take the slower, defining path.
_COMMON = re.compile("[^\t\n\r\x20-\x7e\xa1-\xac\xae-ɏ‐-‧‰-›€]")


@lru_cache(maxsize=4)
def encoder(json_path: str, ranks_path: str | None = None, pattern: str | None = None):
    """Text to an array of ids. The JSON file's tokenizer defines the ids. Where the same vocabulary
    is given as ranks, ordinary text goes through the faster library; text with characters out of the
    common ones, or with the name of a special token, goes through the defining one."""
    from tokenizers import Tokenizer

    own = Tokenizer.from_file(json_path)
    special = [t.content for t in own.get_added_tokens_decoder().values()]
    defining = lambda text: np.array(own.encode(text, add_special_tokens=False).ids, dtype="<u4")
    if ranks_path is None:
        return defining
    import base64

    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f)}
    fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def encode(text: str) -> np.ndarray:
        if _COMMON.search(text) or any(s in text for s in special):
            return defining(text)
        return np.array(fast.encode_ordinary(text), dtype="<u4")

    return encode


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: one if it fits, else full ones but for the first."""
    first = n % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


def tokenize(docs: DataFrame, id_col: str, text: str, tokenizer: dict, capacity: int, end_id: int, keep_ids: bool = False) -> DataFrame:
    """(id_col, piece, start, length, ids_crc32[, ids]): a row per piece."""
    part = docs.select(F.col(f"`{id_col}`"), F.col(text).alias("__text"))
    schema = part.select(id_col, F.lit(0).alias("piece"), *(F.lit(0).cast("bigint").alias(c) for c in ("start", "length", "ids_crc32")), *([F.array().cast("array<bigint>").alias("ids")] if keep_ids else [])).schema
    to = pa.int64()

    def run(batches):
        encode = encoder(**tokenizer)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                some = batch.slice(at, 256)
                rows, piece, start, length, crc, kept = [], [], [], [], [], []
                for k, x in enumerate(some.column(1)):
                    ids = np.append(encode(x.as_py() or ""), np.array([end_id], dtype="<u4"))
                    raw = memoryview(ids.tobytes())
                    for p, (s, n) in enumerate(cut(len(ids), capacity)):
                        rows.append(k), piece.append(p), start.append(s), length.append(n), crc.append(zlib.crc32(raw[4 * s : 4 * (s + n)]))
                        if keep_ids:
                            kept.append(ids[s : s + n].astype(np.int64))
                columns = [some.column(0).take(pa.array(rows, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, to), pa.array(length, to), pa.array(crc, to)]
                yield pa.RecordBatch.from_arrays(columns + ([pa.array(kept, pa.list_(to))] if keep_ids else []), names=[f.name for f in schema])

    return part.mapInArrow(run, schema)


def best_fit_plan(counts: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Best fit decreasing over counts. Returns slot runs (length, first rank, number, first bin,
    offset): the pieces of a length with ranks first .. first + number - 1 go, in order, to the bins
    first bin, first bin + 1, ... at that offset; and the number of bins."""
    room: list[list[tuple[int, int]]] = [[] for _ in range(capacity + 1)]  # by room left: runs of equal bins (first, number)
    runs, bins = [], 0
    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        if not 1 <= length <= capacity:
            raise ValueError(f"length {length} is not within 1 to {capacity}")
        while left:
            r = next((r for r in range(length, capacity) if room[r]), None)
            if r is None:
                fit = capacity // length
                for number, each in ((left // fit, fit), (1, left % fit)):
                    if number and each:
                        for k in range(each):
                            runs.append((length, rank, number, bins, k * length))
                            rank += number
                        room[capacity - each * length].append((bins, number))
                        bins += number
                left = 0
                continue
            first, number = room[r].pop()
            take = min(number, left)
            runs.append((length, rank, take, first, capacity - r))
            room[r - length].append((first, take))
            if take < number:
                room[r].append((first + take, number - take))
            left, rank = left - take, rank + take
    return runs, bins


def pack(docs: DataFrame, tokenizer: dict, id_col: str = "doc_id", text: str = "text", capacity: int = 1024, end_id: int = 2, keep_ids: bool = False, bucket_rows: int = 2_000) -> DataFrame:
    """A row per piece: id_col, piece, start, length, ids_crc32, sequence_id, offset[, ids].

    ``tokenizer``: arguments of :func:`encoder`. Null and empty texts are one piece of the end id
    alone. Null ids are carried. Rows of one id are packed as documents of their own. Columns beside
    id and text are not read. An empty table gives an empty result."""
    spark = docs.sparkSession
    pieces = materialize(tokenize(docs, id_col, text, tokenizer, capacity, end_id, keep_ids))
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    runs, _ = best_fit_plan(counts, capacity)
    buckets = max(1, math.ceil(sum(counts.values()) / bucket_rows))
    slot = pieces.withColumn("bucket", F.pmod(F.xxhash64(id_col, "piece", "ids_crc32"), F.lit(buckets)))
    per = slot.groupBy("length", "bucket").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("length").orderBy("bucket")) - F.col("n")
    per = per.select("length", "bucket", before.alias("before"))
    order = [F.col(id_col), F.col("piece"), F.col("start"), F.col("ids_crc32")]  # equal in all of these: interchangeable
    ranked = slot.withColumn("within", F.row_number().over(Window.partitionBy("length", "bucket").orderBy(*order)))
    ranked = ranked.join(per, ["length", "bucket"]).withColumn("rank", F.col("before") + F.col("within") - 1)
    plan = spark.createDataFrame(runs, "length bigint, first_rank bigint, number bigint, first_bin bigint, offset bigint")
    block = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("number") - 1, F.lit(bucket_rows).cast("bigint")))
    plan = plan.withColumn("block", block).repartition("length", "block", "first_rank")
    step = F.explode(F.sequence(F.col("block"), F.least(F.col("block") + bucket_rows, F.col("number")) - 1))
    slots = plan.withColumn("step", step).select("length", (F.col("first_rank") + F.col("step")).alias("rank"), (F.col("first_bin") + F.col("step")).alias("sequence_id"), "offset")
    # both sides hold a row per piece; the plan's few rows would have Spark take the exploded slots for small
    placed = ranked.join(slots.hint("merge"), ["length", "rank"])
    return placed.select(id_col, "piece", "start", "length", "ids_crc32", "sequence_id", "offset", *(["ids"] if keep_ids else []))


def sequences(packed: DataFrame) -> DataFrame:
    """(sequence_id, ids): the tokens of every sequence, from pieces packed with their ids. A group
    holds at most one capacity of tokens."""
    parts = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("p"))
    return parts.select("sequence_id", F.flatten(F.transform("p", lambda x: x["ids"])).alias("ids"))
