"""Approximate nearest neighbours by balanced posting lists.

Vectors live in posting lists on disk (a DataFrame), only the lists' centroids in memory. Centroids
come from balanced splitting of a bounded sample; every vector is then posted, those near a boundary
to several lists. A query finds its nearest centroids through a graph over the centroids, keeps the
lists whose distance is within a ratio of the nearest one's, and scans these lists exactly.

The ratio is fitted, not set: for a bounded sample of vectors the true neighbours are worked out against
all rows, and the ratio is the least that would have reached ``target_recall`` of them. Where vectors form
clusters that prunes nearly all lists, however many there are; where their components are independent
nothing can be pruned much, and the lists scanned remain a share of all (README has figures of both).

Largest inner product is made nearest distance by one more component that lifts all vectors to the
same norm. Equal vectors are searched once: a vector keeps the least ids that bear it, as many as an
answer can show. Lists too long for one task are cut into parts, and so are the queries of a list."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialize


@dataclass(frozen=True)
class ListParams:
    """``lists_per_root``: lists over the square root of the vectors, so that choosing lists and scanning
    one grow alike. ``max_lists`` and ``sample_rows`` bound what the driver holds; the sample fits the
    centroids only. ``replicas``, ``boundary``: a vector goes to up to so many lists within 1 + boundary of
    its nearest distance. ``target_recall``, ``fit_queries``: the ratio is the least that reaches this recall
    on so many vectors. ``part_rows``: most vectors, and most queries, that one task takes at a time."""

    lists_per_root: float = 1.5
    max_lists: int = 4096
    sample_rows: int = 40_000
    replicas: int = 4
    boundary: float = 0.02
    target_recall: float = 0.95
    fit_queries: int = 96
    degree: int = 16
    beam: int = 24
    part_rows: int = 4_000


class CentroidGraph:
    """Centroids with links to their nearest ones, searched best first by a beam, many queries at once. A
    step looks at the links of a few centroids of the beam alone; a beam of a quarter of all centroids
    or more is a plain scan of them, which is then less work."""

    def __init__(self, centroids: np.ndarray, degree: int):
        self.c = np.ascontiguousarray(centroids, dtype=np.float32)
        k = len(self.c)
        self.norm = (self.c * self.c).sum(1)
        near = np.zeros((k, max(1, min(degree, k - 1))), dtype=np.int64)
        for at in range(0, k, 512) if k > 1 else ():
            d = self.norm - 2 * self.c[at : at + 512] @ self.c.T
            d[np.arange(len(d)), at + np.arange(len(d))] = np.inf
            near[at : at + 512] = np.argsort(d, axis=1, kind="stable")[:, : near.shape[1]]
        # a ring through all centroids keeps the graph connected
        ring = np.stack([(np.arange(k) + 1) % k, (np.arange(k) - 1) % k], axis=1)
        self.links = np.hstack([near, ring]).astype(np.int32)
        step = max(1, k // 32)
        self.entry = np.arange(0, k, step, dtype=np.int32)

    def distances(self, q: np.ndarray, ids: np.ndarray | None = None) -> np.ndarray:
        """Squared distances of rows to all centroids, or to each row's own ``ids``."""
        qn = (q * q).sum(1)[:, None]
        d = qn + self.norm - 2 * q @ self.c.T if ids is None else qn + self.norm[ids] - 2 * np.einsum("bnd,bd->bn", self.c[ids], q)
        return np.maximum(d, 0)

    def search(self, x: np.ndarray, width: int, step: int = 4) -> tuple[np.ndarray, np.ndarray]:
        """Nearest centroids found of each row: (ids, distances), nearest first, ``width`` of them."""
        k = len(self.c)
        width = min(width, k)
        ids, dist = [np.zeros((0, width), np.int32)], [np.zeros((0, width), np.float32)]
        for at in range(0, len(x), 256):
            q = np.ascontiguousarray(x[at : at + 256], dtype=np.float32)
            top, d = self._all(q, width) if 4 * width >= k else self._beam(q, max(width, 8), step)
            ids.append(top[:, :width])
            dist.append(np.sqrt(d[:, :width]))
        return np.concatenate(ids), np.concatenate(dist)

    def _all(self, q: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        d = self.distances(q)
        top = np.argpartition(d, width - 1, axis=1)[:, :width]
        return _in_order(top, np.take_along_axis(d, top, 1))

    def _beam(self, q: np.ndarray, width: int, step: int) -> tuple[np.ndarray, np.ndarray]:
        n, rows = len(q), np.arange(len(q))[:, None]
        seen, opened = np.zeros((n, len(self.c)), dtype=bool), np.zeros((n, len(self.c)), dtype=bool)
        beam = np.broadcast_to(self.entry, (n, len(self.entry)))
        seen[:, self.entry] = True
        d = self.distances(q, beam)
        while True:
            beam, d = _in_order(beam, d)
            beam, d = beam[:, :width], d[:, :width]
            todo = np.where(opened[rows, beam] | np.isinf(d), np.inf, d)
            some = np.argpartition(todo, min(step, todo.shape[1]) - 1, axis=1)[:, :step]
            open_ = ~np.isinf(np.take_along_axis(todo, some, 1))
            if not open_.any():
                return beam, d
            centre = np.take_along_axis(beam, some, 1)
            r, c = np.nonzero(open_)
            opened[r, centre[r, c]] = True
            new = self.links[centre].reshape(n, -1)
            fresh = ~seen[rows, new] & np.repeat(open_, self.links.shape[1], axis=1)
            # a centroid that two of them link to counts once
            order = np.argsort(new, axis=1, kind="stable")
            new, fresh = np.take_along_axis(new, order, 1), np.take_along_axis(fresh, order, 1)
            fresh[:, 1:] &= (new[:, 1:] != new[:, :-1]) | ~fresh[:, :-1]
            r, c = np.nonzero(fresh)
            seen[r, new[r, c]] = True
            beam, d = np.hstack([beam, new]), np.hstack([d, np.where(fresh, self.distances(q, new), np.inf)])


def _in_order(ids: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(d, axis=1, kind="stable")
    return np.take_along_axis(ids, order, 1), np.take_along_axis(d, order, 1)


def balanced_centroids(x: np.ndarray, lists: int, seed: int = 11, rounds: int = 4) -> np.ndarray:
    """About ``lists`` centroids by splitting the largest part near its middle, again and again, then
    a few rounds of means over the nearest rows."""
    r = np.random.default_rng(seed)
    parts = [np.arange(len(x))]
    while len(parts) < min(lists, len(x)):
        parts.sort(key=len)
        whole = parts.pop()
        y = x[whole]
        a, b = y[r.choice(len(y), 2, replace=False)]
        for _ in range(6):
            side = ((y - a) ** 2).sum(1) <= ((y - b) ** 2).sum(1)
            if side.all() or not side.any():
                break
            a, b = y[side].mean(0), y[~side].mean(0)
        lean = np.argsort(y @ (b - a), kind="stable")
        middle = int(np.clip(side.sum(), 0.35 * len(y), 0.65 * len(y)))
        middle = min(max(1, middle), len(y) - 1)
        parts += [whole[lean[:middle]], whole[lean[middle:]]]
    c = np.stack([x[p].mean(0) for p in parts])
    for _ in range(rounds):
        near = np.concatenate([np.argmin((c * c).sum(1) - 2 * x[i : i + 4096] @ c.T, axis=1) for i in range(0, len(x), 4096)])
        count = np.bincount(near, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        c = np.where(count[:, None] > 0, total / np.maximum(count, 1)[:, None], c)
    return c.astype(np.float32)


def _matrix(column) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = np.asarray(column.flatten())  # honours the offset of a sliced batch
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def valid_vectors(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(id, v): rows whose vector is not null, not zero, and holds finite components only; of these,
    the ones with the most common number of components. A null id takes no part."""
    rows = vectors.select(F.col(f"`{id_col}`").cast("bigint").alias("id"), F.col(f"`{vec_col}`").alias("v"))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = rows.filter(F.col("id").isNotNull() & F.col("v").isNotNull() & finite & F.exists("v", lambda x: x != 0))
    width = rows.groupBy(F.size("v").alias("n")).agg(F.count("*").alias("k")).orderBy(F.desc("k"), "n").first()
    return rows.filter(F.size("v") == (width["n"] if width else 0))


@dataclass
class PostingIndex:
    """Distinct vectors (rep, v, ids) in lists, with what choosing lists needs. ``norm2`` is the largest
    squared norm; ``ratio`` and ``width`` choose a query's lists."""

    unique: DataFrame
    posts: DataFrame
    graph: CentroidGraph
    norm2: float
    n: int
    ratio: float
    width: int

    def chosen(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, list) of the lists that queries look through."""
        ids, d = self.graph.search(_as_query(x, self.norm2), self.width)
        row, col = np.nonzero(d <= self.ratio * d[:, :1] + 1e-6)
        return row, ids[row, col]


def _lifted(x: np.ndarray, norm2: float) -> np.ndarray:
    return np.hstack([x, np.sqrt(np.maximum(0.0, norm2 - (x * x).sum(1)))[:, None]])


def _as_query(x: np.ndarray, norm2: float) -> np.ndarray:
    long = np.sqrt(norm2 / (x * x).sum(1))
    return np.hstack([x * long[:, None], np.zeros((len(x), 1))])


def build_index(rows: DataFrame, want: int, p: ListParams) -> PostingIndex | None:
    """The index of valid rows (id, v); None without any. ``want``: neighbours that answers show."""
    # each distinct vector with its least ids, in two steps so that a very common vector meets in no one task
    salt = F.pmod(F.xxhash64("id"), F.lit(16))
    least = rows.withColumn("s", salt).withColumn("r", F.row_number().over(Window.partitionBy("v", "s").orderBy("id"))).filter(F.col("r") <= want)
    least = least.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).filter(F.col("r") <= want)
    unique = materialize(least.groupBy("v").agg(F.array_sort(F.collect_list("id")).alias("ids")).withColumn("rep", F.col("ids")[0]))
    stats = unique.agg(F.count("*").alias("n"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))).alias("m")).first()
    if not stats["n"]:
        return None
    norm2, n, cells = stats["m"], stats["n"], 1 << 20
    part = lambda name, rows_: F.pmod(F.xxhash64("rep", F.lit(name)), F.lit(cells)) < max(1, math.ceil(cells * min(1.0, rows_ / n)))
    picked = unique.filter(part("sample", p.sample_rows))
    sample = [np.array(r["v"], dtype=np.float64) for r in picked.orderBy("rep").select("v").limit(2 * p.sample_rows).collect()] or [np.array(unique.select("v").first()["v"], dtype=np.float64)]
    lists = int(min(p.max_lists, max(1, round(p.lists_per_root * math.sqrt(n)))))
    graph = CentroidGraph(balanced_centroids(_lifted(np.stack(sample), norm2), lists), p.degree)

    def post(batches):
        for b in batches:
            if not b.num_rows:
                continue
            ids, d = graph.search(_lifted(_matrix(b.column("v")).astype(np.float64), norm2), p.beam)
            ids, d = ids[:, : p.replicas], d[:, : p.replicas]
            row, col = np.nonzero(d <= (1 + p.boundary) * d[:, :1] + 1e-6)
            yield pa.RecordBatch.from_arrays([pa.array(ids[row, col].astype(np.int32)), *b.take(pa.array(row)).columns], names=["list", "rep", "v"])

    of = dict(unique.dtypes)["v"]
    posts = materialize(unique.select("rep", "v").mapInArrow(post, f"list int, rep bigint, v {of}"))
    # the fit's queries are the vectors of least hash
    asked = unique.filter(part("fit", 4 * p.fit_queries)).orderBy(F.xxhash64("rep", F.lit("fit")), "rep").limit(p.fit_queries).select("rep", "v").collect()
    ratio, width = _fit(unique, posts, graph, norm2, asked, want, p)
    return PostingIndex(unique, posts, graph, norm2, n, ratio, width)


def _fit(unique: DataFrame, posts: DataFrame, graph: CentroidGraph, norm2: float, asked: list, want: int, p: ListParams) -> tuple[float, int]:
    """(ratio, width): the least distance ratio at which the lists within it hold ``target_recall`` of the
    true neighbours of ``asked``, and a beam that finds that many lists with some to spare."""
    k = len(graph.c)
    if not asked:
        return math.inf, k
    q, q_rep = np.array([r["v"] for r in asked], dtype=np.float64), np.array([r["rep"] for r in asked])

    def nearest(batches):
        """Each task's best for every one of the queries."""
        rep, score = np.zeros((len(q), 0), np.int64), np.zeros((len(q), 0))
        for b in batches:
            if not b.num_rows:
                continue
            ids = np.asarray(b.column("rep"))
            s = q @ _matrix(b.column("v")).astype(np.float64).T
            s[q_rep[:, None] == ids] = -np.inf
            rep, score = np.hstack([rep, np.broadcast_to(ids, s.shape)]), np.hstack([score, s])
            top = np.argsort(-score, axis=1, kind="stable")[:, : want - 1]
            rep, score = np.take_along_axis(rep, top, 1), np.take_along_axis(score, top, 1)
        real = np.isfinite(score)
        row = np.nonzero(real)[0].astype(np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(row), pa.array(rep[real]), pa.array(score[real])], names=["q", "rep", "score"])

    best = unique.select("rep", "v").mapInArrow(nearest, "q int, rep bigint, score double")
    order = Window.partitionBy("q").orderBy(F.desc("score"), "rep")
    best = best.withColumn("r", F.row_number().over(order)).filter(F.col("r") < want).select("q", "rep")
    held = best.join(posts.select("list", "rep"), "rep").collect()  # at most fit_queries * want * replicas
    d = np.sqrt(graph.distances(_as_query(q, norm2).astype(np.float32)))
    ratio = d / np.maximum(d.min(1, keepdims=True), 1e-9)
    need: dict = {}
    for r in held:
        at = (r["q"], r["rep"])
        need[at] = min(need.get(at, math.inf), ratio[r["q"], r["list"]])
    if not need:
        return math.inf, k
    fitted = float(np.quantile(np.array(list(need.values())), p.target_recall, method="higher"))
    most = int((ratio <= fitted).sum(1).max())
    return fitted, min(k, max(p.beam, most + most // 4))


def search(vectors: DataFrame, is_query, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 20, params: ListParams = ListParams()) -> DataFrame:
    """(query_id, rank, vec_id, score): for every row that ``is_query`` (a function of the id column)
    picks, the ``k`` other rows of largest inner product found, nearest first, ties to the smaller id.

    A query gets ``k`` rows wherever there are as many others: one whose lists hold too few looks
    through all lists. Rows repeated in id and vector count once. Null, zero, non-finite and odd-sized
    vectors and null ids take no part, as query or answer. Other columns are not read, whatever their
    names. No valid rows, or an empty table: no result."""
    spark, p, want = vectors.sparkSession, params, k + 1
    rows = materialize(valid_vectors(vectors, id_col, vec_col).distinct())
    index = build_index(rows, want, p)
    if index is None:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    unique, posts, n, lists = index.unique, index.posts, index.n, len(index.graph.c)
    queries = rows.filter(is_query(F.col("id")))
    linked = materialize(queries.join(unique.select("v", "rep"), "v").select(F.col("id").alias("query_id"), "rep", "v"))
    asked = linked.select("rep", "v").dropDuplicates(["rep"])
    chooser = PostingIndex(None, None, index.graph, index.norm2, n, index.ratio, index.width)

    def probe(batches):
        for b in batches:
            if b.num_rows:
                row, to = chooser.chosen(_matrix(b.column("v")).astype(np.float64))
                yield pa.RecordBatch.from_arrays([pa.array(to.astype(np.int32)), *b.take(pa.array(row)).columns], names=["list", "rep", "v"])

    found = materialize(_scan(posts, asked.mapInArrow(probe, posts.schema), want, p))
    enough = min(want, n)
    few = asked.join(found.groupBy("rep").agg(F.count("*").alias("got")), "rep", "left").filter(F.coalesce("got", F.lit(0)) < enough).select("rep", "v")
    held = unique.select(F.col("rep").alias("near"), F.size("ids").alias("held"))
    got_ids = found.join(held, "near").groupBy("rep").agg(F.sum("held").alias("ids")).filter(F.col("ids") >= want).select("rep")
    few = materialize(few.join(got_ids, "rep", "left_anti"))
    if not few.isEmpty():
        every = few.select(F.explode(F.sequence(F.lit(0), F.lit(lists - 1))).alias("list"), "rep", "v")
        found = found.join(few.select("rep"), "rep", "left_anti").unionByName(_scan(posts, every, want, p))
    # answers per distinct query vector, then per query without itself
    each = found.join(unique.select(F.col("rep").alias("near"), "ids"), "near").select("rep", "score", F.explode("ids").alias("vec_id"))
    order = Window.partitionBy("rep").orderBy(F.desc("score"), "vec_id")
    answers = each.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= want)
    answers = answers.groupBy("rep").agg(F.array_sort(F.collect_list(F.struct("r", "vec_id", "score"))).alias("a"))
    out = linked.select("query_id", "rep").join(answers, "rep")
    out = out.select("query_id", F.posexplode(F.slice(F.filter("a", lambda x: x["vec_id"] != F.col("query_id")), 1, k)).alias("i", "x"))
    return out.select("query_id", (F.col("i") + 1).alias("rank"), F.col("x.vec_id").alias("vec_id"), F.col("x.score").alias("score"))


def _scan(posts: DataFrame, probes: DataFrame, want: int, p: ListParams) -> DataFrame:
    """(rep, near, score): the ``want`` best distinct vectors of each query over the lists it probes."""
    probes = materialize(probes)
    # one number per list each way, so at most max_lists
    cut = lambda df: df.groupBy("list").agg(F.ceil(F.count("*") / p.part_rows).cast("int").alias("parts"))
    parts = cut(posts).join(cut(probes).withColumnRenamed("parts", "qparts"), "list")
    parts = F.broadcast(parts)
    left = posts.join(parts, "list").withColumn("part", F.pmod(F.xxhash64("rep"), F.col("parts"))).withColumn("qpart", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("qparts") - 1)))
    right = probes.join(parts, "list").withColumn("qpart", F.pmod(F.xxhash64("rep"), F.col("qparts"))).withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1)))
    key = ["list", "part", "qpart"]

    def best(vs: pa.Table, qs: pa.Table) -> pa.Table:
        names = ["rep", "near", "score"]
        if not vs.num_rows or not qs.num_rows:
            return pa.table([pa.array([], pa.int64()), pa.array([], pa.int64()), pa.array([], pa.float64())], names=names)
        x, ids = _matrix(vs.column("v")).astype(np.float64), np.asarray(vs.column("rep"))
        order = np.argsort(ids, kind="stable")
        x, ids = x[order], ids[order]
        a, q = _matrix(qs.column("v")).astype(np.float64), np.asarray(qs.column("rep"))
        out = ([], [], [])
        more = min(len(ids), want + 8)
        for at in range(0, len(q), 512):
            some = a[at : at + 512]
            s = some @ x.T
            top = np.argpartition(-s, more - 1, axis=1)[:, :more]
            exact = np.einsum("bnd,bd->bn", x[top], some)  # the same sum whatever the list's shape
            for i in range(len(some)):
                o = np.lexsort((ids[top[i]], -exact[i]))[:want]
                out[0].append(np.full(len(o), q[at + i])), out[1].append(ids[top[i][o]]), out[2].append(exact[i][o])
        return pa.table([pa.array(np.concatenate(c)) for c in out], names=names)

    scored = left.select(*key, "rep", "v").groupBy(*key).cogroup(right.select(*key, "rep", "v").groupBy(*key)).applyInArrow(best, "rep bigint, near bigint, score double")
    scored = scored.groupBy("rep", "near").agg(F.max("score").alias("score"))
    order = Window.partitionBy("rep").orderBy(F.desc("score"), "near")
    return scored.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= want).drop("r")
