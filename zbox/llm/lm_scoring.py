"""Language-model scores of documents: a log-bilinear neural model trained by noise contrast.

All words are counted first. The model's vocabulary is the ``vocabulary`` most frequent ones, the end of a
text, and ``BUCKETS`` buckets that every other word falls into by a hash; a word of a bucket gets the bucket's
probability times its smoothed share within it, so probabilities sum to one over all words, unseen
ones included. What comes before is seen through ``contexts`` context classes: the most frequent words and the
end by themselves, all others by a hash of their last two bytes. Two context vectors, weighted component
by component, are summed and multiplied with target vectors, plus a bias.

Training is noise-contrastive estimation in numpy over every run of the learnt texts: in each of four rounds a
quarter of the documents, the trainers (as many as the cluster has cores) each on the texts of its part,
after which parameters are averaged, each row by how often its trainer met it. Noise contrast needs no
normalising; scoring does it exactly: the normaliser of all contexts is one product of two matrices of
exponentials, taken in blocks of the vocabulary.

Word counts grow with the corpus and are joined, not broadcast, save the most frequent ones: a head of
at most ``head_words`` words is held in memory, which takes the hot keys out of the join."""

from __future__ import annotations

import math
import uuid
import zlib
from collections import Counter
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold_bucket, materialize

DIM = 24
BUCKETS = 1024
BLOCK = 4096
_FLUSH = 200_000
_CACHE: dict = {}


def tokens(text: str | None) -> list[bytes]:
    """Words of a text, A-Z lowered, without the end."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


# --- counting -------------------------------------------------------------------------------------


def word_counts(texts: DataFrame) -> DataFrame:
    """(word, c) over column text: partial counts in the workers, summed in Spark."""

    def run(batches):
        def emit(some):
            return pa.RecordBatch.from_arrays([pa.array([w.decode("utf-8", "surrogatepass") for w in some]), pa.array(list(some.values()), pa.int64())], names=["word", "c"])

        some: Counter = Counter()
        for b in batches:
            for x in b.column(0):
                w = tokens(x.as_py())
                for at in range(0, len(w), _FLUSH):
                    some.update(w[at : at + _FLUSH])
                    if len(some) > _FLUSH:
                        yield emit(some)
                        some = Counter()
        if some:
            yield emit(some)

    parts = texts.select("text").mapInArrow(run, "word string, c bigint")
    return parts.groupBy("word").agg(F.sum("c").alias("c"))


def head_of(counts: DataFrame, head_words: int) -> list[tuple[str, int]]:
    """The most frequent words, at most ``head_words``, in order of count and word. The cut is made on
    a histogram of counts of a few hundred bins, so the driver never sees more."""
    bin_ = F.floor(F.log2("c") * 16)
    total, low = 0, None
    for r in sorted(counts.groupBy(bin_.alias("b")).agg(F.count("*").alias("n")).collect(), key=lambda r: -r["b"]):
        if total + r["n"] > head_words:
            break
        total, low = total + r["n"], r["b"]
    if low is None:
        return []
    return sorted(((r["word"], r["c"]) for r in counts.filter(bin_ >= low).collect()), key=lambda x: (-x[1], x[0]))


# --- the model ------------------------------------------------------------------------------------


def suffix_bucket(word: bytes, buckets: int) -> int:
    return zlib.crc32(word[-2:]) % buckets


def new_model(unigram: np.ndarray, contexts: int, seed: int = 5) -> dict[str, np.ndarray]:
    """``out``, ``bias``: a row per word of the vocabulary; ``in``: a row per context class."""
    r, f = np.random.default_rng(seed), np.float32
    return {"in": r.normal(0, 0.1, (contexts, DIM)).astype(f), "out": r.normal(0, 0.1, (len(unigram), DIM)).astype(f), "mix": np.stack([np.ones(DIM), np.full(DIM, 0.5)]).astype(f), "bias": np.log(unigram).astype(f)}


def _summed(rows: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """(n, DIM): sums of ``rows`` by their number ``at``."""
    order = np.argsort(at, kind="stable")
    of = at[order]
    starts = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]]))
    out = np.zeros((n, rows.shape[1]), dtype=np.float32)
    out[of[starts]] = np.add.reduceat(rows[order], starts, axis=0)
    return out


class NceTrainer:
    """AdaGrad on runs (far, near, target) against ``noise`` draws from the unigram distribution that a batch
    shares. Only rows that a batch meets are touched."""

    def __init__(self, model: dict, unigram: np.ndarray, seed: int, rate: float = 0.05, noise: int = 64, batch: int = 2048):
        self.p = {k: v.copy() for k, v in model.items()}
        self.sums = {k: np.full_like(v, 1e-6) for k, v in self.p.items()}
        self.r, self.rate, self.noise, self.batch = np.random.default_rng(seed), rate, noise, batch
        self.upto, self.shift = np.cumsum(unigram), np.log(noise * unigram).astype(np.float32)
        self.met = {"in": np.zeros(len(model["in"]), np.float32), "out": np.zeros(len(unigram), np.float32)}
        self.runs = 0

    def _move(self, name: str, rows, grad: np.ndarray) -> None:
        self.sums[name][rows] += grad * grad
        self.p[name][rows] += self.rate * grad / np.sqrt(self.sums[name][rows])

    def learn(self, far: np.ndarray, near: np.ndarray, target: np.ndarray) -> None:
        for at in range(0, len(target), self.batch):
            self._step(far[at : at + self.batch], near[at : at + self.batch], target[at : at + self.batch])

    def _step(self, b: np.ndarray, a: np.ndarray, w: np.ndarray) -> None:
        p, n = self.p, np.float32(1 / len(w))
        z = np.minimum(np.searchsorted(self.upto, self.r.random(self.noise) * self.upto[-1]), len(self.upto) - 1)
        va, vb, vw, vz = p["in"][a], p["in"][b], p["out"][w], p["out"][z]
        q = p["mix"][0] * va + p["mix"][1] * vb
        sig = lambda x: 1 / (1 + np.exp(-np.clip(x, -30, 30)))
        up = (1 - sig((q * vw).sum(1) + p["bias"][w] - self.shift[w])) * n
        down = sig(q @ vz.T + (p["bias"][z] - self.shift[z])) * n
        gq = up[:, None] * vw - down @ vz
        rows, at = np.unique(np.concatenate([w, z]), return_inverse=True)
        self._move("out", rows, _summed(np.concatenate([up[:, None] * q, -(down.T @ q)]), at, len(rows)))
        self._move("bias", rows, np.bincount(at, weights=np.concatenate([up, -down.sum(0)]), minlength=len(rows)).astype(np.float32))
        m = len(p["in"])
        self._move("in", slice(None), _summed(gq * p["mix"][0], a, m) + _summed(gq * p["mix"][1], b, m))
        self._move("mix", slice(None), np.stack([(gq * va).sum(0), (gq * vb).sum(0)]))
        self.met["in"] += np.bincount(a, minlength=m) + np.bincount(b, minlength=m)
        self.met["out"][rows] += np.bincount(at, minlength=len(rows))
        self.runs += len(w)


def normaliser(model: dict) -> np.ndarray:
    """Natural logarithm of the sum over the vocabulary, by (near, far) context class: the exponentials of the
    two halves of a score multiply, so that all sums are one matrix product, taken block by block."""
    near, far = model["in"].astype(np.float64) * model["mix"][0], model["in"].astype(np.float64) * model["mix"][1]
    out, bias = model["out"].astype(np.float64), model["bias"].astype(np.float64)
    total, top = np.zeros((len(near), len(near))), np.full((len(near), len(near)), -np.inf)
    for at in range(0, len(out), BLOCK):
        a, b = near @ out[at : at + BLOCK].T + bias[at : at + BLOCK], far @ out[at : at + BLOCK].T
        ma, mb = a.max(1), b.max(1)
        part, scale = np.exp(a - ma[:, None]) @ np.exp(b - mb[:, None]).T, ma[:, None] + mb
        new = np.maximum(top, scale)
        total = total * np.exp(top - new) + part * np.exp(scale - new)
        top = new
    return top + np.log(np.maximum(total, 1e-300))


def log10_of(model: dict, z: np.ndarray, far: np.ndarray, near: np.ndarray, target: np.ndarray) -> np.ndarray:
    """log10 probability of each run's target."""
    q = model["mix"][0] * model["in"][near] + model["mix"][1] * model["in"][far]
    return (np.einsum("nd,nd->n", q, model["out"][target]) + model["bias"][target] - z[near, far]) / math.log(10)


def context_classes(words: int, contexts: int) -> tuple[int, int, int]:
    """Words that are classes of their own (the end comes after them), classes by suffix, all classes."""
    own = min(words, contexts // 2)
    suffixes = max(1, contexts - own - 1)
    return own, suffixes, own + 1 + suffixes


class Vocabulary:
    """Numbers of words: the first ``modelled`` of the head in order, then the end, then the buckets; and their
    context classes."""

    def __init__(self, words: list[str], contexts: int, modelled: int):
        self.head = {w.encode("utf-8", "surrogatepass"): i for i, w in enumerate(words)}
        self.end = min(len(words), modelled)
        self.end_context, self.suffixes, self.contexts = context_classes(len(words), contexts)
        own = self.end_context
        self.target = np.array([i if i < self.end else self.end + 1 + zlib.crc32(w) % BUCKETS for w, i in self.head.items()] + [-1], dtype=np.int32)
        self.context = np.array([i if i < own else own + 1 + suffix_bucket(w, self.suffixes) for w, i in self.head.items()] + [own], dtype=np.int32)

    def number(self, w: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place in the head or -1, target, context class) of a text's words; targets and classes with the end."""
        place = np.fromiter(map(self.head.get, w, repeat(-1)), dtype=np.int64, count=len(w))
        target, context = np.append(self.target[place], self.end), np.append(self.context[place], self.end_context)
        for i in np.flatnonzero(place < 0).tolist():
            target[i] = self.end + 1 + zlib.crc32(w[i]) % BUCKETS
            context[i] = self.end_context + 1 + suffix_bucket(w[i], self.suffixes)
        return place, target, context

    def runs(self, target: np.ndarray, context: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(far, near, target) of a text; what stands before it counts as the end."""
        near = np.concatenate([[self.end_context], context[:-1]])
        return np.concatenate([[self.end_context], near[:-1]]), near, target


def _vocabulary(shared) -> Vocabulary:
    """The vocabulary, built once a worker."""
    head = shared.value
    if head["key"] not in _CACHE:
        _CACHE.clear()
        _CACHE[head["key"]] = Vocabulary(head["words"], head["contexts"], head["modelled"])
    return _CACHE[head["key"]]


def _blocks(trainer: NceTrainer):
    """A trainer's rows with how often it met each, in blocks."""
    for name, met in (("in", trainer.met["in"]), ("out", trainer.met["out"]), ("bias", trainer.met["out"]), ("mix", np.full(2, trainer.runs, np.float32))):
        rows = trainer.p[name].reshape(len(met), -1)
        for at in range(0, len(met), BLOCK):
            yield name, at, rows[at : at + BLOCK].astype("<f4").tobytes(), met[at : at + BLOCK].astype("<f4").tobytes()


def _average(table: pa.Table) -> pa.Table:
    """One block's rows over all trainers, each weighted by its trainer's meetings; null where none met it."""
    total = weight = None
    order = sorted(range(table.num_rows), key=lambda i: table.column("trainer")[i].as_py())  # the same sum in every run
    for i in order:
        w = np.frombuffer(table.column("met")[i].as_py(), "<f4").astype(np.float64)
        rows = np.frombuffer(table.column("rows")[i].as_py(), "<f4").reshape(len(w), -1) * w[:, None]
        total, weight = (rows, w) if total is None else (total + rows, weight + w)
    mean = (total / np.maximum(weight, 1e-30)[:, None]).astype("<f4")
    return pa.table({"name": table.column("name")[:1], "at": table.column("at")[:1], "rows": pa.array([mean.tobytes()], pa.binary()), "met": pa.array([weight.astype("<f4").tobytes()], pa.binary())})


def train(texts: DataFrame, shared, unigram: np.ndarray, runs: int, rounds: int = 4, least_runs: int = 4_000_000) -> dict:
    """The model, trained on all runs of ``texts`` (``runs`` of them), each once; where they are fewer than
    ``least_runs``, so many times over that they come to that."""
    model = new_model(unigram, context_classes(len(shared.value["words"]), shared.value["contexts"])[-1])
    spark = texts.sparkSession
    trainers, passes = max(1, spark.sparkContext.defaultParallelism), max(1, math.ceil(least_runs / max(1, runs)))
    # texts that are equal go to one round; which is no matter to the model
    parts = texts.select("text", F.pmod(F.xxhash64("text"), F.lit(rounds)).alias("round"))

    def trainer(start, rate):
        def run(batches):
            from pyspark import TaskContext

            voc, which = _vocabulary(shared), TaskContext.get().partitionId()
            t = NceTrainer(start.value, unigram_shared.value, seed=1000 + which, rate=rate)
            held, n, kept = [], 0, []

            def learn():
                far, near, to = (np.concatenate(x) for x in zip(*held, strict=True))
                mixed = t.r.permutation(len(to))
                t.learn(far[mixed], near[mixed], to[mixed])

            for batch in batches:
                for x in batch.column(0):
                    _, target, context = voc.number(tokens(x.as_py()))
                    held.append(voc.runs(target, context))
                    n += len(target)
                    if n >= 32 * t.batch:
                        learn()
                        kept += held if passes > 1 else []
                        held, n = [], 0
            if held:
                learn()
                kept += held if passes > 1 else []
            for _ in range(passes - 1 if kept else 0):  # fewer than least_runs are held
                held = kept
                learn()
            for name, at, rows, met in _blocks(t) if t.runs else ():
                yield pa.RecordBatch.from_pydict({"name": [name], "at": [at], "rows": [rows], "met": [met], "trainer": [which]}, schema=pa.schema([("name", pa.string()), ("at", pa.int32()), ("rows", pa.binary()), ("met", pa.binary()), ("trainer", pa.int32())]))

        return run

    unigram_shared = spark.sparkContext.broadcast(unigram)
    for k in range(rounds):
        start = spark.sparkContext.broadcast(model)
        some = parts.filter(F.col("round") == k).select("text").coalesce(trainers)
        blocks = some.mapInArrow(trainer(start, 0.05 / (1 + k) ** 0.5), "name string, at int, rows binary, met binary, trainer int")
        got = blocks.groupBy("name", "at").applyInArrow(_average, "name string, at int, rows binary, met binary").collect()  # the model's size
        model = {name: v.copy() for name, v in model.items()}
        for r in got:
            met = np.frombuffer(bytes(r["met"]), "<f4") > 0
            rows = np.frombuffer(bytes(r["rows"]), "<f4").reshape(len(met), -1)
            of = model[r["name"]].reshape(len(model[r["name"]]), -1)
            of[r["at"] : r["at"] + len(met)][met] = rows[met]
        start.destroy()
        del got
    unigram_shared.destroy()
    return model


# --- scoring --------------------------------------------------------------------------------------


def score(docs: DataFrame, id_col: str = "doc_id", text: str = "text", folds: int = 7, held_fold: int = 2, contexts: int = 384, vocabulary: int = 40_000, head_words: int = 100_000) -> DataFrame:
    """One row per row of ``docs``: id_col, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Documents of ``held_fold`` are scored but not learnt from. base_score: smoothed unigram log10
    probability; score: the model's. Null and empty texts are the end alone. Null ids are carried (and
    fall in the fold of the empty string). Repeated rows are counted and scored each. With nothing to
    learn from, every token is unseen. Other columns are not read, whatever their names. An empty table
    gives an empty result."""
    spark = docs.sparkSession
    part = docs.select(F.col(f"`{id_col}`").alias("id"), (fold_bucket(F.col(f"`{id_col}`"), folds) == held_fold).alias("held_out"), F.col(f"`{text}`").alias("text"))
    learn = part.filter(~F.col("held_out")).select("text")
    counts = materialize(word_counts(learn))
    ends = learn.select(F.lit(1)).count()
    words, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    n, v = words + ends, distinct + (1 if ends else 0)
    head = head_of(counts, head_words)
    # tokens and distinct words of each bucket: all but the modelled words, joined away as a small table of words
    modelled = head[:vocabulary]
    known = spark.createDataFrame([(w,) for w, _ in modelled], "word string")
    of_bucket = F.pmod(F.crc32(F.encode("word", "UTF-8")), F.lit(BUCKETS)).cast("int")
    rest = counts.join(F.broadcast(known), "word", "left_anti").groupBy(of_bucket.alias("b")).agg(F.sum("c").alias("c"), F.count("*").alias("d")).collect()
    tokens_in, words_in = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for r in rest:
        tokens_in[r["b"]], words_in[r["b"]] = r["c"], r["d"]
    unigram = np.concatenate([[c for _, c in modelled], [ends], tokens_in]) + 0.5
    unigram /= unigram.sum()
    log_count = np.log10(np.array([c for _, c in head] + [0], dtype=np.float64) + 1)
    share = np.log10(tokens_in + words_in + 1)
    shared = spark.sparkContext.broadcast({"key": uuid.uuid4().hex, "words": [w for w, _ in head], "contexts": contexts, "modelled": vocabulary})  # at most head_words
    trained = train(learn, shared, unigram, n)
    model = spark.sparkContext.broadcast((trained, normaliser(trained), log_count, share))  # (vocabulary + BUCKETS) * DIM + contexts ** 2 numbers

    def run(batches):
        voc, (m, z, logc, inside) = _vocabulary(shared), model.value
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                some = batch.slice(at, 256)
                out = {k: [] for k in ("n", "known", "head", "lm", "rare")}
                for x in some.column(2):
                    w = tokens(x.as_py())
                    place, target, context = voc.number(w)
                    far, near, to = voc.runs(target, context)
                    bucket = to[to > voc.end] - voc.end - 1
                    out["n"].append(len(w) + 1)
                    out["known"].append(int((place >= 0).sum()) + (1 if ends else 0))
                    out["head"].append(float(logc[place[place >= 0]].sum()))
                    # of a bucket's word the share within is (its count + 1) over all of the bucket; counts beyond the head are joined
                    lm = sum(float(log10_of(m, z, far[i : i + 65536], near[i : i + 65536], to[i : i + 65536]).sum(dtype=np.float64)) for i in range(0, len(to), 65536))
                    out["lm"].append(lm - float(inside[bucket].sum()) + float(logc[place[place >= voc.end]].sum()))
                    out["rare"].append([w[k].decode("utf-8", "surrogatepass") for k in np.flatnonzero(place < 0)])
                arrays = [pa.array(out["n"], pa.int64()), pa.array(out["known"], pa.int64()), pa.array(out["head"]), pa.array(out["lm"]), pa.array(out["rare"], pa.list_(pa.string()))]
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), *arrays], names=["id", "held_out", *out])

    kind = dict(part.dtypes)["id"]
    fields = f"id {kind}, held_out boolean, n bigint, known bigint, head double, lm double, rare array<string>"
    # numbered as written: the number is stored, so it is the same in every later read
    base = materialize(part.mapInArrow(run, fields).withColumn("row", F.monotonically_increasing_id()))
    rare = base.select("row", F.explode_outer("rare").alias("word")).filter(F.col("word").isNotNull()).groupBy("row", "word").agg(F.count("*").alias("k"))
    found = rare.join(counts, "word")  # a word that was never learnt adds nothing: log10(0 + 1)
    tail = found.groupBy("row").agg(F.sum(F.col("k") * F.log10(F.col("c") + 1)).alias("tail"), F.sum("k").alias("tail_known"))
    all_ = base.drop("rare").join(tail, "row", "left")
    tail_sum, tail_known = F.coalesce("tail", F.lit(0.0)), F.coalesce("tail_known", F.lit(0))
    ended = math.log10(ends + 1)
    return all_.select(
        F.col("id").alias(id_col), "held_out", F.col("n").alias("n_tokens"), (F.col("known") + tail_known).alias("n_known"), F.lit(n).cast("bigint").alias("train_tokens"),
        (F.col("head") + ended + tail_sum - F.col("n") * math.log10(n + v + 1)).alias("base_score"),
        (F.col("lm") + tail_sum).alias("score"),
    )
