"""Quality by attention-based multiple-instance learning.

A document is a bag of passages; only the bag has a label. Every passage of the whole text is encoded
(statistics of its bytes and words, hashed word buckets, one hidden layer), a gated attention decides
how much each passage counts, and the weighted sum of the passages' codes gives the score. Encoder,
attention and output are trained together on document labels alone, in numpy.

Labels come from a bounded sample of labelled documents, chosen by a hash of the id (``max_docs``);
everything else is one pass over the documents without a shuffle."""

from __future__ import annotations

import zlib
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import fold_bucket, materialize

PASSAGE_WORDS = 96
BUCKETS = 32
# Classes of bytes; any other ASCII mark is the last class.
BYTE_CLASSES = (b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" ", b"\t\n\v\f\r", b".", b",;:", b"!?", b"'\"()[]{}", b"|", b"#*$%&<>", b"@=/+_-\\~^`")
_OTHER = len(BYTE_CLASSES)
_TABLE = np.full(256, _OTHER, dtype=np.int64)
for _k, _chars in enumerate(BYTE_CLASSES):
    _TABLE[list(_chars)] = _k
_TABLE[0x80:0xC0], _TABLE[0xC0:] = _OTHER + 1, _OTHER + 2
CLASSES = _OTHER + 3
#: Class shares, buckets, word length, distinct words, repeats next to each other, log words,
#: and of the document: repeated lines, log words.
WIDTH = CLASSES + BUCKETS + 6


def encode(text: str | None) -> np.ndarray:
    """Passages of a text as rows of ``WIDTH`` numbers; a text without words is one row of zeros."""
    b = (text or "").encode("utf-8", "surrogatepass")
    w = b.split()
    if not w:
        return np.zeros((1, WIDTH), dtype=np.float32)
    n, size = len(w), PASSAGE_WORDS
    p = -(-n // size)
    raw = np.frombuffer(b, dtype=np.uint8)
    cls = _TABLE[raw]
    space = (cls == 3) | (cls == 4)
    begins = ~space
    begins[1:] &= space[:-1]
    passage = np.maximum(np.cumsum(begins) - 1, 0) // size
    shares = np.bincount(passage * CLASSES + cls, minlength=p * CLASSES).reshape(p, CLASSES).astype(np.float64)
    total = shares.sum(1)
    words = np.full(p, size, dtype=np.float64)
    words[-1] = n - size * (p - 1)
    solid = total - shares[:, 3] - shares[:, 4]
    at = np.arange(0, n, size)
    of = np.repeat(np.arange(p), words.astype(np.int64))
    digest = np.fromiter(map(zlib.crc32, w), dtype=np.int64, count=n)
    hashed = np.bincount(of * BUCKETS + digest % BUCKETS, minlength=p * BUCKETS).reshape(p, BUCKETS)
    again = np.zeros(n)
    again[1:] = np.fromiter(map(eq, w, w[1:]), dtype=np.float64, count=n - 1)
    distinct = np.array([len(set(w[i : i + size])) for i in at])
    lines = [x for x in b.split(b"\n") if x.strip()]
    own = sum(map(len, set(lines)))
    repeated = 1 - own / max(1, sum(map(len, lines)))
    extra = np.stack([solid / words / 10, distinct / words, np.add.reduceat(again, at) / words, np.log1p(words) / 5, np.full(p, repeated), np.full(p, np.log1p(n) / 10)], axis=1)
    return np.hstack([shares / total[:, None], hashed / words[:, None], extra]).astype(np.float32)


def _segments(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
    return np.add.reduceat(x, starts, axis=0)


class AttentionMil:
    """Gated attention over passages. ``fit`` is full-batch Adam on the log loss."""

    def __init__(self, hidden: int = 32, gate: int = 16, seed: int = 7):
        self.hidden, self.gate, self.seed = hidden, gate, seed
        self.p: dict[str, np.ndarray] | None = None
        self.prior = 0.5

    def _forward(self, x, starts, counts, p):
        h = np.tanh(x @ p["W"] + p["b"])
        t, s = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-(h @ p["U"])))
        e = (t * s) @ p["a"]
        top = np.maximum.reduceat(e, starts)
        w = np.exp(e - np.repeat(top, counts))
        w /= np.repeat(_segments(w, starts), counts)
        z = _segments(h * w[:, None], starts)
        logit = np.clip(z @ p["c"] + p["d"][0], -30, 30)
        return h, t, s, w, z, 1 / (1 + np.exp(-logit))

    def fit(self, bags: list[np.ndarray], labels: np.ndarray, steps: int = 400, rate: float = 0.02, decay: float = 1e-4) -> AttentionMil:
        """No labels, or labels of one kind: every score is the prior (one half without labels)."""
        y = np.asarray(labels, dtype=np.float64)
        if len(y):
            self.prior = float((y.sum() + 1) / (len(y) + 2))
        if len(set(y.tolist())) < 2:
            return self
        x = np.concatenate(bags)
        self.mean, self.scale = x.mean(0, dtype=np.float64).astype(np.float32), np.maximum(x.std(0, dtype=np.float64), 1e-3).astype(np.float32)
        x = np.clip((x - self.mean) / self.scale, -8, 8)
        counts = np.array([len(b) for b in bags])
        starts = np.concatenate([[0], np.cumsum(counts)[:-1]])
        r, f = np.random.default_rng(self.seed), x.shape[1]
        p = {"W": r.normal(0, f**-0.5, (f, self.hidden)), "b": np.zeros(self.hidden), "V": r.normal(0, 0.2, (self.hidden, self.gate)), "U": r.normal(0, 0.2, (self.hidden, self.gate)), "a": r.normal(0, 0.2, self.gate), "c": r.normal(0, 0.2, self.hidden), "d": np.array([np.log(self.prior / (1 - self.prior))])}
        p = {k: q.astype(np.float32) for k, q in p.items()}
        y = y.astype(np.float32)
        m, v = ({k: np.zeros_like(q) for k, q in p.items()} for _ in range(2))
        for step in range(1, steps + 1):
            h, t, s, w, z, out = self._forward(x, starts, counts, p)
            g = (out - y) / len(y)
            gz = g[:, None] * p["c"]
            gzr = np.repeat(gz, counts, axis=0)
            gw = (gzr * h).sum(1)
            ge = w * (gw - np.repeat(_segments(w * gw, starts), counts))
            gt = ge[:, None] * p["a"]
            gs_, gt_ = gt * t * s * (1 - s), gt * s * (1 - t * t)
            gh = (gzr * w[:, None] + gt_ @ p["V"].T + gs_ @ p["U"].T) * (1 - h * h)
            grad = {"W": x.T @ gh, "b": gh.sum(0), "V": h.T @ gt_, "U": h.T @ gs_, "a": (ge[:, None] * t * s).sum(0), "c": z.T @ g, "d": np.array([g.sum()])}
            lr = np.float32(rate * 0.5 * (1 + np.cos(np.pi * step / (steps + 1))))
            for k in p:
                q = np.asarray(grad[k], dtype=np.float32) + (decay * p[k] if k not in "bd" else 0)
                m[k] = 0.9 * m[k] + 0.1 * q
                v[k] = 0.999 * v[k] + 0.001 * q * q
                p[k] -= lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        self.p = p
        return self

    def score(self, bags: list[np.ndarray]) -> np.ndarray:
        if self.p is None:
            return np.full(len(bags), self.prior)
        x = np.clip((np.concatenate(bags) - self.mean) / self.scale, -8, 8)
        counts = np.array([len(b) for b in bags])
        return self._forward(x, np.concatenate([[0], np.cumsum(counts)[:-1]]), counts, self.p)[-1].astype(np.float64)


def labelled_sample(docs: DataFrame, labels: DataFrame, id_col: str, text: str, label: str, folds: int, max_docs: int, max_passages: int) -> tuple[list[np.ndarray], np.ndarray]:
    """Encoded passages and labels of about ``max_docs`` labelled documents outside fold 0, the ones
    of least hash, as far as they have ``max_passages`` in all: so much the driver may hold, however long the
    texts. Labels that are null or contradict each other are left out."""
    pure = labels.select(F.col(id_col).alias("id"), F.col(label).cast("int").alias("y")).filter("id is not null and y is not null")
    pure = pure.filter(fold_bucket(F.col("id"), folds) != 0).groupBy("id").agg(F.min("y").alias("y"), F.max("y").alias("y2")).filter("y = y2").select("id", "y")
    n = pure.count()
    if not n:
        return [], np.array([])
    cells = 1 << 20
    some = pure.filter(F.pmod(F.xxhash64("id"), F.lit(cells)) < max(1, int(cells * min(1.0, max_docs / n))))
    if some.count() > 2 * max_docs:  # holds for any spread of hashes; checked since it is broadcast
        raise ValueError("the labelled sample is larger than twice its bound")
    part = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text}`").alias("t")).join(F.broadcast(some), "id").select("id", "y", "t")

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 256):
                some = b.slice(at, 256)
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), pa.array([encode(x.as_py()).tobytes() for x in some.column(2)], pa.binary())], names=["id", "y", "x"])

    rows = materialize(part.mapInArrow(run, "id bigint, y int, x binary"))
    # about max_docs rows, of which only the lengths are ordered in one task
    sizes = rows.select("id", (F.length("x") / (4 * WIDTH)).cast("bigint").alias("n")).groupBy("id").agg(F.sum("n").alias("n"))
    upto = F.sum("n").over(Window.orderBy(F.xxhash64("id"), "id").rowsBetween(Window.unboundedPreceding, 0))
    fits = sizes.withColumn("upto", upto).filter(F.col("upto") <= max_passages).select("id")
    rows = rows.join(fits, "id", "left_semi").select("id", "y", "x").collect()
    rows.sort(key=lambda r: (r["id"], bytes(r["x"])))
    return [np.frombuffer(bytes(r["x"]), dtype=np.float32).reshape(-1, WIDTH) for r in rows], np.array([r["y"] for r in rows])


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "quality", folds: int = 5, max_docs: int = 4000, max_passages: int = 60_000) -> AttentionMil:
    """The classifier of ``labels`` (id_col, label), learnt from a bounded sample of the labelled documents
    outside fold 0 (``max_docs``, ``max_passages``).

    A document without label, a label without document, null ids and labels and ids with both labels teach
    nothing; null and empty texts are one empty passage; rows repeated in id count as often as they stand.
    Without labels, or with labels of one kind, every score is the prior. Other columns are not read."""
    return AttentionMil().fit(*labelled_sample(docs, labels, id_col, text, label, folds, max_docs, max_passages))


def add_score(docs: DataFrame, model: AttentionMil, text: str = "text", keep: list[str] | None = None, out: str = "score") -> DataFrame:
    """``keep`` (all columns by default) and ``out``: the score, 0 to 1, of every whole text. Null and
    empty texts are one empty passage; long texts are read whole. Repeated rows score alike, null ids are
    carried. A column named ``out``, in any case, is replaced. An empty table gives an empty result."""
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() != out.lower()]
    part = docs.select(*(F.col(f"`{c}`") for c in keep), F.col(f"`{text}`").alias("__text"))
    schema = part.drop("__text").withColumn(out, F.lit(0.0)).schema

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                some = batch.slice(at, 128)
                bags = [encode(x.as_py()) for x in some.column(some.num_columns - 1)]
                yield pa.RecordBatch.from_arrays([*some.columns[:-1], pa.array(model.score(bags))], names=[*some.schema.names[:-1], out])

    return part.mapInArrow(run, schema)
