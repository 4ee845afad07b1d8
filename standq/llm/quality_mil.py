"""Quality classifier: attention-based multiple-instance learning over passages.

A document is a bag of passages. Every passage is encoded by a learned layer over its measured features; gated attention
gives each a weight, learned from document labels alone; the weighted sum of encodings is scored.
"""

from __future__ import annotations

from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, free, ship, texts

PASSAGE_BYTES = 800
#: Labelled documents that training reads at most, those of least hash; longer texts than this many bytes are not among them.
TRAIN_DOCS, TRAIN_BYTES = 6000, 1 << 20
#: Passages of a document that training reads at most, evenly spaced (scores read all). So fitting collects at most
#: TRAIN_DOCS * TRAIN_PASSAGES * N_FEATURES * 4 bytes.
TRAIN_PASSAGES = 64
HIDDEN, GATE, STEPS = 20, 10, 260

#: Kinds of bytes: 0 control, then lower, upper, digit, blank, line end, each other ASCII mark by itself, and of other
#: characters the first byte and the bytes after it. Which of them tell anything is learned.
MARKS = [b for b in range(33, 127) if not chr(b).isalnum()]
KINDS = np.zeros(256, np.int64)
KINDS[97:123], KINDS[65:91], KINDS[48:58], KINDS[[32, 9]], KINDS[10] = 1, 2, 3, 4, 5
KINDS[MARKS] = 6 + np.arange(len(MARKS))
KINDS[192:], KINDS[128:192] = 6 + len(MARKS), 7 + len(MARKS)
N_KINDS, N_WORDS = 8 + len(MARKS), 8
N_FEATURES = N_KINDS + N_WORDS


def word_measures(piece: bytes) -> tuple[float, ...]:
    words = piece.split()
    n = len(words)
    if not n:
        return (0.0,) * N_WORDS
    sizes = list(map(len, words))
    mean = sum(sizes) / n
    capital = sum(map(bytes.isupper, words)) / n
    two = list(zip(words, words[1:], strict=False))
    return (
        min(n / 100, 5.0), min(mean / 10, 5.0), len(set(words)) / n, sum(map(eq, words, words[1:])) / n, capital,
        len(set(two)) / len(two) if two else 1.0, sum(s <= 2 for s in sizes) / n, min(max(sizes) / 40, 5.0),
    )


def features(text: str) -> np.ndarray:
    """One row a passage of ``PASSAGE_BYTES`` bytes; an empty text has one passage of zeros."""
    raw = text.encode("utf-8", "surrogatepass")
    if not raw:
        return np.zeros((1, N_FEATURES), np.float32)
    n = -(-len(raw) // PASSAGE_BYTES)
    if n > 1 and len(raw) - (n - 1) * PASSAGE_BYTES < PASSAGE_BYTES // 4:
        n -= 1  # a short end belongs to the last passage
    where = np.minimum(np.arange(len(raw)) // PASSAGE_BYTES, n - 1)
    counts = np.bincount(where * N_KINDS + KINDS[np.frombuffer(raw, np.uint8)], minlength=n * N_KINDS).reshape(n, N_KINDS)
    ends = [*range(PASSAGE_BYTES, n * PASSAGE_BYTES, PASSAGE_BYTES), len(raw)]
    words = [word_measures(raw[k * PASSAGE_BYTES : e]) for k, e in enumerate(ends)]
    share = np.sqrt(counts / counts.sum(axis=1, keepdims=True))
    return np.concatenate([share, np.array(words)], axis=1).astype(np.float32)


class GatedAttention:
    """Encoder, gated attention and scorer, trained by Adam on whole bags."""

    def __init__(self, seed: int = 7):
        rng = np.random.default_rng(seed)
        draw = lambda *s: rng.normal(0, 1 / np.sqrt(s[0]), s)
        self.mean, self.spread = np.zeros(N_FEATURES), np.ones(N_FEATURES)
        self.p = {"E": draw(N_FEATURES, HIDDEN), "e": np.zeros(HIDDEN), "V": draw(HIDDEN, GATE), "U": draw(HIDDEN, GATE), "w": draw(GATE, 1)[:, 0], "c": draw(HIDDEN, 1)[:, 0], "d": np.zeros(1)}
        self.constant: float | None = None

    def forward(self, x: np.ndarray, starts: np.ndarray) -> dict[str, np.ndarray]:
        p, sizes = self.p, np.diff(np.append(starts, len(x)))
        x = np.clip((x - self.mean) / self.spread, -6, 6)
        h = np.tanh(x @ p["E"] + p["e"])
        t, g = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-(h @ p["U"])))
        s = (t * g) @ p["w"]
        s = np.exp(s - np.repeat(np.maximum.reduceat(s, starts), sizes))
        a = s / np.repeat(np.add.reduceat(s, starts), sizes)
        z = np.add.reduceat(a[:, None] * h, starts)
        y = 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["d"][0], -30, 30)))
        return {"x": x, "h": h, "t": t, "g": g, "a": a, "z": z, "y": y, "sizes": sizes}

    def score(self, bags: list[np.ndarray]) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(bags), self.constant)
        starts = np.concatenate(([0], np.cumsum([len(b) for b in bags])[:-1])).astype(np.int64)
        return self.forward(np.concatenate(bags).astype(np.float64), starts)["y"]

    def fit(self, bags: list[np.ndarray], labels: np.ndarray) -> GatedAttention:
        if not len(labels) or labels.min() == labels.max():
            self.constant = float(labels[0]) if len(labels) else 0.5
            return self
        x = np.concatenate(bags).astype(np.float64)
        starts = np.concatenate(([0], np.cumsum([len(b) for b in bags])[:-1])).astype(np.int64)
        self.mean, self.spread = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-3)
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v = {k: np.zeros_like(w) for k, w in self.p.items()}
        for step in range(1, STEPS + 1):
            f = self.forward(x, starts)
            for k, grad in self.gradients(f, starts, labels).items():
                grad = grad + 1e-4 * self.p[k]
                m[k] = 0.9 * m[k] + 0.1 * grad
                v[k] = 0.999 * v[k] + 0.001 * grad**2
                self.p[k] = self.p[k] - 0.03 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        return self

    def gradients(self, f: dict[str, np.ndarray], starts: np.ndarray, labels: np.ndarray) -> dict[str, np.ndarray]:
        p, n = self.p, len(labels)
        dy = (f["y"] - labels) / n
        dz = np.repeat(dy[:, None] * p["c"], f["sizes"], axis=0)
        da = (dz * f["h"]).sum(axis=1)
        ds = f["a"] * (da - np.repeat(np.add.reduceat(f["a"] * da, starts), f["sizes"]))
        dt = ds[:, None] * p["w"] * f["g"] * (1 - f["t"] ** 2)
        dg = ds[:, None] * p["w"] * f["t"] * f["g"] * (1 - f["g"])
        dh = (f["a"][:, None] * dz + dt @ p["V"].T + dg @ p["U"].T) * (1 - f["h"] ** 2)
        return {
            "E": f["x"].T @ dh, "e": dh.sum(axis=0), "V": f["h"].T @ dt, "U": f["h"].T @ dg, "w": (f["t"] * f["g"]).T @ ds,
            "c": f["z"].T @ dy, "d": np.array([dy.sum()]),
        }


def fold(c: str = "doc_id", folds: int = 3):
    return F.crc32(F.col(f"`{c}`").cast("string").cast("binary")) % folds


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = TRAIN_DOCS) -> GatedAttention:
    """Fit on at most ``most`` labelled documents outside the held-out third, those of least hash of identifier, and on at
    most ``TRAIN_PASSAGES`` passages of each, evenly spaced.

    Labels other than 0 and 1, and documents labelled both ways, are left out. Without both labels the score is constant.
    """
    known = labels.select(F.col("doc_id").alias("k"), F.col("quality").alias("q")).filter(F.col("q").isin(0, 1) & F.col("k").isNotNull())
    known = known.groupBy("k").agg(F.min("q").alias("q"), F.max("q").alias("other")).filter("q = other").select("k", "q")
    chosen = known.filter(fold("k") != 1).orderBy(F.xxhash64("k"), "k").limit(most)
    rows = docs.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{text_col}`").alias("t")).filter(F.octet_length("t") <= TRAIN_BYTES)
    rows = rows.join(F.broadcast(chosen), "k")  # at most ``most`` pairs of numbers
    # repeated identifiers make more rows than labels: ``most`` of them, again those of least hash, and so many passages
    rows = rows.orderBy(F.xxhash64("k", "t"), "k").limit(most)

    def start():
        def work(batch):
            found = [features(t) for t in texts(batch, "t")]
            return {"f": [x[np.linspace(0, len(x) - 1, min(len(x), TRAIN_PASSAGES)).astype(int)].tobytes() for x in found]}

        return work

    got = annotate(rows, start, [T.StructField("f", T.BinaryType())], ["t"], ["k", "q"]).collect()  # at most ``most`` bags
    got.sort(key=lambda r: (r.k, bytes(r.f)))
    bags = [np.frombuffer(bytes(r.f), np.float32).reshape(-1, N_FEATURES) for r in got]
    return GatedAttention().fit(bags, np.array([r.q for r in got], np.float64))


def score(docs: DataFrame, model: GatedAttention, text_col: str = "text", out: str = "score", keep: list[str] | None = None) -> DataFrame:
    """``docs`` with the chance of label 1 of every whole text. Null counts as empty, which is scored too."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # some thousand numbers

    def start():
        def work(batch: pa.RecordBatch) -> dict[str, list]:
            return {out: held.value.score([features(t) for t in texts(batch, text_col)])}

        return work

    return annotate(docs, start, [T.StructField(out, T.DoubleType())], [text_col], keep)


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without those scored under 0.5; columns as they were."""
    ship(docs.sparkSession)
    out = free(docs, "_quality")
    scored = score(docs, train(docs, labels), out=out)
    return scored.filter(F.col(out) >= 0.5).select(*(F.col(f"`{c}`") for c in docs.columns))


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    out = score(docs, model, keep=["doc_id"])
    return out.select("doc_id", F.coalesce(fold() == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
