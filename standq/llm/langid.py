"""Language identification by nearest centroid: normalised TF-IDF character n-grams, several centroids a language."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, ship, staged, texts
from .quality_mil import fold
from .simhash import typed

#: Hashed n-gram classes; documents that training reads at most in all and of one language; centroids of a language.
DIM, TRAIN_ALL, TRAIN_EACH, CENTROIDS = 2048, 6000, 1200, 4
#: Documents that every language has in the sample at least (all, if it has fewer).
TRAIN_LEAST = 6
LETTER = re.compile(r"[^\W\d_]")
#: ASCII letters and bytes of non-ASCII characters stay, all else is a blank.
TABLE = bytes(b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def grams(text: str) -> np.ndarray:
    """Counts of hashed byte n-grams of one to three of the lower-cased whole text."""
    raw = b" " + b" ".join(text.lower().encode("utf-8", "surrogatepass").translate(TABLE).split()) + b" "
    x = np.frombuffer(raw, np.uint8).astype(np.uint32)
    two = x[:-1] * np.uint32(0x9E3779B1) + x[1:]
    three = two[:-1] * np.uint32(0x85EBCA77) + x[2:] * np.uint32(0xC2B2AE3D)
    out = np.zeros(DIM, np.int64)
    for h in (x * np.uint32(0x27D4EB2F), two * np.uint32(0x165667B1), three):
        out += np.bincount((h ^ (h >> np.uint32(15))) % np.uint32(DIM), minlength=DIM)
    return out


def normal(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def spherical_means(x: np.ndarray, k: int, seed: int = 3, rounds: int = 12) -> np.ndarray:
    rng = np.random.default_rng(seed)
    centers = x[rng.choice(len(x), min(k, len(x)), replace=False)]
    for _ in range(rounds):
        own = (x @ centers.T).argmax(axis=1)
        sums = np.stack([x[own == c].sum(axis=0) if (own == c).any() else centers[c] for c in range(len(centers))])
        centers = normal(sums)
    return centers


class Centroids:
    def __init__(self, idf: np.ndarray, languages: list[str], owners: np.ndarray, centers: np.ndarray, least: np.ndarray):
        self.idf, self.languages, self.owners, self.centers, self.least = idf, languages, owners, centers, least

    @staticmethod
    def vectors(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
        return normal(np.log1p(counts) * idf).astype(np.float32)

    @classmethod
    def fit(cls, counts: np.ndarray, langs: list[str], seen: np.ndarray | None = None, n: int = 0) -> Centroids:
        """``seen``: in how many of ``n`` documents each n-gram class occurs; by default in those of ``counts``."""
        if seen is None:
            seen, n = (counts > 0).sum(axis=0), len(counts)
        idf = np.log((1 + n) / (1 + seen)) + 0.2
        x, names, owners, centers, least = cls.vectors(counts, idf), sorted(set(langs)), [], [], []
        for i, name in enumerate(names):
            own = x[[k for k, v in enumerate(langs) if v == name]]
            c = spherical_means(own, CENTROIDS)
            centers.append(c)
            owners += [i] * len(c)
            near = (own @ c.T).max(axis=1)
            least.append(max(0.0, np.quantile(near, 0.01) - 0.15))
        return cls(idf, names, np.array(owners, np.int64), np.concatenate(centers) if centers else np.zeros((0, DIM), np.float32), np.array(least))

    def predict(self, counts: np.ndarray) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Nearest language, cosine (0 to 1), and whether it is too far from every centroid."""
        if not self.languages:
            return ["und"] * len(counts), np.zeros(len(counts)), np.ones(len(counts), bool)
        near = self.vectors(counts, self.idf) @ self.centers.T.astype(np.float32)
        best = near.argmax(axis=1)
        cosine, lang = np.clip(near[np.arange(len(near)), best].astype(np.float64), 0, 1), self.owners[best]
        return [self.languages[i] for i in lang], cosine, cosine < self.least[lang]


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Centroids:
    """Fit on documents with a language outside the held-out quarter.

    Centroids come from a sample: of every language about the same number of documents, at most about ``TRAIN_EACH``, and
    all about ``TRAIN_ALL``, but never less than ``TRAIN_LEAST`` of one; chosen by hash of identifier and text. So with
    very many languages the sample grows with their number, and no language is left out. Document frequencies are counted
    over all learnable documents.
    """
    known = docs.select(F.col(f"`{id_col}`").alias("k"), F.col(f"`{text_col}`").alias("t"), F.col(f"`{lang_col}`").alias("lang"))
    known = known.filter(F.col("lang").isNotNull() & F.col("t").isNotNull() & (F.coalesce(fold("k", 4), F.lit(0)) != 2))
    sizes = known.groupBy("lang").agg(F.count("*").alias("n"))
    many = sizes.count()
    if not many:
        return Centroids.fit(np.zeros((0, DIM)), [])
    each = max(TRAIN_LEAST, min(TRAIN_EACH, TRAIN_ALL // many))
    place = F.pmod(F.xxhash64("k", "t"), F.lit(1_000_003)) / 1_000_003.0
    share = F.least(F.lit(1.0), F.lit(float(each)) / F.col("n"))
    own = known.join(F.broadcast(sizes) if many <= 100_000 else sizes, "lang").withColumn("chosen", place < share)

    def run(batches):
        seen, n = np.zeros(DIM, np.int64), 0
        for batch in batches:
            out: dict[str, list] = {"lang": [], "k": [], "c": []}
            for k, t, lang, chosen in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                counts = grams(t)
                seen += counts > 0
                n += 1
                if chosen:
                    out["lang"].append(lang)
                    out["k"].append(k)
                    out["c"].append(np.minimum(counts, 65535).astype("<u2").tobytes())
            if out["lang"]:
                yield pa.RecordBatch.from_pydict({**out, "n": [0] * len(out["k"])})
        if n:  # frequencies of the task, on a row without a language
            yield pa.RecordBatch.from_pydict({"lang": [None], "k": [None], "c": [seen.astype("<u8").tobytes()], "n": [n]})

    kinds = "lang string, k string, c binary, n long"
    got = own.select(F.col("k").cast("string"), "t", "lang", "chosen").mapInArrow(typed(run, kinds), kinds)
    made = staged(got, "grams")
    counted = np.zeros(DIM, np.int64)
    cells = made.filter("lang is null").select("n", "c")

    def add(batches):
        total, n = np.zeros(DIM, np.int64), 0
        for batch in batches:
            for m, c in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                total, n = total + np.frombuffer(c, "<u8").astype(np.int64), n + m
        if n:
            yield pa.RecordBatch.from_pydict({"n": [n], "c": [total.tobytes()]})

    few = cells.repartition(max(1, min(64, spark_partitions(cells) // 16))).mapInArrow(typed(add, "n long, c binary"), "n long, c binary").collect()  # 64 rows at most
    n = sum(r.n for r in few)
    for r in few:
        counted += np.frombuffer(bytes(r.c), np.int64)
    rows = made.filter("lang is not null").select("lang", "k", "c").collect()  # at most ``each`` documents a language
    rows.sort(key=lambda r: (r.lang, str(r.k), bytes(r.c)))
    counts = np.array([np.frombuffer(bytes(r.c), "<u2") for r in rows]).reshape(-1, DIM)
    return Centroids.fit(counts, [r.lang for r in rows], counted, n)


def spark_partitions(df: DataFrame) -> int:
    return len(df.inputFiles())


FOUND = [
    T.StructField("nearest_lang", T.StringType()),
    T.StructField("similarity", T.DoubleType()),
    T.StructField("rejected", T.BooleanType()),
    T.StructField("detected_lang", T.StringType()),
]


def identify(docs: DataFrame, model: Centroids, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``docs`` with nearest_lang, similarity (cosine, 0 to 1), rejected (farther from every centroid than the language's
    training texts) and detected_lang (``und`` if rejected). Null texts and texts without a letter are ``und``, 0, true."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # some hundred thousand numbers

    def start():
        def work(batch: pa.RecordBatch) -> dict[str, list]:
            whole = texts(batch, text_col)
            lettered = [bool(LETTER.search(t)) for t in whole]
            lang, cosine, far = ["und"] * len(whole), np.zeros(len(whole)), np.ones(len(whole), bool)
            own = [i for i, ok in enumerate(lettered) if ok]
            for at in range(0, len(own), 256):
                part = own[at : at + 256]
                a, b, c = held.value.predict(np.array([grams(whole[i]) for i in part]))
                for i, name in zip(part, a, strict=True):
                    lang[i] = name
                cosine[part], far[part] = b, c
            return {"nearest_lang": lang, "similarity": cosine, "rejected": far, "detected_lang": ["und" if f else n for n, f in zip(lang, far, strict=True)]}

        return work

    return annotate(docs, start, FOUND, [text_col], keep)


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    out = identify(docs, train(docs), keep=["doc_id"])
    return out.select("doc_id", F.coalesce(fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), F.col("nearest_lang").alias("lang_pred"), F.col("similarity").alias("score"), "rejected")
