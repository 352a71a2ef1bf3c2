"""Quality rules: logistic regression over hashed word and character n-grams.

The model is fitted on a bounded sample of labelled documents (`max_train`, the rows of
the lowest seeded hash), calibrated on labelled documents it was not fitted on, and then
scores every document, whole, in Arrow batches; fixed thresholds turn the probability of
being good into a verdict.

Features: byte n-grams of 1 to 4, words and word pairs, each hashed into one weight table
and counted as a share of the n-grams of that family in the document. Upper and lower
case, punctuation and layout are kept, as they tell much about quality.

Defined results: a null or blank text has no features, gets a null probability and is
rejected ("empty"); rows are judged each by itself, so ties and repeated rows get equal
verdicts; columns beyond `doc_id` and `text` are ignored by the scorer and kept by the
filter; without labelled documents of both classes (an empty table among others) there is no
model: then no text is rejected but blank ones, and the verdict of the others is "unjudged".
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import _grams as G
from ._linear import logistic, platt, sigmoid

BITS = 18
CHARS = (1, 2, 3, 4)
#: Probability of being good under which a document is rejected, and from which it is accepted without review.
REJECT, ACCEPT = 0.35, 0.80
MAX_TRAIN = 2000


def _word_buckets(h: np.ndarray, bits: int) -> np.ndarray:
    return (h >> np.uint64(64 - bits)).astype(np.int64)


def _pairs(h: np.ndarray) -> np.ndarray:
    """Hashes of neighbouring words; a word followed by itself hashes alike whatever the word."""
    if len(h) < 2:
        return np.zeros(0, np.uint64)
    return np.where(h[:-1] == h[1:], np.uint64(0x5BD1E995A5A5A5A5), G.mix(h[:-1] * np.uint64(31) + h[1:]))


def features(text: str, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Sparse (indices, values) of one text."""
    buf = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
    off = np.array([0, len(buf)])
    parts = [G.bucket(G.byte_grams(buf, n), n, bits).astype(np.int64) for n in CHARS]
    h, _ = G.words(buf, off)
    parts += [_word_buckets(h, bits), _word_buckets(_pairs(h), bits)]
    idx = np.concatenate(parts)
    val = np.concatenate([np.full(len(p), 1 / max(len(p), 1)) for p in parts])
    at, inv = np.unique(idx, return_inverse=True)
    return at.astype(np.int32), (np.bincount(inv, val, len(at)) * 10).astype(np.float32)


def margins(buf: np.ndarray, off: np.ndarray, w: np.ndarray, b: float, bits: int = BITS) -> np.ndarray:
    """Margins of all rows of a byte view, as `features` and the weights give them one by one."""
    z = np.full(len(off) - 1, b)
    for n in CHARS:
        s, c = G.row_sums(w[G.bucket(G.byte_grams(buf, n), n, bits)], off, n)
        z += 10 * s / np.maximum(c, 1)
    h, wo = G.words(buf, off)
    for n, v in ((1, h), (2, _pairs(h))):
        s, c = G.row_sums(w[_word_buckets(v, bits)], wo, n)
        z += 10 * s / np.maximum(c, 1)
    return z


def sample_rows(docs: DataFrame, labels: DataFrame, target: str, max_train: int, seed: int) -> DataFrame:
    """(doc_id, text, y) of at most `max_train` labelled documents, those of the lowest seeded hash; a document labelled both ways is left out."""
    y = labels.where(F.col("doc_id").isNotNull() & F.col(target).isin(0, 1)).groupBy("doc_id").agg(F.min(target).alias("y"), F.max(target).alias("y2")).where("y = y2")
    picked = y.orderBy(F.xxhash64(F.col("doc_id"), F.lit(seed)), "doc_id").limit(max_train).select("doc_id", "y")
    return docs.select("doc_id", "text").where("length(trim(text)) > 0").join(F.broadcast(picked), "doc_id").select("doc_id", "text", F.col("y").cast("int").alias("y"))


def distinct_sample(rows: list[tuple]) -> list[tuple[str, int]]:
    """(text, y) of sampled rows (doc_id, text, y) in order of doc_id; of rows of one doc_id the first text."""
    seen: dict = {}
    for i, text, y in sorted(rows):
        seen.setdefault(i, (text, y))
    return list(seen.values())


def fit_rows(rows: list[tuple[str, int]], bits: int = BITS) -> dict | None:
    """Model of (text, y) rows: weights, intercept and calibration (a, b); None without four rows of both classes. Every fourth row of a class is kept for calibration."""
    y = np.array([r[1] for r in rows], float)
    if len(rows) < 4 or y.min() == y.max():
        return None
    held = np.zeros(len(rows), bool)
    for c in (0, 1):
        held[np.flatnonzero(y == c)[3::4]] = True
    x = [features(r[0], bits) for r in rows]
    kept_out = [r for r, h in zip(x, held) if h]
    train = [r for r, h in zip(x, held) if not h]
    del x, rows
    w, b = logistic(train, y[~held], 1 << bits)
    if held.any() and y[held].min() < y[held].max():
        z = np.array([(v * w[i]).sum() + b for i, v in kept_out])
        a, c = platt(z, y[held])
    else:
        a, c = 1.0, 0.0
    return {"w": w, "b": b, "a": a, "c": c, "bits": bits}


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", max_train: int = MAX_TRAIN, seed: int = 7, bits: int = BITS) -> dict | None:
    """Model fitted on the bounded sample, in one task: only the weights come to the driver."""

    def run(batches):
        rows = [t for b in batches for t in zip(*(c.to_pylist() for c in b.columns))]
        m = fit_rows(distinct_sample(rows), bits)
        if m is None:
            return
        yield pa.RecordBatch.from_arrays([pa.array([m["w"].tobytes()], pa.binary()), *[pa.array([float(m[k])]) for k in ("b", "a", "c")]], ["w", "b", "a", "c"])

    got = sample_rows(docs, labels, target, max_train, seed).repartition(1).mapInArrow(run, "w binary, b double, a double, c double").collect()
    if not got:
        return None
    m = got[0]
    return {"w": np.frombuffer(m["w"], np.float32), "b": m["b"], "a": m["a"], "c": m["c"], "bits": bits}


def _probability(buf: np.ndarray, off: np.ndarray, m: dict) -> np.ndarray:
    return sigmoid(m["a"] * margins(buf, off, m["w"], m["b"], m["bits"]) + m["c"])


def score(docs: DataFrame, model: dict | None, reject: float = REJECT, accept: float = ACCEPT) -> DataFrame:
    """(doc_id, probability, verdict, kept) of every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = held.value
        for batch in batches:
            for part in G.chunks(batch, "text"):
                buf, off = G.view(part.column(1))
                _, wo = G.words(buf, off)
                empty = np.diff(wo) == 0
                p = _probability(buf, off, m) if m else np.zeros(len(empty))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(p, mask=empty if m else np.ones(len(empty), bool)), pa.array(empty)], ["doc_id", "probability", "blank"])

    scored = docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, probability double, blank boolean")
    p = F.col("probability")
    verdict = F.when(F.col("blank"), "empty").when(p.isNull(), "unjudged").when(p < reject, "reject").when(p < accept, "review").otherwise("accept")
    return scored.select("doc_id", "probability", verdict.alias("verdict"), (~F.col("blank") & F.coalesce(p >= reject, F.lit(True))).alias("kept"))


def keep_good(docs: DataFrame, model: dict | None, reject: float = REJECT) -> DataFrame:
    """The rows of `docs` that are not rejected, all columns, in one narrow pass."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    schema = docs.schema
    at = schema.fieldNames().index("text")

    def run(batches):
        m = held.value
        for batch in batches:
            for part in G.chunks(batch, "text"):
                buf, off = G.view(part.column(at))
                _, wo = G.words(buf, off)
                good = _probability(buf, off, m) >= reject if m else True
                yield part.filter(pa.array((np.diff(wo) > 0) & good))

    return docs.mapInArrow(run, schema)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return score(docs, fit(docs, labels))
