"""Compression classifier: a good and a bad zstandard dictionary judge each text.

Two dictionaries are trained on labelled good and bad documents (a bounded sample,
`max_train`). A text is compressed, whole, with each; the difference of the compressed
sizes per byte of text, bad minus good, says which dictionary knows it better, and a
logistic calibration on held-out labelled rows turns the difference into a score.

A text is compressed in consecutive blocks of `BLOCK` bytes, each on its own with the
dictionary, so that the dictionary counts as much in a long text as in a short one; the
blocks cover the text to its end.

Defined results: null and empty texts get a null difference and score and are not kept;
rows are scored each by itself (repeated rows get equal scores); where the sample has not two
texts of both classes (an empty table among others) there is no model: then the difference and
score are null throughout and every text that is not empty is kept; columns beyond `doc_id` and
`text` play no part.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard as zstd
from pyspark.sql import DataFrame, SparkSession

from . import _grams as G
from ._linear import platt, sigmoid
from .quality_rules import distinct_sample, sample_rows

LEVEL = 3
BLOCK = 1024
DICT_BYTES = 512 * 1024
#: Bytes of the typical difference added to every text: a few bytes alone prove nothing.
PSEUDO = 64
MAX_TRAIN = 2000
#: Score from which a text is kept.
KEEP_FROM = 0.4


def _train(texts: list[bytes], dict_bytes: int) -> zstd.ZstdCompressionDict:
    """Dictionary of `texts`; where they are too few for the trainer, their plain concatenation."""
    samples = [t[i : i + BLOCK] for t in texts for i in range(0, len(t), BLOCK)]
    size = min(dict_bytes, max(256, sum(map(len, samples)) // 8))
    try:
        return zstd.train_dictionary(size, samples, level=LEVEL)
    except zstd.ZstdError:
        return zstd.ZstdCompressionDict(b"".join(samples)[-dict_bytes:], dict_type=zstd.DICT_TYPE_RAWCONTENT)


class Pair:
    """The two compressors over dictionaries given as bytes."""

    def __init__(self, good: bytes, bad: bytes, raw: tuple[bool, bool] = (False, False)):
        self.c = []
        for data, is_raw in zip((good, bad), raw):
            d = zstd.ZstdCompressionDict(data, dict_type=zstd.DICT_TYPE_RAWCONTENT if is_raw else zstd.DICT_TYPE_AUTO)
            d.precompute_compress(level=LEVEL)
            self.c.append(zstd.ZstdCompressor(dict_data=d, level=LEVEL, write_content_size=False, write_checksum=False, write_dict_id=False))

    def difference(self, data, typical: float = 0.0) -> float:
        """(size with the bad dictionary - size with the good one) / bytes, as if `PSEUDO` bytes more had shown the typical difference."""
        n = len(data)
        good, bad = (sum(len(c.compress(data[i : i + BLOCK])) for i in range(0, n, BLOCK)) for c in self.c)
        return (bad - good + PSEUDO * typical) / (n + PSEUDO)


def fit_rows(rows: list[tuple[bytes, int]], dict_bytes: int = DICT_BYTES) -> dict | None:
    """Model of (text, y) rows: both dictionaries and the calibration (a, b); every third row of a class is kept for calibration. None without two rows of both classes."""
    side = {c: [t for t, y in rows if y == c] for c in (0, 1)}
    if min(map(len, side.values())) < 2:
        return None
    part = {c: [t for i, t in enumerate(ts) if i % 3 != 2 or len(ts) < 3] for c, ts in side.items()}
    dicts = {c: _train(ts, dict_bytes) for c, ts in part.items()}
    raw = tuple(dicts[c].dict_id() == 0 for c in (1, 0))
    model = {"good": dicts[1].as_bytes(), "bad": dicts[0].as_bytes(), "raw": raw}
    pair = Pair(model["good"], model["bad"], raw)
    model["typical"] = float(np.mean([pair.difference(t) for ts in side.values() for i, t in enumerate(ts) if i % 3 == 2 or len(ts) < 3]))
    held = [(pair.difference(t, model["typical"]), c) for c, ts in side.items() for i, t in enumerate(ts) if i % 3 == 2 or len(ts) < 3]
    d, y = np.array([h[0] for h in held]), np.array([h[1] for h in held], float)
    model["a"], model["b"] = map(float, platt(d, y))
    return model


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", max_train: int = MAX_TRAIN, seed: int = 11, dict_bytes: int = DICT_BYTES) -> dict | None:
    """Model fitted on the bounded sample, in one task: only the dictionaries come to the driver."""

    def run(batches):
        rows = [t for b in batches for t in zip(*(c.to_pylist() for c in b.columns))]
        m = fit_rows([(t.encode("utf-8", "replace"), y) for t, y in distinct_sample(rows)], dict_bytes)
        if m:
            yield pa.RecordBatch.from_arrays([*[pa.array([m[k]], pa.binary()) for k in ("good", "bad")], pa.array([list(m["raw"])], pa.list_(pa.bool_())), *[pa.array([m[k]]) for k in ("typical", "a", "b")]], ["good", "bad", "raw", "typical", "a", "b"])

    got = sample_rows(docs, labels, target, max_train, seed).repartition(1).mapInArrow(run, "good binary, bad binary, raw array<boolean>, typical double, a double, b double").collect()
    if not got:
        return None
    m = got[0].asDict()
    return m | {"good": bytes(m["good"]), "bad": bytes(m["bad"]), "raw": tuple(m["raw"])}


def score(docs: DataFrame, model: dict | None, keep_from: float = KEEP_FROM) -> DataFrame:
    """(doc_id, difference, score, kept) of every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = held.value
        pair = Pair(m["good"], m["bad"], m["raw"]) if m else None
        for batch in batches:
            for part in G.chunks(batch, "text"):
                buf, off = G.view(part.column(1))
                data = buf.tobytes()
                n = np.diff(off)
                if not m:
                    none = pa.nulls(len(n), pa.float64())
                    yield pa.RecordBatch.from_arrays([part.column(0), none, none, pa.array(n > 0)], ["doc_id", "difference", "score", "kept"])
                    continue
                d = np.array([pair.difference(data[a:b], m["typical"]) if b > a else np.nan for a, b in zip(off[:-1], off[1:])])
                p = sigmoid(m["a"] * d + m["b"])
                empty = n == 0
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(d, mask=empty), pa.array(p, mask=empty), pa.array((p >= keep_from) & ~empty)], ["doc_id", "difference", "score", "kept"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, difference double, score double, kept boolean")


def op2_compression_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return score(docs, fit(docs, labels))
