"""Language identification with string kernels.

The blended-spectrum presence kernel of two texts counts the distinct byte n-grams of
lengths 1 to `P` that both contain, divided by the root of the product of their own
counts. Nyström landmarks (labelled texts, equally many of each language) approximate it:
a text is described by its kernel values with the landmarks, and one-versus-rest kernel
ridge regression on that description gives one score per language. `ROWS` texts at a time
are scored by one product of their 0/1 n-gram matrix with that of the landmarks times the
regression weights, which the model holds multiplied out.

The fit takes a bounded sample of labelled rows (`per_language`, those of the lowest
seeded hash of each language); scoring reads every text whole. N-grams are hashed to
2**BITS places.

Defined results: a null, empty or letterless text is "und" with null scores; languages
outside the fit are never named; ties go to the language first in order of name; repeated
rows get equal results; without any labelled row the result is "und" throughout; columns
beyond `doc_id`, `text` and the label are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import _grams as G

BITS = 18
P = 4
PER_LANGUAGE = 120
LANDMARKS = 40
RIDGE = 1e-2
#: Texts scored by one product.
ROWS = 64


def spectra(buf: np.ndarray, off: np.ndarray, mark: np.ndarray, bits: int = BITS, p: int = P) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of each distinct hashed n-gram of each text of a byte view; rows in no order.

    `mark` has a cell for every row and place and needs no clearing: of the positions that
    write to one cell, the one that is read back from it stands for all.
    """
    row = np.repeat(np.arange(len(off) - 1, dtype=np.int64) << bits, np.diff(off))
    end = np.repeat(off[1:], np.diff(off))
    rows = []
    for k in range(1, p + 1):
        g = G.bucket(G.byte_grams(buf, k), k, bits)
        at = (row[: len(g)] + g)[np.arange(len(g)) + k <= end[: len(g)]]
        rows.append(at)
    at = np.concatenate(rows)
    number = np.arange(len(at), dtype=np.int32)
    mark[at] = number
    at = at[mark[at] == number]
    return at >> bits, at & ((1 << bits) - 1)


def presence(buf: np.ndarray, off: np.ndarray, bits: int = BITS, p: int = P) -> np.ndarray:
    """0/1 matrix, rows by hashed n-grams, of the texts of a byte view."""
    x = np.zeros((len(off) - 1, 1 << bits), bool)
    x[spectra(buf, off, np.empty(x.size, np.int32), bits, p)] = True
    return x


def kernel(x: np.ndarray, z: np.ndarray, zn: np.ndarray, xn: np.ndarray | None = None) -> np.ndarray:
    """Normalised kernel of presence rows x with landmark rows z; the roots of the rows' own counts are xn and zn."""
    xn = np.sqrt(np.maximum(x.sum(1), 1)) if xn is None else xn
    return (x.astype(np.float32) @ z.astype(np.float32).T) / xn[:, None] / zn[None]


def _bytes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    return G.view(G.lowered(pa.array(texts, pa.large_string())))


def fit_rows(rows: list[tuple[str, str]], landmarks: int = LANDMARKS, bits: int = BITS, ridge: float = RIDGE) -> dict | None:
    """Model from (text, language) rows, the first `landmarks` of each language being the landmarks.

    The product with the landmarks and the one with the regression weights are both linear in
    the 0/1 row of a text, so the model keeps their product: for each n-gram of a landmark
    (`places`) one weight a language (`v`).
    """
    langs = sorted({lang for _, lang in rows})
    if not langs:
        return None
    first: list[int] = []
    for lang in langs:
        first += [i for i, r in enumerate(rows) if r[1] == lang][:landmarks]

    def blocks(which: list[int]):
        for i in range(0, len(which), 32):
            yield presence(*_bytes([rows[j][0] for j in which[i : i + 32]]), bits)

    z = np.concatenate(list(blocks(first)))
    zn = np.sqrt(np.maximum(z.sum(1), 1))
    places = np.flatnonzero(z.any(0))
    z = z[:, places]
    kzz = kernel(z, z, zn, zn).astype(np.float64)
    vals, vecs = np.linalg.eigh((kzz + kzz.T) / 2)
    keep = vals > 1e-6 * vals.max()
    root = vecs[:, keep] / np.sqrt(vals[keep])
    phi = np.concatenate([kernel(x[:, places], z, zn, np.sqrt(np.maximum(x.sum(1), 1))) for x in blocks(list(range(len(rows))))]).astype(np.float64) @ root
    y = np.array([[1.0 if r[1] == lang else -1.0 for lang in langs] for r in rows])
    phi1 = np.hstack([phi, np.ones((len(phi), 1))])
    # each language weighs the same, however many rows it has
    share = np.array([1 / sum(q[1] == r[1] for q in rows) for r in rows])
    lhs = (phi1 * share[:, None]).T @ phi1 + ridge * np.eye(phi1.shape[1])
    beta = np.linalg.solve(lhs, (phi1 * share[:, None]).T @ y)
    w = (root @ beta[:-1]) / zn[:, None]
    return {"langs": langs, "places": places.astype(np.int32), "v": (z.T.astype(np.float32) @ w.astype(np.float32)), "b": beta[-1].astype(np.float32), "bits": bits}


def scores(buf: np.ndarray, off: np.ndarray, m: dict, mark: np.ndarray, column: np.ndarray) -> np.ndarray:
    """Scores of the texts of a byte view, rows by languages; column: the model's column of each place, or -1."""
    row, place = spectra(buf, off, mark, m["bits"])
    n = len(off) - 1
    own = np.sqrt(np.maximum(np.bincount(row, minlength=n), 1))
    at = column[place]
    x = np.zeros((n, len(m["places"])), np.float32)
    x[row[at >= 0], at[at >= 0]] = 1
    return ((x @ m["v"]) / own[:, None] + m["b"]).astype(np.float64)


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE, seed: int = 5, label: str = "lang", **kw) -> dict | None:
    """Model fitted on `per_language` labelled rows of each language."""
    ids = docs.where(F.col(label).isNotNull() & (F.length(F.trim("text")) > 0)).select("doc_id", label, F.xxhash64(F.col("doc_id"), F.lit(seed)).alias("h"))
    # Spark limits each partition to its first rows before the exchange (WindowGroupLimit)
    w = Window.partitionBy(label).orderBy("h", "doc_id")
    picked = ids.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= per_language).select("doc_id", F.col("rank"))
    rows = docs.select("doc_id", "text", label).where("length(trim(text)) > 0").join(F.broadcast(picked), "doc_id").select("text", F.col(label).cast("string").alias("lang"), "rank", F.col("doc_id").cast("string").alias("id"))

    def run(batches):
        got = sorted((t for b in batches for t in zip(*(c.to_pylist() for c in b.columns))), key=lambda t: (t[2], t[1], t[3], t[0]))
        m = fit_rows([(t[0], t[1]) for t in got], **kw)
        if m:
            yield pa.RecordBatch.from_arrays([pa.array([m["langs"]], pa.list_(pa.string())), *[pa.array([m[k].tobytes()], pa.binary()) for k in ("places", "v", "b")], pa.array([m["bits"]], pa.int32())], ["langs", "places", "v", "b", "bits"])

    # one task fits, and the weights alone come to the driver
    got = rows.repartition(1).mapInArrow(run, "langs array<string>, places binary, v binary, b binary, bits int").collect()
    if not got:
        return None
    m = got[0]
    return {"langs": list(m["langs"]), "places": np.frombuffer(m["places"], np.int32), "v": np.frombuffer(m["v"], np.float32).reshape(-1, len(m["langs"])), "b": np.frombuffer(m["b"], np.float32), "bits": m["bits"]}


def identify(docs: DataFrame, model: dict | None) -> DataFrame:
    """(doc_id, language, score, margin): the best language, its score and its lead over the next."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = held.value
        if m:
            mark = np.empty(ROWS << m["bits"], np.int32)
            column = np.full(1 << m["bits"], -1, np.int32)
            column[m["places"]] = np.arange(len(m["places"]))
        for batch in batches:
            for piece in G.chunks(batch, "text"):
                for at in range(0, piece.num_rows, ROWS):
                    part = piece.slice(at, ROWS)
                    ids, text = part.column(0), part.column(1)
                    letters = pc.fill_null(pc.match_substring_regex(text, r"\p{L}"), False).to_numpy(zero_copy_only=False)
                    if not m:
                        none = pa.nulls(len(ids), pa.float64())
                        yield pa.RecordBatch.from_arrays([ids, pa.array(["und"] * len(ids)), none, none], ["doc_id", "language", "score", "margin"])
                        continue
                    s = scores(*G.view(G.lowered(text)), m, mark, column)
                    best = s.argmax(1)
                    top = s[np.arange(len(s)), best]
                    rest = s.copy()
                    rest[np.arange(len(s)), best] = -np.inf
                    lead = top - rest.max(1) if s.shape[1] > 1 else top
                    names = np.where(letters, np.array(m["langs"], object)[best], "und")
                    yield pa.RecordBatch.from_arrays([ids, pa.array(names.tolist(), pa.string()), pa.array(top, mask=~letters), pa.array(lead, mask=~letters)], ["doc_id", "language", "score", "margin"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, language string, score double, margin double")


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, fit(docs))
