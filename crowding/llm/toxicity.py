"""Toxicity grades by cumulative-link ordinal regression on sparse text features.

P(grade <= j) = sigmoid(theta_j - w.x) with rising thresholds theta and one w for all of them. Features are
the distinct words of a text and their first four, five and six letters, hashed; those that tell labelled
toxic rows from others best are kept. Grades: 0 not toxic; of toxic rows 1, or 2 when they hold more
telltale features than the median toxic row. Output: the grades' probabilities, the expected severity
(sum of grade times probability), the likeliest grade, and toxic (P(grade > 0) >= 0.5).

Fitting uses the SAMPLE labelled documents with the smallest id hash (a bound, whatever the table's size);
scoring goes over all rows and whole texts.

Edge cases: a null or empty text has no features and gets the grade the thresholds alone give; null labels
and labels without a document are not fitted on, of contradicting labels of an id the larger counts; without
labels of both kinds every row gets grade 0 with certainty; repeated rows score alike; an empty table stays
empty; other columns are carried along, except that columns of the output's names are replaced.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from crowding.llm.common import Bounded, claim, released, slices, table

SAMPLE = 20_000
BITS = 20
BLOCK = 1 << 14
FEATURES = 4096
#: Bytes of words with their features that a worker keeps.
CACHE = 16 << 20
OUT = ["p_grade_0", "p_grade_1", "p_grade_2", "expected_severity", "grade", "toxic"]
_WORD = re.compile(r"[^\W\d_]+")


def word_features(word: str) -> list[int]:
    """Hashed features of a word in lower case."""
    parts = [f"w{word}", *[f"{k}{word[:k]}" for k in (4, 5, 6) if len(word) >= k]]
    return [zlib.crc32(p.encode()) & (1 << BITS) - 1 for p in parts]


@dataclass
class OrdinalModel:
    """features (hashed ids), weights w, thresholds theta."""

    features: np.ndarray
    weights: np.ndarray
    theta: np.ndarray
    known: Bounded = field(default_factory=lambda: Bounded(CACHE), repr=False)

    def __getstate__(self):
        return {"features": self.features, "weights": self.weights, "theta": self.theta}

    def __setstate__(self, s):
        self.__init__(s["features"], s["weights"], s["theta"])

    def vector(self, text: str) -> list[int]:
        """Places of the text's features in the model."""
        if not hasattr(self, "place"):
            self.place = {int(f): i for i, f in enumerate(self.features)}
        known, place, out = self.known, self.place, set()
        claim(f"toxicity {id(self)}", known.forget)
        for w in set(_WORD.findall(text.lower())):
            got = known.find(w)
            if got is None:
                got = tuple(place[f] for f in word_features(w) if f in place)
                if len(w) < 64:
                    known.keep(w, got, 200 + 2 * len(w) + 8 * len(got))
            if got:
                out.update(got)
        return sorted(out)

    def probabilities(self, x: float) -> np.ndarray:
        below = 1 / (1 + np.exp(-np.clip(self.theta - x, -500, 500)))
        return np.diff(np.concatenate([[0.0], below, [1.0]]))


def fit_ordinal(rows: list[list[int]], y: np.ndarray, n_features: int, steps: int = 300, l2: float = 2e-4, rate: float = 0.05) -> tuple[np.ndarray, np.ndarray]:
    """(w, theta) by Adam on the whole (bounded) sample; gaps between thresholds are kept positive as exponentials."""
    grades = int(y.max()) + 1
    at = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    cols = np.concatenate([np.asarray(r, dtype=np.int64) for r in rows]) if len(at) else np.zeros(0, np.int64)
    share = np.clip(np.cumsum(np.bincount(y, minlength=grades))[:-1] / len(y), 1e-6, 1 - 1e-6)
    first = np.log(share / (1 - share))
    p = np.concatenate([np.zeros(n_features), first[:1], np.log(np.maximum(np.diff(first), 1e-2))])
    m, v = np.zeros_like(p), np.zeros_like(p)
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -500, 500)))
    for t in range(1, steps + 1):
        w, gaps = p[:n_features], np.exp(p[n_features + 1 :])
        theta = p[n_features] + np.concatenate([[0.0], np.cumsum(gaps)])
        x = np.bincount(at, w[cols], len(rows))
        edge = np.concatenate([[-np.inf], theta, [np.inf]])
        hi, lo = sig(edge[y + 1] - x), sig(edge[y] - x)
        prob = np.maximum(hi - lo, 1e-12)
        d_hi, d_lo = hi * (1 - hi) / prob, lo * (1 - lo) / prob
        g_x = (d_hi - d_lo) / len(rows)
        g_edge = -(np.bincount(y + 1, d_hi, grades + 1) - np.bincount(y, d_lo, grades + 1))[1:-1] / len(rows)
        g = np.concatenate([np.bincount(cols, g_x[at], n_features) + l2 * w, [g_edge.sum()], [g_edge[j + 1 :].sum() * gaps[j] for j in range(grades - 2)]])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        p = p - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-9)
    theta = p[n_features] + np.concatenate([[0.0], np.cumsum(np.exp(p[n_features + 1 :]))])
    return p[:n_features], theta


def labelled(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, text, toxic of the sample."""
    spark = docs.sparkSession
    known = labels.filter("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    picked = known.select(F.col("doc_id").cast("long").alias("id"), "toxic", F.xxhash64("doc_id").alias("h")).orderBy("h", "id").limit(sample).collect()
    small = spark.createDataFrame([(r["id"], r["toxic"]) for r in picked], "id long, toxic_label int")
    rows = docs.select("doc_id", "text").join(F.broadcast(small), F.col("doc_id") == F.col("id"))
    return rows.select(F.col("id").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), F.col("toxic_label").alias("toxic"))


def choose_features(rows: DataFrame, top: int = FEATURES) -> tuple[np.ndarray, np.ndarray]:
    """(features, telltale): hashed features most associated with toxic rows, and which of them tell on their own.

    Tasks count in arrays of 2^BITS; blocks of these are summed, and each block returns its best.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros((2, 1 << BITS), np.int32)
        total = [0, 0]
        for b in batches:
            for text, toxic in zip(b.column("text").to_pylist(), b.column("toxic").to_pylist()):
                f = {x for w in set(_WORD.findall(text.lower())) for x in word_features(w)}
                n[int(toxic > 0), list(f)] += 1
                total[int(toxic > 0)] += 1
        if sum(total):
            for k in range(0, 1 << BITS, BLOCK):
                yield pa.RecordBatch.from_arrays([pa.array([k // BLOCK]), pa.array([total[0]]), pa.array([total[1]]), pa.array([zlib.compress(n[:, k : k + BLOCK].tobytes(), 1)], pa.binary())], names=["block", "clean", "toxic", "counts"])

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = sum(np.frombuffer(zlib.decompress(c), np.int32).reshape(2, -1).astype(np.int64) for c in pdf["counts"])
        clean, toxic = pdf["clean"].sum(), pdf["toxic"].sum()
        n, seen = clean + toxic, a + b
        with np.errstate(all="ignore"):
            chi = n * (b * (clean - a) - a * (toxic - b)) ** 2.0 / (toxic * clean * seen * (n - seen))
        chi = np.where((b >= 3) & (b * clean > 2 * a * toxic), np.nan_to_num(chi), 0)
        pick = [i for i in np.lexsort((np.arange(len(chi)), -chi))[:512] if chi[i] > 0]
        base = int(pdf["block"].iloc[0]) * BLOCK
        return pd.DataFrame({"feature": [base + i for i in pick], "chi": chi[pick], "purity": (b[pick] / np.maximum(seen[pick], 1)), "n": b[pick]})

    parts = rows.repartition(8, "doc_id").mapInArrow(released(count), "block long, clean long, toxic long, counts binary")
    found = parts.groupBy("block").applyInPandas(best, "feature long, chi double, purity double, n long").toPandas()  # 512 rows a block at most
    found = found.sort_values(["chi", "feature"], ascending=[False, True]).head(top)
    return found["feature"].to_numpy(np.int64), ((found["purity"] >= 0.9) & (found["n"] >= 10)).to_numpy()


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> OrdinalModel:
    rows = labelled(docs, labels, sample)
    features, telltale = choose_features(rows)
    if not len(features):
        return OrdinalModel(np.zeros(0, np.int64), np.zeros(0), np.array([500.0, 501.0]))
    model = OrdinalModel(features, np.zeros(len(features)), np.zeros(2))

    def vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = [model.vector(t) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("toxic"), pa.array(x, pa.list_(pa.int32()))], names=["doc_id", "toxic", "x"])

    got = sorted((r["doc_id"], int(r["toxic"] > 0), r["x"]) for r in rows.mapInArrow(vectors, "doc_id long, toxic int, x array<int>").toLocalIterator())
    marks = np.array([int(telltale[x].sum()) for _, _, x in got])
    y = np.array([t for _, t, _ in got])
    if y.all() or not y.any():
        return OrdinalModel(np.zeros(0, np.int64), np.zeros(0), np.array([500.0, 501.0]))
    y = y + y * (marks > np.median(marks[y == 1]))
    w, theta = fit_ordinal([x for _, _, x in got], y, len(features))
    theta = theta if len(theta) == 2 else np.append(theta, theta[-1] + 500)
    return OrdinalModel(features, w, theta)


def score(docs: DataFrame, model: OrdinalModel, text_col: str = "text") -> DataFrame:
    """docs with the columns of OUT."""
    docs = docs.drop(*OUT)
    at = docs.columns.index(text_col)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        w = m.weights
        for b in slices(batches):
            p = np.array([m.probabilities(float(w[m.vector(t or "")].sum())) for t in b.column(at).to_pylist()]).reshape(-1, 3)
            cols = [*[pa.array(p[:, k]) for k in range(3)], pa.array(p @ np.arange(3.0)), pa.array(p.argmax(axis=1).astype(np.int32)), pa.array((p[:, 0] <= 0.5).astype(np.int32))]
            yield pa.RecordBatch.from_arrays([*b.columns, *cols], names=[*b.schema.names, *OUT])

    kinds = [T.DoubleType()] * 4 + [T.IntegerType()] * 2
    return docs.mapInArrow(released(run), T.StructType([*docs.schema.fields, *[T.StructField(n, k) for n, k in zip(OUT, kinds)]]))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Severity of every document, by a model fitted on labels."""
    docs = table(spark, sf_dir, "documents")
    return score(docs.select(F.col("doc_id"), "text"), train(docs, table(spark, sf_dir, "labels"))).drop("text")
