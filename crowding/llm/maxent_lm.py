"""Language model: hashed maximum entropy with a class-factored softmax, beside a unigram base.

Tokens are words in lower case (A-Z) and one end a text. Units of the model are the most frequent words and
16 shapes for all others (last character, ASCII or not, length); a rarer word has the probability of its
shape times its smoothed share among the shape's words, so that texts have true probabilities. P(unit | h) =
P(class | h) P(unit | class, h); both are softmaxes over sums of weight rows, picked by hashed features of
the history: previous unit, pair of previous units, and a skip to the second last.

Equal events (unit and its two predecessors) of a batch of texts are handled once, with their number.

Training: every round goes over its share of all training texts; each task descends on its own texts from
the common weights (mini-batches, a step size per row falling with its gradients), and the tasks' changes are
averaged row by row, weighted by how often a task used the row, through two levels of sums.

Word counts for all words are made by shuffle; only the most frequent words, HEAD at most, are broadcast, the rest of
each text is joined with the counts.

Edge cases: a null or empty text is its end token alone; a null doc_id counts as empty text in the hash, so
it is held out; without training texts counts are 0 and the model stays at its start; repeated rows score
alike, each with its own row; an empty table stays empty; other columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.llm.common import settle, slices, table, utf8

HEAD = 1 << 18
CLASSES, SLOTS = 32, 32
UNITS = CLASSES * SLOTS
SHAPES = 16
ALPHA = 0.1
CLASS_ROWS, WORD_ROWS = 1 << 15, 1 << 15
BATCH = 4096
ROUNDS = 2
RATE = 0.35
#: Last characters that are shapes of their own, beside '.' and ','.
MARKS = "!?;:|)\"'"


def shape(word: bytes) -> int:
    """0..15, from last character, bytes beyond ASCII, and length."""
    last = word[-1:]
    end = 1 if last == b"." else 2 if last == b"," else 3 if last in [c.encode() for c in MARKS] else 0
    return end * 4 + 2 * (not word.isascii()) + (len(word) > 5)


def shape_sql(word: str) -> "F.Column":
    """The same as an expression."""
    last = F.substring(word, -1, 1)
    end = F.when(last == ".", 1).when(last == ",", 2).when(last.isin(list(MARKS)), 3).otherwise(0)
    return end * 4 + F.when(F.octet_length(word) != F.char_length(word), 2).otherwise(0) + F.when(F.octet_length(word) > 5, 1).otherwise(0)


def with_split(docs: DataFrame) -> DataFrame:
    """doc_id, text, held_out."""
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"),
        (F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 10 == 0).alias("held_out"),
    )


def word_counts(train: DataFrame) -> DataFrame:
    """(word, n) over all training tokens, the end token as the empty word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter[bytes] = Counter()

        def flush():
            words, n = list(seen), list(seen.values())
            for i in range(0, len(words), 65536):
                yield pa.RecordBatch.from_arrays([pa.array(words[i : i + 65536], pa.binary()).cast(pa.string()), pa.array(n[i : i + 65536], pa.int64())], names=["word", "n"])
            seen.clear()

        for b in slices(batches):
            for t in utf8(b, "text"):
                seen.update(t.lower().split())
            seen[b""] += b.num_rows
            if len(seen) > 300_000:
                yield from flush()
        yield from flush()

    return train.select("text").mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


class _Places(dict):
    """Place of a head word; for others minus one minus their shape."""

    def __missing__(self, word: bytes) -> int:
        return -1 - shape(word)


class Vocabulary:
    """Head words by falling count, with what scoring needs of the counts of all words."""

    def __init__(self, words: list[bytes], counts: np.ndarray, total: int, distinct: int, shape_total: np.ndarray, shape_distinct: np.ndarray):
        self.words, self.counts, self.total, self.distinct = words, counts, total, distinct
        self.shape_total, self.shape_distinct = shape_total, shape_distinct

    def prepare(self) -> None:
        if hasattr(self, "place"):
            return
        self.place = _Places((w, i) for i, w in enumerate(self.words))
        n = min(len(self.words), UNITS - SHAPES)
        shapes = np.array([shape(w) for w in self.words[n:]], dtype=np.int64)
        # units of places, and behind them those of shapes, so that a negative place finds its shape's unit
        self.unit = np.concatenate([np.arange(n), UNITS - SHAPES + shapes, UNITS - 1 - np.arange(SHAPES)]).astype(np.int32)
        self.rest = self.log_share(self.counts[n:], shapes)
        self.rest = np.concatenate([np.zeros(n), self.rest, np.zeros(SHAPES)])
        self.base = np.concatenate([self.log_base(self.counts), np.zeros(SHAPES)])

    def log_base(self, c):
        return np.log10((c + ALPHA) / (self.total + ALPHA * (self.distinct + 1)))

    def log_share(self, c, shapes):
        return np.log10((c + ALPHA) / (self.shape_total[shapes] + ALPHA * (self.shape_distinct[shapes] + 1)))

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("place", "unit", "rest", "base")}


def vocabulary(counts: DataFrame, head: int = HEAD) -> Vocabulary:
    """The head is every word of the highest classes of counts (64 to a factor of e) that together have at most `head`
    words; no class is taken in part, so words of one count are in or out together, and head is never exceeded."""
    total, distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    level = F.floor(F.log(F.col("n").cast("double")) * 64).cast("int")
    spread = counts.groupBy(level.alias("c")).agg(F.count(F.lit(1)).alias("words")).orderBy(F.desc("c")).collect()  # 64 rows to a factor of e: under 2,900
    lowest, got = 1 << 30, 0
    for r in spread:
        if got + r["words"] > head:
            break
        got, lowest = got + r["words"], r["c"]
    rows = counts.filter(level >= lowest).toPandas().sort_values(["n", "word"], ascending=[False, True], kind="stable")
    words = [w.encode() for w in rows["word"]]
    units = counts.sparkSession.createDataFrame([(w.decode(),) for w in words[: UNITS - SHAPES]], "w string")
    rest = counts.join(F.broadcast(units), F.col("word") == F.col("w"), "left_anti").groupBy(shape_sql("word").alias("s")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).collect()
    shape_total, shape_distinct = np.zeros(SHAPES), np.zeros(SHAPES)
    for r in rest:
        shape_total[r["s"]], shape_distinct[r["s"]] = r["n"], r["v"]
    return Vocabulary(words, rows["n"].to_numpy(np.float64), int(total), int(distinct), shape_total, shape_distinct)


class Weights:
    """Rows of class logits and of slot logits; the first rows of each are biases."""

    def __init__(self, to_class: np.ndarray, to_slot: np.ndarray):
        self.to_class, self.to_slot = to_class, to_slot

    @classmethod
    def start(cls, vocab: Vocabulary) -> "Weights":
        freq = np.full(UNITS, 1e-3)
        n = min(len(vocab.words), UNITS - SHAPES)
        freq[:n] += vocab.counts[:n]
        freq[UNITS - SHAPES :] += vocab.shape_total
        grid = np.empty((CLASSES, SLOTS))
        grid[_CLASS_OF, _SLOT_OF] = freq
        to_class, to_slot = np.zeros((CLASS_ROWS, CLASSES), np.float32), np.zeros((WORD_ROWS, SLOTS), np.float32)
        to_class[0] = np.log(grid.sum(axis=1) / grid.sum())
        to_slot[:CLASSES] = np.log(grid / grid.sum(axis=1, keepdims=True))
        return cls(to_class, to_slot)


# Shapes go with the most frequent words in the first classes, so that classes fall in mass.
_ORDER = np.concatenate([np.arange(UNITS - SHAPES, UNITS), np.arange(UNITS - SHAPES)])
_CLASS_OF, _SLOT_OF = np.empty(UNITS, np.int64), np.empty(UNITS, np.int64)
_CLASS_OF[_ORDER], _SLOT_OF[_ORDER] = np.arange(UNITS) // SLOTS, np.arange(UNITS) % SLOTS


def _hash(kind: int, a: np.ndarray, b, low: int, rows: int) -> np.ndarray:
    z = a.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.asarray(b).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(kind * 0x165667B19E3779F9 & 2**64 - 1)
    z ^= z >> np.uint64(29)
    z *= np.uint64(0xBF58476D1CE4E5B9)
    return (low + ((z >> np.uint64(32)) % np.uint64(rows - low)).astype(np.int64)).astype(np.int64)


def history(units: np.ndarray, starts: np.ndarray) -> list[np.ndarray]:
    """The two units before each, UNITS before a text's start."""
    out, since = [], np.arange(len(units)) - np.repeat(starts, np.diff(np.append(starts, len(units))))
    for k in (1, 2):
        h = np.full(len(units), UNITS, np.int64)
        h[k:] = units[:-k] if len(units) > k else h[k:]
        h[since < k] = UNITS
        out.append(h)
    return out


def features(h: list[np.ndarray], cls: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows of to_class, rows of to_slot), one column a token."""
    zero = np.zeros(len(cls), np.int64)
    a = [zero, _hash(1, h[0], zero, 1, CLASS_ROWS), _hash(2, h[0], h[1], 1, CLASS_ROWS), _hash(3, h[1], zero, 1, CLASS_ROWS)]
    b = [cls, _hash(5, h[0], cls, CLASSES, WORD_ROWS), _hash(6, h[1], cls, CLASSES, WORD_ROWS)]
    return np.stack(a), np.stack(b)


def _softmax(w: np.ndarray, rows: np.ndarray) -> np.ndarray:
    z = w[rows[0]]
    for r in rows[1:]:
        z += w[r]
    z -= z.max(axis=1, keepdims=True)
    np.exp(z, out=z)
    z /= z.sum(axis=1, keepdims=True)
    return z


def events(units: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, list[np.ndarray], np.ndarray, np.ndarray]:
    """(unit, history, how often, event of each token) of the distinct events."""
    h = history(units, starts)
    base = UNITS + 1
    key, inverse, times = np.unique((h[1] * base + h[0]) * base + units, return_inverse=True, return_counts=True)
    return key % base, [key // base % base, key // (base * base)], times, inverse


def log10_prob(w: Weights, units: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """log10 P(unit | history) of every token of the texts that begin at starts."""
    unit, h, _, inverse = events(units, starts)
    cls, slot = _CLASS_OF[unit], _SLOT_OF[unit]
    out = np.empty(len(unit))
    for i in range(0, len(unit), BATCH):
        s = slice(i, i + BATCH)
        a, b = features([x[s] for x in h], cls[s])
        k = np.arange(a.shape[1])
        out[s] = np.log10(np.maximum(_softmax(w.to_class, a)[k, cls[s]], 1e-30)) + np.log10(np.maximum(_softmax(w.to_slot, b)[k, slot[s]], 1e-30))
    return out[inverse]


class Learner:
    """Mini-batch descent from given weights, with what each row has been used for."""

    def __init__(self, start: Weights, rate: float = RATE):
        self.w = Weights(start.to_class.copy(), start.to_slot.copy())
        self.used = [np.zeros(len(x), np.float32) for x in (self.w.to_class, self.w.to_slot)]
        self.square = [np.full(len(x), 1e-2, np.float32) for x in (self.w.to_class, self.w.to_slot)]
        self.rate = rate

    def _step(self, k: int, w: np.ndarray, rows: np.ndarray, target: np.ndarray, times: np.ndarray) -> None:
        n = rows.shape[1]
        g = _softmax(w, rows)
        g[np.arange(n), target] -= 1
        g *= times[:, None]
        flat = rows.ravel()
        order = np.argsort(flat, kind="stable")
        at = flat[order]
        first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        which = at[first]
        total = np.add.reduceat(g[order % n], first, axis=0)
        count = np.add.reduceat(times[order % n], first)
        self.square[k][which] += np.einsum("ij,ij->i", total, total) / w.shape[1]
        self.used[k][which] += count
        w[which] -= (self.rate / np.sqrt(self.square[k][which] * w.shape[1]))[:, None] * total

    def learn(self, units: np.ndarray, starts: np.ndarray) -> None:
        unit, h, times, _ = events(units, starts)
        mixed = np.random.default_rng(len(unit)).permutation(len(unit))  # events are sorted; batches must not be
        unit, h, times = unit[mixed], [x[mixed] for x in h], times[mixed].astype(np.float32)
        cls, slot = _CLASS_OF[unit], _SLOT_OF[unit]
        for i in range(0, len(unit), BATCH):
            s = slice(i, i + BATCH)
            a, b = features([x[s] for x in h], cls[s])
            self._step(0, self.w.to_class, a, cls[s], times[s])
            self._step(1, self.w.to_slot, b, slot[s], times[s])


def texts_to_places(vocab: Vocabulary, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, list[list[bytes]]]:
    """(places of all tokens, starts of texts, words)."""
    vocab.prepare()
    get = vocab.place.__getitem__
    words = [t.lower().split() + [b""] for t in texts]
    places = np.array([p for ws in words for p in map(get, ws)], dtype=np.int64)
    sizes = np.array([len(w) for w in words], dtype=np.int64)
    return places, np.cumsum(sizes) - sizes, words


_PARTS = 16  # pieces in which weight changes travel


def _pieces(n: int) -> list[slice]:
    return [slice(n * i // _PARTS, n * (i + 1) // _PARTS) for i in range(_PARTS)]


def _average(pdf: pd.DataFrame) -> pd.DataFrame:
    used = [np.frombuffer(u, np.float32) for u in pdf["used"]]
    total = np.maximum(sum(u.astype(np.float64) for u in used), 1e-9)
    width = len(pdf["change"].iloc[0]) // 2 // len(total)
    change = sum(np.frombuffer(c, np.float16).reshape(-1, width).astype(np.float32) * (u / total).astype(np.float32)[:, None] for c, u in zip(pdf["change"], used))
    first = pdf.iloc[0]
    return pd.DataFrame({"kind": [first["kind"]], "piece": [first["piece"]], "part": [0], "used": [total.astype(np.float32).tobytes()], "change": [change.astype(np.float16).tobytes()]})


def train_round(texts: DataFrame, vocab, weights: Weights) -> Weights:
    """Weights after one round over texts; vocab is a broadcast."""
    sc = texts.sparkSession.sparkContext
    shared = sc.broadcast(weights)
    schema = "kind int, piece int, part int, used binary, change binary"
    tasks = max(1, texts.rdd.getNumPartitions() // 2)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        learner, any_text = Learner(shared.value), False
        for b in slices(batches):
            if b.num_rows:
                places, starts, _ = texts_to_places(vocab.value, utf8(b, "text"))
                learner.learn(vocab.value.unit[places], starts)
                any_text = True
        part = TaskContext.get().partitionId() // max(1, math.isqrt(tasks))
        for k, name in enumerate(("to_class", "to_slot") if any_text else ()):
            for i, s in enumerate(_pieces(len(learner.used[k]))):
                change = getattr(learner.w, name)[s] - getattr(shared.value, name)[s]
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([i], pa.int32()), pa.array([part], pa.int32()), pa.array([learner.used[k][s].tobytes()], pa.binary()), pa.array([np.clip(change, -60000, 60000).astype(np.float16).tobytes()], pa.binary())], names=["kind", "piece", "part", "used", "change"])

    changes = texts.select("text").coalesce(tasks).mapInArrow(run, schema)
    some = changes.groupBy("kind", "piece", "part").applyInPandas(_average, schema)
    new = Weights(weights.to_class.copy(), weights.to_slot.copy())
    for r in some.groupBy("kind", "piece").applyInPandas(_average, schema).toLocalIterator():  # as large as the weights
        w = (new.to_class, new.to_slot)[r["kind"]]
        s = _pieces(len(w))[r["piece"]]
        w[s] += np.frombuffer(r["change"], np.float16).reshape(-1, w.shape[1]).astype(np.float32)
    shared.unpersist()
    return new


def train(texts: DataFrame, vocab: Vocabulary, shared, rounds: int = ROUNDS) -> Weights:
    """rounds passes over a hash share of the texts each, which together are all texts once."""
    weights = Weights.start(vocab)
    for k in range(rounds):
        share = texts.filter(F.pmod(F.xxhash64("doc_id"), F.lit(rounds)) == k)
        weights = train_round(share, shared, weights)
    return weights


def score(docs: DataFrame, counts: DataFrame, vocab: Vocabulary, shared, weights: Weights) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    model = docs.sparkSession.sparkContext.broadcast(weights)
    kinds = [pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.struct([("word", pa.string()), ("tf", pa.int64())]))]
    names = ["doc_id", "held_out", "n_tokens", "n_head", "base", "model", "rest"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = shared.value
        for b in slices(batches):
            if not b.num_rows:
                continue
            places, starts, words = texts_to_places(v, utf8(b, "text"))
            lp = log10_prob(model.value, v.unit[places], starts) + v.rest[places]
            sizes = np.diff(np.append(starts, len(places)))
            rest = []
            for i in range(len(words)):
                ws, at = words[i], starts[i]
                miss = Counter(ws[j] for j in np.flatnonzero(places[at : at + sizes[i]] < 0))
                rest.append([{"word": w.decode(), "tf": n} for w, n in miss.items()])
            known = np.add.reduceat((places >= 0).astype(np.int64), starts)
            cols = [b.column("doc_id"), b.column("held_out"), sizes, known, np.add.reduceat(v.base[places], starts), np.add.reduceat(lp, starts), rest]
            yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    rows = docs.select("doc_id", "held_out", "text").mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_head long, base double, model double, rest array<struct<word: string, tf: long>>")
    rows = settle(rows.withColumn("row", F.monotonically_increasing_id()), "lm-scores")
    low, z = F.lit(vocab.total + ALPHA * (vocab.distinct + 1)), F.array(*[F.lit(float(a + ALPHA * (b + 1))) for a, b in zip(vocab.shape_total, vocab.shape_distinct)])
    rest = rows.select("row", F.inline("rest")).join(counts.withColumnsRenamed({"word": "w"}), F.col("word") == F.col("w"), "left")
    c = F.coalesce("n", F.lit(0)).cast("double") + F.lit(ALPHA)
    rest = rest.groupBy("row").agg(
        F.sum(F.when(F.col("n") > 0, F.col("tf")).otherwise(0)).alias("more_known"), F.sum(F.col("tf") * F.log10(c / low)).alias("more_base"),
        F.sum(F.col("tf") * F.log10(c / F.get(z, shape_sql("word")))).alias("more_model"),
    )
    zero = lambda x: F.coalesce(x, F.lit(0))
    return rows.drop("rest").join(rest, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("n_head") + zero("more_known")).cast("long").alias("n_known"), F.lit(vocab.total).cast("long").alias("train_tokens"),
        (F.col("base") + zero("more_base")).alias("base_score"), (F.col("model") + zero("more_model")).alias("score"),
    )


def op5_maxent_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents scored by the base and by a model trained on those that are not held out."""
    docs = with_split(table(spark, sf_dir, "documents"))
    learn = docs.filter(~F.col("held_out"))
    counts = settle(word_counts(learn), "lm-counts")
    vocab = vocabulary(counts)
    shared = spark.sparkContext.broadcast(vocab)
    return score(docs, counts, vocab, shared, train(learn, vocab, shared))
