"""Toxicity by class-conditional Kneser-Ney models.

Words (A-Z lower-cased, other ASCII than letters and digits separates) are
modelled as byte sequences: one interpolated Kneser-Ney model of order ``ORDER``
for toxic and one for ordinary text.  Both back off to the same continuation
counts, pooled over the classes, so an expression too rare to tell gets the
same probability from both.  A text's log-likelihoods are normalised by length,
over the whole text and over its strongest passage, and a logistic fit maps the
differences to a score.

Counts come from a bounded sample of labelled rows (``MOST_TOXIC`` and
``MOST_ORDINARY``); half of it fits the counts for calibration.  Null and empty
texts have differences of 0 and the score of that.  Without labels of both
classes every score is the share of toxic labels (0 if there are none).
"""

from __future__ import annotations

from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .decontam import fold_words
from .fit import labelled_sample, logistic, sigmoid
from .shared import arrow_schema, held, materialise, prepare, tidy

ORDER = 6
DISCOUNTS = (0.0, 1.0, 1.25, 1.5)  # of counts 0, 1, 2, and 3 or more: a single sighting tells no class
MOST_TOXIC, MOST_ORDINARY = 2500, 5000
PASSAGE = 3
TELLING = 3.0
MEMO = 300_000
FEATURES = ("toxic_ll", "ordinary_ll", "peak_word", "peak_passage", "telling", "log_words")
_PAD = b"\x01" * (ORDER - 1)


def grams(word: bytes) -> list[bytes]:
    s = _PAD + word + b"\x02"
    return [s[i : i + ORDER] for i in range(len(s) - ORDER + 1)]


class TwoClassKneserNey:
    """Log-likelihoods of byte n-grams under two classes with shared backoff."""

    def __init__(self, counts: tuple[dict[bytes, int], dict[bytes, int]]):
        self.top = counts
        self.context = tuple(self._contexts(c) for c in counts)
        seen = set(counts[0]) | set(counts[1])
        self.lower: list[tuple[dict, dict]] = []
        while seen and len(next(iter(seen))) > 1:
            cont = Counter(g[1:] for g in seen)
            self.lower.append((cont, self._contexts(cont)))
            seen = set(cont)
        self.memo: dict[bytes, tuple[float, float]] = {}
        self.words: dict[bytes, tuple[float, float]] = {}

    @staticmethod
    def _contexts(counts: dict[bytes, int]) -> dict[bytes, tuple[int, float]]:
        total, freed = defaultdict(int), defaultdict(float)
        for g, n in counts.items():
            total[g[:-1]] += n
            freed[g[:-1]] += DISCOUNTS[min(n, 3)]
        return {h: (total[h], freed[h]) for h in total}

    @staticmethod
    def _blend(counts, contexts, g: bytes, back: float) -> float:
        total = contexts.get(g[:-1])
        if total is None:
            return back
        n = counts.get(g, 0)
        return (n - DISCOUNTS[min(n, 3)] + total[1] * back) / total[0]

    def gram(self, g: bytes) -> tuple[float, float]:
        got = self.memo.get(g)
        if got is None:
            p = 1.0 / 256
            for k in range(len(self.lower) - 1, -1, -1):
                p = self._blend(*self.lower[k], g[k + 1 :], p)
            got = tuple(float(np.log(self._blend(self.top[c], self.context[c], g, p))) for c in (0, 1))
            if len(self.memo) > MEMO:
                self.memo.clear()
            self.memo[g] = got
        return got

    def word(self, w: bytes) -> tuple[float, float]:
        got = self.words.get(w)
        if got is None:
            got = tuple(map(sum, zip(*map(self.gram, grams(w)))))
            if len(w) <= 64:
                if len(self.words) > MEMO:
                    self.words.clear()
                self.words[w] = got
        return got

    def features(self, text: bytes) -> tuple[float, ...]:
        """Toxic and ordinary log-likelihood per byte, their strongest
        difference for a word, and for PASSAGE words, per word; the sum of the
        differences above TELLING, each word once; the logarithm of the length."""
        words = fold_words(text)
        if not words:
            return (0.0,) * len(FEATURES)
        known = self.words
        ll = np.array([known.get(w) or self.word(w) for w in words])
        d = ll[:, 1] - ll[:, 0]
        k = min(PASSAGE, len(d))
        c = np.concatenate([[0.0], np.cumsum(d)])
        n = sum(map(len, words)) + len(words)
        telling = {w: x for w, x in zip(words, d.tolist()) if x > TELLING}
        return float(ll[:, 1].sum()) / n, float(ll[:, 0].sum()) / n, float(d.max()), float((c[k:] - c[:-k]).max()) / PASSAGE, sum(telling.values()), float(np.log1p(len(d)))


def _columns(f) -> np.ndarray:
    f = np.asarray(f, float).reshape(-1, len(FEATURES))
    return np.column_stack([f[:, 0] - f[:, 1], f[:, 2:]])


class ToxicityModel:
    def __init__(self, model: TwoClassKneserNey | None, weights: np.ndarray, prior: float):
        self.model, self.weights, self.prior = model, weights, prior

    def score(self, features) -> np.ndarray:
        if self.model is None:
            return np.full(len(features), self.prior)
        return sigmoid(np.column_stack([_columns(features), np.ones(len(features))]) @ self.weights)


def _count_grams(sample: DataFrame) -> dict[tuple[int, int], dict[bytes, int]]:
    """n-gram counts by (class, fold), a word counting once a document, so that
    repetition within one proves nothing; as large as the sample allows."""
    ddl = "y int, fold int, gram binary, n bigint"
    schema = arrow_schema(ddl)

    def work(it):
        counts: dict = defaultdict(Counter)
        for batch in it:
            d = batch.to_pydict()
            for y, fold, t in zip(d["y"], d["fold"], d["text"]):
                counts[y, fold].update(set(fold_words((t or "").encode())))
        out = defaultdict(Counter)
        for key, words in counts.items():
            for w, n in words.items():
                for g in grams(w):
                    out[key][g] += n
        for (y, fold), c in out.items():
            yield pa.RecordBatch.from_pydict({"y": [y] * len(c), "fold": [fold] * len(c), "gram": list(c), "n": list(c.values())}, schema=schema)

    got = sample.mapInArrow(tidy(work), ddl).groupBy("y", "fold", "gram").agg(F.sum("n").alias("n")).toArrow()
    out: dict = defaultdict(dict)
    for b in got.to_batches():
        for y, fold, g, n in zip(*(c.to_pylist() for c in b.columns)):
            out[y, fold][bytes(g)] = n
    return out


def fit(docs: DataFrame, labels: DataFrame, train=None, most: tuple[int, int] = (MOST_ORDINARY, MOST_TOXIC)) -> ToxicityModel:
    prepare(docs.sparkSession)
    train = F.lit(True) if train is None else train
    sample = materialise(labelled_sample(docs, labels, "toxic", train, dict(enumerate(most))).withColumn("fold", F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(2)).cast("int")), "toxic-sample")
    counts = _count_grams(sample)
    n = {r["y"]: r["n"] for r in sample.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if not n.get(0) or not n.get(1):
        return ToxicityModel(None, np.zeros(len(FEATURES)), n.get(1, 0) / max(1, sum(n.values())))
    half = TwoClassKneserNey((counts[0, 0], counts[1, 0])) if counts[0, 0] and counts[1, 0] else None
    both = [Counter(counts[y, 0]) for y in (0, 1)]
    for y in (0, 1):
        both[y].update(counts[y, 1])
    full = TwoClassKneserNey(tuple(map(dict, both)))
    seen = features_of(sample.where("fold = 1") if half else sample, half or full, "y int").toArrow().to_pydict()
    x, y = _columns(list(zip(*(seen[k] for k in FEATURES)))), np.array(seen["y"], float)
    if len(set(y)) < 2:
        return ToxicityModel(None, np.zeros(len(FEATURES)), n[1] / sum(n.values()))
    return ToxicityModel(full, logistic(x, y, ridge=0.01), 0.0)


_local: dict[int, TwoClassKneserNey] = {}


def _worker_model(box) -> TwoClassKneserNey:
    if box.id not in _local:
        _local.clear()
        _local[box.id] = TwoClassKneserNey(box.value)
    return _local[box.id]


class _Shipped:
    """A broadcast of the counts; each worker builds the model once."""

    def __init__(self, spark, model: TwoClassKneserNey):
        import uuid

        self.box, self.id = spark.sparkContext.broadcast(model.top), uuid.uuid4().hex

    @property
    def value(self):
        return self.box.value


def features_of(docs: DataFrame, model: TwoClassKneserNey, keep: str) -> DataFrame:
    """The kept columns (a DDL string) and the features of every text."""
    box = _Shipped(docs.sparkSession, model)
    names = [x.split(" ")[0] for x in keep.split(", ")]
    ddl = f"{keep}, " + ", ".join(f"{f} double" for f in FEATURES)
    schema = arrow_schema(ddl)

    def work(it):
        m = _worker_model(box)
        for batch in it:
            texts = batch.column(batch.schema.get_field_index("text")).cast(pa.binary())
            f = [m.features(t or b"") for a in range(0, len(texts), 256) for t in texts.slice(a, 256).to_pylist()]
            cols = list(zip(*f)) or [[]] * len(FEATURES)
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(n)) for n in names] + [pa.array(c, pa.float64()) for c in cols], schema=schema)

    return docs.select(*names, "text").mapInArrow(tidy(work), ddl)


def score(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id, toxic and ordinary log-likelihood per byte, the peaks, and the score."""
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    if model.model is None:
        return src.select("doc_id", *[F.lit(0.0).alias(f) for f in FEATURES], F.lit(float(model.prior)).alias("score"))
    w = [float(x) for x in model.weights]
    z = w[0] * (F.col("toxic_ll") - F.col("ordinary_ll")) + sum((a * F.col(f) for a, f in zip(w[1:-1], FEATURES[2:])), F.lit(w[-1]))
    return features_of(src, model.model, "doc_id bigint").withColumn("score", 1 / (1 + F.exp(-z)))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = fit(docs, labels, ~held(1, 3))
    s = score(docs, model)
    return s.select("doc_id", held(1, 3).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"), "toxic_ll", "ordinary_ll")
