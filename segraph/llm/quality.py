"""Document quality from a linear-chain conditional random field over lines.

Every line is a node with the states good and bad.  Its potential is linear in
features of the line and of its two neighbours; four free weights score each pair of
neighbouring states.  Both are learnt together: the conditional likelihood of
the line labels climbs along its gradient, which forward-backward gives.  Only
documents are labelled, so the lines' labels are latent: at first they are the
document's; after each round of training, lines of bad documents that the chain
holds for clearly good are labelled good, and the other way round, while every document
keeps at least the line that speaks most for its label.  Marginals, weighted by line
length, make the document's quality, which a logistic fit on the other half of the
sample turns into a score.

The fit sees a bounded sample (``MOST`` rows of each label).  Null and empty
texts are one empty line.  Without both labels every score is the share of
good labels (1 if there are none).  Rows are scored one by one: repeated rows
and ties get equal scores, an empty table no row.  Extra columns pass through
``score`` untouched; where one has the name of a result, the result's
name gets an underscore behind it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .fit import labelled_sample, logistic, sigmoid
from .shared import arrow_schema, free_names, held, prepare, tidy
from .textvec import Words, column_bytes, segment_sum, slices

MOST = 3000
N_FEATURES = 13
RESULTS = ("quality_share", "quality_score")
_KIND = np.zeros(256, np.uint8)  # 1 lower, 2 upper, 3 digit, 4 mild punctuation, 5 symbol, 6 blank, 7 beyond ASCII
_KIND[33:127] = 5
_KIND[97:123], _KIND[65:91], _KIND[48:58] = 1, 2, 3
_KIND[[ord(c) for c in ".,;:'\"-?()"]] = 4
_KIND[[9, 10, 11, 12, 13, 32]] = 6
_KIND[128:] = 7


def line_features(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features by line, bytes by line, n+1 line offsets by document)."""
    n_docs = len(offs) - 1
    nl = np.flatnonzero(data == 10)
    of = np.searchsorted(nl, offs) + np.arange(n_docs + 1)
    start = np.empty(of[-1], np.int64)
    first = of[:-1]
    rest = np.ones(of[-1], bool)
    rest[first] = False
    start[first] = offs[:-1]
    start[rest] = nl + 1
    end = np.empty(of[-1], np.int64)
    final = np.zeros(of[-1], bool)
    final[of[1:] - 1] = True
    end[final] = offs[1:]
    end[~final] = nl
    size = end - start
    kind = _KIND[data]

    def share(mask):
        c = np.concatenate([[0], np.cumsum(mask, dtype=np.int64)])
        return c[end] - c[start]

    lower, upper, digit, mild, symbol, far = (share(kind == k) for k in (1, 2, 3, 4, 5, 7))
    letters = lower + upper + far
    w = Words(data, offs)
    line = np.searchsorted(start, w.start, "right") - 1
    while len(line) and (bad := end[line] <= w.start).any():  # empty lines share a start
        line[bad] += 1
    wof = np.searchsorted(line, np.arange(len(start) + 1))
    words = np.diff(wof)
    # distinct words of a line: order by line first, then by hash
    key = np.lexsort((w.hash, line)) if len(line) else np.zeros(0, np.int64)
    h, ln = w.hash[key], line[key]
    new = np.ones(len(h), np.int64)
    if len(h):
        new[1:] = (h[1:] != h[:-1]) | (ln[1:] != ln[:-1])
    distinct = segment_sum(new, wof)
    again = np.zeros(len(h), np.int64)
    if len(h) > 1:
        again[1:] = (w.hash[1:] == w.hash[:-1]) & (line[1:] == line[:-1])
    again = segment_sum(again, wof)
    b, wd, let = np.maximum(size, 1), np.maximum(words, 1), np.maximum(letters, 1)
    bang, pipe = share(data == 33), share(data == 124)
    f = np.column_stack([
        np.log1p(size) / 8, np.log1p(words) / 6, np.minimum(letters / wd / 8, 3), upper / let, digit / b * 4, mild / b * 8, symbol / b * 6, np.minimum(symbol / wd, 2),
        bang / wd, np.minimum(pipe / wd * 2, 2), distinct / wd, again / wd, (size == 0).astype(float),
    ])
    return f, size, of


def with_neighbours(f: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Own features, those of the line before and of the line after (0 at the ends)."""
    before, after = np.zeros_like(f), np.zeros_like(f)
    before[1:], after[:-1] = f[:-1], f[1:]
    before[of[:-1]] = 0
    after[of[1:] - 1] = 0
    return np.column_stack([f, before, after])


def _columns(of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First line and line count of documents, long ones first, and how many documents have a t-th line."""
    n = np.diff(of)
    order = np.argsort(-n, kind="stable")
    n = n[order]
    return of[:-1][order], n, np.searchsorted(-n, -np.arange(1, int(n.max(initial=0)) + 1), "right")


def forward_backward(logit: np.ndarray, of: np.ndarray, pair: np.ndarray):
    """P(good) of every line, P(state, next state) of every line but a
    document's last (0 there), and the log partition sum by document.  All chains at once, one
    step per line position.  logit: score of good; pair[a, b]: score of b behind a."""
    first, n, alive = _columns(of)
    fore, back = np.zeros((len(logit), 2)), np.zeros((len(logit), 2))
    unit = np.column_stack([np.zeros(len(logit)), logit])
    fore[first] = unit[first]
    for t, m in enumerate(alive[1:], 1):
        at = first[:m] + t
        x = fore[at - 1]
        for b in (0, 1):
            fore[at, b] = np.logaddexp(x[:, 0] + pair[0, b], x[:, 1] + pair[1, b]) + unit[at, b]
        at = first[:m] + n[:m] - 1 - t
        x = back[at + 1] + unit[at + 1]
        for a in (0, 1):
            back[at, a] = np.logaddexp(x[:, 0] + pair[a, 0], x[:, 1] + pair[a, 1])
    both = fore + back
    last = of[1:] - 1
    z = np.logaddexp(fore[last, 0], fore[last, 1])
    edges = np.zeros((len(logit), 2, 2))
    inner = np.ones(len(logit), bool)
    inner[last] = False
    at = np.flatnonzero(inner)
    doc = np.repeat(np.arange(len(of) - 1), np.diff(of))[at]
    edges[at] = np.exp(np.minimum(fore[at][:, :, None] + pair + (unit + back)[at + 1][:, None, :] - z[doc][:, None, None], 0))
    return sigmoid(both[:, 1] - both[:, 0]), edges, z


def marginals(logit: np.ndarray, of: np.ndarray, pair) -> np.ndarray:
    """P(good) of every line.  pair: scores of neighbouring states, or one score of agreement."""
    t = np.asarray(pair, float) if np.ndim(pair) else np.eye(2) * pair
    first, n, alive = _columns(of)
    out = []
    for direction, (to_good, to_bad) in ((1, (t[:, 1], t[:, 0])), (-1, (t[1], t[0]))):
        msg = np.zeros(len(logit))
        for step, m in enumerate(alive[1:], 1):
            at = first[:m] + step if direction == 1 else first[:m] + n[:m] - 1 - step
            x = msg[at - direction] + logit[at - direction]
            # log-odds of good that the neighbour passes on
            msg[at] = np.logaddexp(x + to_good[1], to_good[0]) - np.logaddexp(x + to_bad[1], to_bad[0])
        out.append(msg)
    return sigmoid(logit + out[0] + out[1])


ROUNDS, STEPS = 2, 8
CLEAR = 0.95
RIDGE = 1.0


def train_chain(x: np.ndarray, of: np.ndarray, label: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Weights of a line's features (last: constant) and of pairs, for documents
    with line features x (lines by document: of), labels and weights."""
    n = np.diff(of)
    doc = np.repeat(np.arange(len(n)), n)
    per = weight[doc]
    x1 = np.column_stack([x, np.ones(len(x))])
    y = label[doc].astype(float)
    w, pair = logistic(x, y, ridge=RIDGE, weight=per), np.zeros((2, 2))
    inner = np.ones(len(x), bool)
    inner[of[1:] - 1] = False
    at = np.flatnonzero(inner)

    def value(w, pair, y):
        """Weighted log-likelihood less the penalty, with what its gradient needs."""
        logit = x1 @ w
        p, edges, z = forward_backward(logit, of, pair)
        a, b = y[at].astype(int), y[at + 1].astype(int)
        ll = (per * y * logit).sum() + (per[at] * pair[a, b]).sum() - (weight * z).sum() - RIDGE * ((w[:-1] ** 2).sum() + (pair**2).sum()) / 2
        return ll, p, edges, (a, b)

    for r in range(ROUNDS):
        if r:
            p = marginals(x1 @ w, of, pair)
            for_it = np.where(label[doc] == 1, p, 1 - p)  # how far a line speaks for its document's label
            y = np.where(for_it < 1 - CLEAR, 1 - label[doc], label[doc]).astype(float)
            best = np.lexsort((-for_it, doc))[of[:-1]]
            y[best] = label
        ll, p, edges, (a, b) = value(w, pair, y)
        for _ in range(STEPS):
            held = np.zeros((2, 2))
            np.add.at(held, (a, b), per[at])
            g = x1.T @ (per * (y - p)) - RIDGE * np.append(w[:-1], 0)
            gp = held - (per[:, None, None] * edges).sum(0) - RIDGE * pair
            curve = (x1 * (per * p * (1 - p) + 1e-9)[:, None]).T @ x1 + np.diag(np.full(len(w), RIDGE))
            dw = np.linalg.solve(curve, g)
            dp = gp / ((per[:, None, None] * edges * (1 - edges)).sum(0) + RIDGE)
            step, better = 1.0, None
            while step > 1e-3:
                better = value(w + step * dw, pair + step * dp, y)
                if better[0] > ll:
                    break
                step /= 3
            if better is None or better[0] <= ll + 1e-4 * abs(ll) / len(n):
                break
            w, pair = w + step * dw, pair + step * dp
            ll, p, edges, (a, b) = better
    return w, pair


class QualityModel:
    def __init__(self, weights=None, pair=0.0, calibration=None, prior: float = 1.0):
        self.weights, self.pair, self.calibration, self.prior = weights, pair, calibration, prior

    def lines(self, data, offs) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """P(good) and bytes of every line, line offsets by document."""
        f, size, of = line_features(data, offs)
        return marginals(with_neighbours(f, of) @ self.weights[:-1] + self.weights[-1], of, self.pair), size, of

    def documents(self, data, offs) -> np.ndarray:
        """Length-weighted mean of the marginals."""
        p, size, of = self.lines(data, offs)
        w = size + 1.0
        return segment_sum(p * w, of) / segment_sum(w, of)

    def score(self, q: np.ndarray) -> np.ndarray:
        q = np.clip(q, 1e-4, 1 - 1e-4)
        return sigmoid(self.calibration[0] * np.log(q / (1 - q)) + self.calibration[1])


def fit(docs: DataFrame, labels: DataFrame, train=None, most: int = MOST) -> QualityModel:
    prepare(docs.sparkSession)
    train = F.lit(True) if train is None else train
    sample = labelled_sample(docs, labels, "quality", train, {0: most, 1: most})
    ddl = "y int, lines int, x binary, size binary"
    schema = arrow_schema(ddl)

    def work(it):
        for batch in it:
            for part in slices(batch, "text"):
                names = part.schema.names
                f, size, of = line_features(*column_bytes(part.column(names.index("text"))))
                x = with_neighbours(f, of).astype(np.float32)
                d = part.to_pydict()
                rows = [{"y": y, "lines": int(b - a), "x": x[a:b].tobytes(), "size": size[a:b].tobytes()} for y, a, b in zip(d["y"], of[:-1], of[1:])]
                yield pa.RecordBatch.from_pylist(rows, schema=schema)

    got = sample.select("doc_id", "y", "text").mapInArrow(tidy(work), ddl).toArrow().to_pylist()  # bounded by most
    got.sort(key=lambda r: (r["y"], r["x"]))
    ys = {r["y"] for r in got}
    if len(ys) < 2:
        return QualityModel(prior=float(next(iter(ys), 1)))
    fold = np.array([i % 2 for i in range(len(got))])

    def chain_fit(rows):
        x = np.concatenate([np.frombuffer(r["x"], np.float32).reshape(-1, 3 * N_FEATURES) for r in rows]).astype(float)
        of = np.concatenate([[0], np.cumsum([r["lines"] for r in rows])])
        y = np.array([r["y"] for r in rows])
        per = np.minimum(1.0, 20 / np.diff(of))  # long documents don't drown the others
        mass = per * np.diff(of)
        balance = np.where(y == 1, 0.5 / max(mass[y == 1].sum(), 1), 0.5 / max(mass[y == 0].sum(), 1)) * len(x)
        return train_chain(x, of, y, per * balance)

    w, pair = chain_fit([r for r, f in zip(got, fold) if f == 0])
    q, y = [], []
    for r, f in zip(got, fold):
        if f == 1:
            x = np.frombuffer(r["x"], np.float32).reshape(-1, 3 * N_FEATURES)
            p = marginals(x @ w[:-1] + w[-1], np.array([0, r["lines"]]), pair)
            size = np.frombuffer(r["size"], np.int64) + 1.0
            q.append(float((p * size).sum() / size.sum()))
            y.append(r["y"])
    q = np.clip(np.array(q), 1e-4, 1 - 1e-4)
    cal = logistic(np.log(q / (1 - q))[:, None], np.array(y, float), ridge=0.1)
    w, pair = chain_fit(got)
    return QualityModel(w, pair, cal)


def score(docs: DataFrame, model: QualityModel) -> DataFrame:
    """docs, quality_share (length-weighted marginal) and quality_score, or what ``free_names`` makes of these."""
    prepare(docs.sparkSession)
    own = free_names(docs.columns, *RESULTS)
    if model.weights is None:
        return docs.select("*", *[F.lit(float(model.prior)).alias(n) for n in own])
    from pyspark.sql import types as T

    def work(it):
        for batch in it:
            for part in slices(batch, "text"):
                q = model.documents(*column_bytes(part.column(part.schema.get_field_index("text"))))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(q), pa.array(model.score(q))], names=[*part.schema.names, *own])

    return docs.mapInArrow(tidy(work), T.StructType([*docs.schema.fields, *[T.StructField(n, T.DoubleType()) for n in own]]))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = fit(docs, labels, ~held(2, 4))
    s = score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), model)
    return s.select("doc_id", held(2, 4).alias("held_out"), F.col("quality_score").alias("score"), (F.col("quality_score") >= 0.7).cast("int").alias("predicted"))
