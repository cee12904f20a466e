"""Token counts by dynamic programming shared along a trie.

The distinct pre-tokens of a slice of texts are walked as a trie in sorted
order: the stack holds, for each prefix length, the forward score (log of the
summed probability of all segmentations) and the best segmentation's score and
length.  A prefix shared with the pre-token before is not computed again.
Terminal values go to a bounded table that the worker's later texts reuse.

White space has tokens too if ``whole`` is set; else the words alone count.
Null and empty texts have no tokens.  Of equally good segmentations the one
whose last piece is longest counts.  Extra columns are ignored; repeated rows
count each.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import pieces as P
from .shared import arrow_schema, prepare, tidy

KEPT = 600_000
OUT_DDL = "doc_id bigint, n_words bigint, n_tokens bigint, forward_logp double"


def count_sorted(words: list[str], vocab: P.Pieces) -> list[tuple[int, float]]:
    """(tokens of the best segmentation, forward log score) of sorted distinct words."""
    out = []
    fwd, best, size = [0.0], [0.0], [0]
    logp, longest, before = vocab.logp, vocab.longest, ""
    exp, log = math.exp, math.log
    for w in words:
        n, k = len(w), 0
        most = min(n, len(before))
        while k < most and w[k] == before[k]:
            k += 1
        del fwd[k + 1 :], best[k + 1 :], size[k + 1 :]
        for d in range(k + 1, n + 1):
            top = s_best = -math.inf
            c_best, terms = 0, []
            for a in range(max(0, d - longest), d):
                p = logp.get(w[a:d])
                if p is None:
                    if a < d - 1:
                        continue
                    nb = len(w[a].encode("utf-8", "surrogatepass"))
                    p, cost = nb * vocab.floor, nb
                else:
                    cost = 1
                t = fwd[a] + p
                terms.append(t)
                if t > top:
                    top = t
                if best[a] + p > s_best:
                    s_best, c_best = best[a] + p, size[a] + cost
            fwd.append(top + log(sum(exp(t - top) for t in terms)) if len(terms) > 1 else top)
            best.append(s_best)
            size.append(c_best)
        out.append((size[n], fwd[n]))
        before = w
    return out


_known: dict[str, dict[str, tuple[int, float]]] = {}


def count_texts(texts: list[str], vocab_path: str, whole: bool = False) -> list[tuple[int, int, float]]:
    """(words, tokens, forward log score) of each text, or of its words unless whole."""
    vocab, known = P.load(vocab_path), _known.setdefault(vocab_path, {})
    words = [P.words_of(t) for t in texts]
    split = [P.units_of(t) for t in texts] if whole else words
    here = set().union(*split) if split else set()
    if len(known) + len(here) > KEPT:
        known.clear()
    new = sorted(w for w in here if w not in known)
    known.update(zip(new, count_sorted(new, vocab)))
    get = known.__getitem__
    out = []
    for ws, us in zip(words, split):
        got = list(map(get, us))
        out.append((len(ws), sum(c for c, _ in got), math.fsum(f for _, f in got)))
    return out


def digest(docs: DataFrame, vocab_path: str, whole: bool = False) -> DataFrame:
    """doc_id, words, tokens and forward log score of every text."""
    prepare(docs.sparkSession)
    schema = arrow_schema(OUT_DDL)

    def work(it):
        for batch in it:
            ids, texts = batch.column(0), batch.column(1)
            for a in range(0, batch.num_rows, 1024):
                got = count_texts([t or "" for t in texts.slice(a, 1024).to_pylist()], vocab_path, whole)
                yield pa.RecordBatch.from_arrays([ids.slice(a, 1024), *[pa.array(c, f.type) for c, f in zip(zip(*got), list(schema)[1:])]], schema=schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(work), OUT_DDL)
