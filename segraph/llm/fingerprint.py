"""Document fingerprints by locally consistent parsing.

A text is a sequence of code points.  Each level collapses runs, reduces the
names by deterministic coin tossing (the lowest bit in which a name differs
from its left neighbour, and its value) until six labels remain, cuts at local
maxima of the labels and names every phrase by a hash of its contents.  Cuts
depend on a few neighbours only, so equal substrings have the same interior
phrases wherever they stand.  The fingerprint is, for each level of ``LEVELS``,
SLOTS minima of its phrase names under fixed orders; likeness is the share of
equal minima.

Null and empty texts have the fingerprint of no phrase; two of them are alike
to 1, one and another text to 0.  Repeated ids are ordered by text, null ids
come last.  A single document is its own next one.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import arrow_schema, block_of, partitions, prepare, range_bounds, tidy
from .textvec import mix, powers

U = np.uint64
LEVELS, SLOTS = (2, 3), 24
_rng = np.random.Generator(np.random.PCG64(19))
ORDERS = _rng.integers(1, 2**63, SLOTS, dtype=np.uint64) * U(2) + U(1)
EMPTY = "-" * (4 * SLOTS * len(LEVELS))


def _coin(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """2 * (lowest bit in which a differs from b) + that bit of a."""
    d = a ^ b
    low = np.bitwise_count((d & (~d + U(1))) - U(1)).astype(np.uint64)
    return ((low << U(1)) | ((a >> (low & U(63))) & U(1))).astype(np.uint8)


_all = np.arange(128, dtype=np.uint64)
_STEP = _coin(np.repeat(_all, 128), np.tile(_all, 128))  # of all pairs of labels; equal ones don't occur


def _labels(names: np.ndarray, first: np.ndarray) -> np.ndarray:
    prev = np.empty_like(names)
    prev[1:] = names[:-1]
    prev[first] = ~names[first]
    lab = _coin(names, prev)
    for _ in range(3):
        left = np.empty_like(lab)
        left[1:] = lab[:-1]
        left[first] = lab[first] ^ 1
        lab = _STEP[(lab.astype(np.int32) << 7) | left]
    return lab


def parse(names: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Phrase names of the next level and their offsets by document."""
    n = len(names)
    first = of[:-1][np.diff(of) > 0]
    new = np.ones(n, bool)
    new[1:] = names[1:] != names[:-1]
    new[first] = True
    at = np.flatnonzero(new)
    length = np.diff(np.append(at, n)).astype(np.uint64)
    names = names[at]
    names = np.where(length > 1, mix(names + length * U(0xA0761D6478BD642F)), names)
    of = np.searchsorted(at, of)
    first = of[:-1][np.diff(of) > 0]
    n = len(names)
    lab = _labels(names, first)
    cut = np.zeros(n, bool)
    cut[1:-1] = (lab[1:-1] > lab[:-2]) & (lab[1:-1] > lab[2:])
    last = of[1:][np.diff(of) > 0] - 1
    cut[last] = False
    cut[first] = True
    start = np.flatnonzero(cut)
    c = np.zeros(n + 1, np.uint64)
    np.cumsum(names * powers("base", n), out=c[1:])
    end = np.append(start[1:], n)
    return mix((c[end] - c[start]) * powers("inv", n)[start] + (end - start).astype(np.uint64)), np.searchsorted(start, of)


def levels_of(texts: list[str], most: int):
    """(names, offsets) of each level from 1 to most."""
    of = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) for t in texts], out=of[1:])
    names = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    names = mix(names + U(0x8EBC6AF09C88C6E3))
    for _ in range(most):
        if len(names):
            names, of = parse(names, of)
        yield names, of


def sketches(texts: list[str]) -> np.ndarray:
    """(texts, SLOTS * levels) 16-bit minima; rows of empty texts are 0."""
    out = np.zeros((len(texts), SLOTS * len(LEVELS)), np.uint16)
    full = np.array([len(t) > 0 for t in texts], bool)
    for k, (names, of) in enumerate(levels_of(texts, max(LEVELS)), 1):
        if k in LEVELS and full.any():
            col = LEVELS.index(k) * SLOTS
            at = of[:-1][full]
            for j in range(SLOTS):
                out[full, col + j] = mix(np.minimum.reduceat(names * ORDERS[j], at)) >> U(48)
    return out


def fingerprints(texts: list[str]) -> list[str]:
    return [EMPTY if not t else r.byteswap().tobytes().hex() for t, r in zip(texts, sketches(texts))]


def likeness(a: str, b: str) -> float:
    """Share of equal minima."""
    return sum(a[i : i + 4] == b[i : i + 4] for i in range(0, len(a), 4)) / (len(a) // 4)


def _chunks(rows, most: int = 1 << 20):
    part, size = [], 0
    for r in rows:
        part.append(r)
        size += len(r[1])
        if size >= most:
            yield part
            part, size = [], 0
    if part:
        yield part


OUT_DDL = "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, text and block, in descending order within each block; every
    block ends with a copy (halo = 1) of the document that follows it, so no
    block has to see another.  The first follows the last."""
    spark = docs.sparkSession
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    bounds = range_bounds(src, "doc_id", partitions(spark))
    src = src.withColumn("block", block_of("doc_id", bounds))
    tops = {r["block"]: r["top"] for r in src.groupBy("block").agg(F.max("doc_id").alias("top")).collect()}  # one a block
    order = sorted((b for b in tops if tops[b] is not None), reverse=True)
    after = list(zip(order, order[1:] + order[:1])) if order else []
    if 0 in tops and tops[0] is None and order:  # a block of null ids alone comes last
        after = [(b, n) for b, n in after[:-1]] + [(order[-1], None), (0, order[0])]
    halo = spark.createDataFrame([(tops[n], b) for b, n in after if n is not None], "top bigint, target int")
    own = src.withColumn("halo", F.lit(0))
    more = src.join(F.broadcast(halo), src["doc_id"] == halo["top"]).select("doc_id", "text", F.col("target").alias("block"), F.lit(1).alias("halo"))
    return own.union(more).repartitionById(len(bounds) + 1, F.col("block")).sortWithinPartitions("halo", F.col("doc_id").desc_nulls_last(), "text")


def digest(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited text, and likenesses."""
    prepare(docs.sparkSession)
    schema = arrow_schema(OUT_DDL)

    def emit(part, following):
        texts = [t for _, t in part] + [following]
        edited = []
        for a, b in zip(texts, texts[1:]):
            n = len(a) // 3
            edited.append(a[: len(a) - n] + b[:n])
        s = sketches(texts + edited)
        m, k = len(texts), len(part)
        hexed = [EMPTY if not t else r.byteswap().tobytes().hex() for t, r in zip(texts + edited, s)]
        empty = np.array([not t for t in texts + edited])

        def alike(i, j):
            same = (s[i] == s[j]).mean(1)
            return np.where(empty[i] != empty[j], 0.0, same)

        i = np.arange(k)
        return pa.RecordBatch.from_pydict({
            "doc_id": [d for d, _ in part], "n_chars": [len(t) for _, t in part], "edited_sha256": [hashlib.sha256(e.encode("utf-8", "surrogatepass")).hexdigest() for e in edited],
            "fingerprint": hexed[:k], "edited_fingerprint": hexed[m:], "near_edited": alike(i, m + i), "near_next": alike(i, i + 1),
        }, schema=schema)

    def work(it):
        wait, first, ended = [], None, False
        for batch in it:
            ids, texts, halo = (batch.column(batch.schema.get_field_index(c)) for c in ("doc_id", "text", "halo"))
            for a in range(0, batch.num_rows, 1024):
                rows = list(zip(ids.slice(a, 1024).to_pylist(), texts.slice(a, 1024).to_pylist(), halo.slice(a, 1024).to_pylist()))
                if first is None and rows:
                    first = rows[0][1]
                own = wait + [(d, t) for d, t, h in rows if not h]
                wait = own[-1:]
                at = 0
                for part in _chunks(own[:-1]):
                    at += len(part)
                    yield emit(part, own[at][1])
                ends = [t for _, t, h in rows if h]
                if ends and wait:
                    yield emit(wait, ends[0])
                    wait, ended = [], True
        if wait and not ended:
            yield emit(wait, first)

    return with_next(docs).select("doc_id", "text", "halo").mapInArrow(tidy(work), OUT_DDL)
