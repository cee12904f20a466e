"""Benchmark decontamination with an Aho-Corasick automaton.

Texts are reduced to words (A-Z lower-cased, anything else in ASCII but digits
and a-z separates), joined by single blanks.  The windows of all items form one
automaton per block of ``block_windows`` windows; each text is scanned once per
block and every hit is mapped back to words and byte offsets of the original.

Null text has no words.  An empty benchmark hits nothing.  Items whose text is
null or without words have no window.  Repeated windows report all their items.
Repeated rows get equal results, an empty table no row.  Extra columns pass through ``mark``
untouched; where one has the name of a result, the result's name gets an underscore behind it.
"""

from __future__ import annotations

import hashlib
import itertools
import uuid

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import arrow_schema, free_names, prepare, tidy

WINDOW = 10
BLOCK_WINDOWS = 200_000
_FOLD = bytearray(b" " * 128 + bytes(range(128, 256)))
_FOLD[48:58] = range(48, 58)
_FOLD[97:123] = range(97, 123)
_FOLD[65:91] = range(97, 123)
FOLD = bytes(_FOLD)
HITS_DDL = "n_words bigint, hit_from array<int>, hit_to array<int>, items array<string>"


def fold_words(text: bytes) -> list[bytes]:
    return text.translate(FOLD).split()


def item_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(item_id, windows): every run of ``window`` words of an item, or all its words if fewer."""
    t = F.translate(F.coalesce(F.col("text"), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    words = F.filter(F.split(t, r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"), lambda w: w != "")
    n = F.size("w")
    at = F.when(n > window, F.sequence(F.lit(1), n - window + 1)).otherwise(F.array(F.lit(1)))
    return benchmark.select(F.col("item_id").cast("string").alias("item_id"), words.alias("w")).where(n > 0).select("item_id", F.explode(F.transform(at, lambda i: F.array_join(F.slice("w", i, window), " "))).alias("win"))


def _blocks(benchmark: DataFrame, window: int, block_windows: int):
    """Windows with their items, in driver-sized blocks streamed one partition at a time."""
    rows = item_windows(benchmark, window).groupBy("win").agg(F.array_sort(F.collect_set("item_id")).alias("items")).toLocalIterator()
    rows = iter(rows)
    while block := [(r["win"], r["items"]) for r in itertools.islice(rows, block_windows)]:
        yield block


_automata: dict[str, object] = {}


def _automaton(block):
    """The worker's automaton of a broadcast block, built once."""
    key = block.value[0]
    if key not in _automata:
        _automata.clear()
        a = ahocorasick.Automaton()
        for win, items in block.value[1]:
            b = win.encode()
            a.add_word(f" {b.decode('latin-1')} ", (b.count(b" ") + 1, items))
        if len(a):
            a.make_automaton()
        _automata[key] = a
    return _automata[key]


def scan(text: bytes, automaton) -> tuple[int, np.ndarray, set[str]]:
    """Number of words, whether each is hit (empty if none is), items that occur."""
    words = fold_words(text)
    if not words or not len(automaton):
        return len(words), np.zeros(0, bool), set()
    line = (b" %b " % b" ".join(words)).decode("latin-1")
    found = [(end, n, items) for end, (n, items) in automaton.iter(line)]
    if not found:
        return len(words), np.zeros(0, bool), set()
    gaps = np.flatnonzero(np.frombuffer(line.encode("latin-1"), np.uint8) == 32)
    ends = np.searchsorted(gaps, [e for e, _, _ in found])
    delta = np.zeros(len(words) + 1, np.int64)
    np.add.at(delta, ends - np.array([n for _, n, _ in found]), 1)
    np.add.at(delta, ends, -1)
    return len(words), np.cumsum(delta[:-1]) > 0, set().union(*(i for _, _, i in found))


def runs(hit: np.ndarray) -> tuple[list[int], list[int]]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))
    return edge[::2].tolist(), edge[1::2].tolist()


def mark(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_windows: int = BLOCK_WINDOWS) -> DataFrame:
    """docs and ``contamination`` columns: n_words, hit_from/hit_to (word runs,
    end exclusive) and items.  Blocks of windows are taken in turn over rows
    that carry their hits along, so no block needs a shuffle."""
    spark = docs.sparkSession
    prepare(spark)
    own = free_names(docs.columns, *RESULTS)
    out = docs
    first = True
    for block in itertools.chain(_blocks(benchmark, window, block_windows), [None]):
        if block is None and not first:
            break
        out = _pass(out, spark.sparkContext.broadcast((uuid.uuid4().hex, block or [])), first, own)
        first = False
    return out


HITS_FIELDS = list(arrow_schema(HITS_DDL))
RESULTS = tuple(f.name for f in HITS_FIELDS)


def _pass(docs: DataFrame, block, first: bool, own: list[str]) -> DataFrame:
    from pyspark.sql import types as T

    kinds = (T.LongType(), T.ArrayType(T.IntegerType()), T.ArrayType(T.IntegerType()), T.ArrayType(T.StringType()))
    schema = T.StructType([f for f in docs.schema.fields if f.name not in own] + [T.StructField(n, k) for n, k in zip(own, kinds)])

    def work(it):
        for batch in it:
            auto = _automaton(block)
            names = batch.schema.names
            texts = batch.column(names.index("text")).cast(pa.binary())
            cols = {n: [] for n in RESULTS}
            old = None if first else {r: batch.column(names.index(n)).to_pylist() for r, n in zip(RESULTS, own)}
            for i, t in enumerate(x for a in range(0, len(texts), 256) for x in texts.slice(a, 256).to_pylist()):
                n, hit, items = scan(t or b"", auto)
                if old and old["hit_from"][i]:
                    hit = hit if len(hit) else np.zeros(n, bool)
                    for f, e in zip(old["hit_from"][i], old["hit_to"][i]):
                        hit[f:e] = True
                    items |= set(old["items"][i])
                f, e = runs(hit) if len(hit) else ([], [])
                for name, v in zip(RESULTS, (n, f, e, sorted(items))):
                    cols[name].append(v)
            keep = [i for i, n in enumerate(names) if n not in own]
            yield pa.RecordBatch.from_arrays([batch.column(i) for i in keep] + [pa.array(cols[f.name], f.type) for f in HITS_FIELDS], names=[names[i] for i in keep] + own)

    return docs.mapInArrow(tidy(work), schema)


def original_spans(text: str, hit_from: list[int], hit_to: list[int]) -> list[tuple[int, int]]:
    """Code-point spans of hit word runs in the original text."""
    import re

    at = [m.span() for m in re.finditer(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", text)]
    return [(at[f][0], at[e - 1][1]) for f, e in zip(hit_from, hit_to)]


def digest(docs: DataFrame, benchmark: DataFrame, **kw) -> DataFrame:
    """One row per document: counts, hash of its items and the verdict."""
    m = mark(docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text")), benchmark, **kw)
    hit = F.aggregate(F.arrays_zip("hit_from", "hit_to"), F.lit(0).cast("long"), lambda s, x: s + (x["hit_to"] - x["hit_from"]))
    return m.select("doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.size("hit_from") > 0).alias("contaminated"))


def sha256_of_items(items: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
