"""Near-duplicate documents: b-bit MinHash, bands, exact confirmation, components.

1. One pass reads every text once: word shingles, K minima under K
   multiply-shift orders, their low B bits packed as signature, BANDS keys over
   the full minima, and two keys of the whole word sequence.
2. Texts of one word sequence are one class, numbered on writing; only classes go on.
3. Bands with more than one class give candidates, in three steps that are
   linear in the band's size, or bounded by what documents truly share:
   each class against the band's head; each class of a band that still holds
   several components against the band's hub, the class whose shingles are most
   frequent among the rest; and each class outside its band's largest component
   (a stranger) against all classes that a prefix filter leaves.
4. The prefix filter is exact.  All shingles of the remaining classes are put in one
   order, rare ones first.  If two classes reach the threshold, and the first
   shingle they share stands at places i and j of their lists, then neither
   n_a - i nor n_b - j is below the overlap that the threshold asks of sizes n_a and
   n_b.  So a stranger meets only classes that share one of its rarest shingles.
   No pair of a band is left out, and none is capped.
5. The collision-corrected similarity of two signatures discards pairs that are
   SLACK standard errors below the threshold; the rest is confirmed on the full
   shingle sets.
6. Components by pointer jumping and smallest-label exchange, in written tables.

With K=128 in 32 bands of 4, a pair of similarity 0.8 shares no band with
probability 5e-8.

Null and empty texts have no shingles and stand alone.  Rows with a null id
stand alone with component null.  Rows of a repeated id are told apart by their
texts: each is linked by its own text, and equal rows get equal results.  Extra
columns don't reach the result; the result of an empty table is empty.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import Scratch, arrow_schema, prepare, tidy
from .textvec import Words, column_bytes, slices

K, BANDS, BITS = 128, 32, 8
SLACK = 6.0
_rng = np.random.Generator(np.random.PCG64(7))
ORDERS = _rng.integers(1, 2**63, K, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
PASS_DDL = "doc_id bigint, n_shingles bigint, k1 bigint, k2 bigint, bands array<bigint>, sig binary"


def minima(sh: np.ndarray, of: np.ndarray) -> np.ndarray:
    """(documents, K) smallest shingle values by order; all ones where there is no shingle."""
    out = np.full((len(of) - 1, K), np.iinfo(np.uint64).max, np.uint64)
    full = np.flatnonzero(np.diff(of))
    if len(full):
        at = of[:-1][full]
        step = 1 << 15  # shingles at a time, so that products stay in cache
        cuts = [0]
        while cuts[-1] < len(at):
            cuts.append(max(cuts[-1] + 1, int(np.searchsorted(at, at[cuts[-1]] + step))))
        for a, b in zip(cuts, cuts[1:]):
            lo, hi = at[a], at[b] if b < len(at) else len(sh)
            part, rel = sh[lo:hi], at[a:b] - lo
            for j in range(K):
                out[full[a:b], j] = np.minimum.reduceat(part * ORDERS[j], rel)
    return out


def distinct_sizes(sh: np.ndarray, of: np.ndarray) -> np.ndarray:
    return np.array([len(np.unique(sh[a:b])) if b - a > 1 else b - a for a, b in zip(of[:-1], of[1:])], np.int64)


def signatures(docs: DataFrame, size: int) -> DataFrame:
    """The one pass over texts."""
    schema = arrow_schema(PASS_DDL)
    rows = K // BANDS

    def work(it):
        for batch in it:
            for part in slices(batch, "text", 2 << 20):
                names = part.schema.names
                w = Words(*column_bytes(part.column(names.index("text"))))
                sh, of = w.shingles(size)
                k1, k2 = w.sequence_keys()
                m = minima(sh, of)
                bands = np.tile(np.arange(1, BANDS + 1, dtype=np.uint64), (len(m), 1))  # keys of different bands never meet
                for r in range(rows):
                    bands = (bands ^ m[:, r::rows]) * np.uint64(0x9E3779B97F4A7C15)
                    bands ^= bands >> np.uint64(29)
                low = ((m * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(64 - BITS)).astype(np.uint8)
                flat = pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1, dtype=np.int32) * BANDS), pa.array(bands.view(np.int64).ravel()))
                yield pa.RecordBatch.from_arrays([part.column(names.index("doc_id")), pa.array(distinct_sizes(sh, of)), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), flat, pa.array([r.tobytes() for r in low], pa.binary())], schema=schema)

    return docs.mapInArrow(tidy(work), PASS_DDL)


def similarity(a: bytes, b: bytes) -> float:
    """Jaccard estimate from packed low bits, corrected for chance collisions."""
    same = float(np.mean(np.frombuffer(a, np.uint8) == np.frombuffer(b, np.uint8)))
    c = 2.0**-BITS
    return max(0.0, (same - c) / (1 - c))


def _confirmed(pairs: DataFrame, texts: DataFrame, size: int, num: int, den: int, scratch: Scratch) -> DataFrame:
    """Those pairs (a, b) whose signatures don't rule them out and whose full
    sets meet den * intersection >= num * union."""
    t = num / den
    least = t - SLACK * math.sqrt(t * (1 - t) / K)

    def near(it):
        for batch in it:
            a, b = (np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint8).reshape(-1, K) for i in (2, 3))
            c = 2.0**-BITS
            est = ((a == b).mean(1) - c) / (1 - c)
            keep = batch.filter(pa.array(est >= least))
            yield pa.RecordBatch.from_arrays([keep.column(0), keep.column(1)], names=["a", "b"])

    sigs = texts.select("rep", "sig")
    est = scratch.write(pairs).join(sigs.toDF("a", "sa"), "a").join(sigs.toDF("b", "sb"), "b").select("a", "b", "sa", "sb").mapInArrow(tidy(near), "a bigint, b bigint")
    body = texts.select("rep", "text")
    both = est.join(body.toDF("a", "ta"), "a").join(body.toDF("b", "tb"), "b").select("a", "b", "ta", "tb")

    def exact(it):
        for batch in it:
            a, b = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            keep, done = [], 0
            for part in slices(batch, "ta", 2 << 20):
                sets = []
                for i in (2, 3):
                    sh, of = Words(*column_bytes(part.column(i))).shingles(size)
                    sets.append([np.unique(sh[x:y]) for x, y in zip(of[:-1], of[1:])])
                for k, (x, y) in enumerate(zip(*sets)):
                    both_ = len(np.intersect1d(x, y, assume_unique=True))
                    if both_ and den * both_ >= num * (len(x) + len(y) - both_):
                        keep.append(done + k)
                done += part.num_rows
            yield pa.RecordBatch.from_pydict({"a": [a[i] for i in keep], "b": [b[i] for i in keep]}, schema=arrow_schema("a bigint, b bigint"))

    return scratch.write(both.mapInArrow(tidy(exact), "a bigint, b bigint"))


def components(links: DataFrame, scratch: Scratch) -> DataFrame:
    """(rep, comp): the smallest id reachable from each end of the links.

    Alternates two steps on a written edge table until it is a star forest:
    every node hands the smallest neighbour to its larger neighbours, then to
    its smaller ones.  Each step is one aggregation and one join by node.
    """
    e = scratch.write(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    while True:
        # larger neighbours to the smallest of node and neighbours
        both = e.union(e.select("v", "u")).toDF("u", "v")
        low = scratch.write(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")))  # written, so that a hot node's join can be split
        e1 = scratch.write(both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct())
        # smaller neighbours and the node itself to the smallest of them
        low = e1.groupBy("u").agg(F.min("v").alias("m"))
        e2 = scratch.write(e1.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low).where("u <> v").distinct())
        heads = e2.select("v").distinct()
        n = e2.groupBy("u").agg(F.count("*").alias("n")).where("n > 1").limit(1).count() or e2.select("u").join(heads, F.col("u") == heads["v"], "left_semi").limit(1).count()
        e = e2
        if not n:
            return e.select(F.col("u").alias("rep"), F.col("v").alias("comp"))


def clusters(docs: DataFrame, size: int = 5, threshold: tuple[int, int] = (80, 100)) -> DataFrame:
    """doc_id, n_shingles and component_id of every document; documents are
    linked whose shingle sets meet threshold[1] * intersection >= threshold[0] * union."""
    spark = docs.sparkSession
    prepare(spark)
    num, den = threshold
    scratch = Scratch(spark, "near")
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    seen = scratch.write(signatures(src, size))
    live = seen.where("n_shingles > 0 and doc_id is not null")
    classes = scratch.write(live.groupBy("k1", "k2").agg(F.min("doc_id").alias("head")).withColumn("rep", F.monotonically_increasing_id()))
    # equal rows of an id meet in one class: any of them will do
    own = live.join(classes, ["k1", "k2"]).where("doc_id = head").dropDuplicates(["k1", "k2"])
    reps = scratch.write(own.select("rep", "head", "k1", "k2", F.col("n_shingles").alias("n"), "sig", "bands"))
    band = reps.select("rep", F.explode("bands").alias("key"))
    held = scratch.write(band.groupBy("key").agg(F.min("rep").alias("first"), F.max("rep").alias("last")).where("first <> last").select("key", "first"))
    band = scratch.write(band.join(held, "key"))
    texts = scratch.write(_texts(src, reps.join(band.select("rep").distinct(), "rep", "left_semi")))
    pairs = band.where("rep <> first").select(F.col("rep").alias("a"), F.col("first").alias("b")).distinct()
    comp = components(_confirmed(pairs, texts, size, num, den, scratch), scratch)
    left = _mixed(band, comp, scratch)
    if left.limit(1).count():
        spread = scratch.write(_prefixes(texts.join(left.select("rep").distinct(), "rep", "left_semi"), size, num, den, scratch))
        # the class whose shingles are most frequent stands nearest to all others
        mean = spread.groupBy("rep").agg(F.avg("mean").alias("mean"))
        hub = left.join(mean, "rep", "left").groupBy("key").agg(F.max(F.struct(F.coalesce("mean", F.lit(0.0)), "rep", "comp")).alias("x")).select("key", F.col("x.rep").alias("hub"), F.col("x.comp").alias("hub_comp"))
        pairs = left.join(hub, "key").where("comp <> hub_comp").select(F.greatest("rep", "hub").alias("a"), F.least("rep", "hub").alias("b")).distinct()
        comp = _joined(comp, _confirmed(pairs, texts, size, num, den, scratch), scratch)
        left = _mixed(band, comp, scratch)
        strangers = scratch.write(left.where("comp <> main").select("rep").distinct())
        place = scratch.write(spread.where("pos is not null").join(comp, "rep", "left").select("rep", "h", "n", "pos", F.coalesce("comp", "rep").alias("comp")))
        a = place.join(strangers, "rep", "left_semi").toDF("a", "h", "na", "pa", "ca")
        b = place.toDF("b", "h", "nb", "pb", "cb")
        # the overlap that both sizes ask for must fit behind the shared shingle's places
        fits = F.lit(num + den) * F.least(F.col("na") - F.col("pa"), F.col("nb") - F.col("pb")) >= F.lit(num) * (F.col("na") + F.col("nb"))
        pairs = a.join(b, (a["h"] == b["h"]) & fits & (F.col("ca") != F.col("cb"))).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
        comp = _joined(comp, _confirmed(pairs, texts, size, num, den, scratch), scratch)
    member = classes.join(comp, "rep", "left").select("k1", "k2", "head", F.coalesce("comp", "rep").alias("comp"))
    least = member.groupBy("comp").agg(F.min("head").alias("component"))
    known = scratch.write(member.join(least, "comp").select("k1", "k2", "component"))
    scratch.clear(seen, known)
    return seen.select("doc_id", "n_shingles", "k1", "k2").join(known, ["k1", "k2"], "left").select("doc_id", "n_shingles", F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).otherwise(F.col("doc_id")).alias("component_id"))


def _texts(src: DataFrame, reps: DataFrame) -> DataFrame:
    """rep, text, sig and n of the given classes.  Texts are found by their
    class's id and told apart by their own keys, as ids may repeat."""

    def work(it):
        for batch in it:
            for part in slices(batch, "text", 2 << 20):
                k1, k2 = Words(*column_bytes(part.column(1))).sequence_keys()
                yield pa.RecordBatch.from_arrays([part.column(1), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64))], names=["text", "k1", "k2"])

    mine = src.join(reps.select(F.col("head").alias("doc_id")).distinct(), "doc_id", "left_semi").select("doc_id", "text")
    keyed = mine.mapInArrow(tidy(work), "text string, k1 bigint, k2 bigint")
    return keyed.join(reps.select("rep", "sig", "n", "k1", "k2"), ["k1", "k2"]).dropDuplicates(["k1", "k2"]).select("rep", "text", "sig", "n")


def _mixed(band: DataFrame, comp: DataFrame, scratch: Scratch) -> DataFrame:
    """key, rep, comp and main (the largest component) of bands that hold several components."""
    now = scratch.write(band.select("key", "rep").join(comp, "rep", "left").select("key", "rep", F.coalesce("comp", "rep").alias("comp")))
    by_comp = now.groupBy("key", "comp").agg(F.count("*").alias("n"))
    mixed = by_comp.groupBy("key").agg(F.max(F.struct("n", "comp")).alias("main"), F.count("*").alias("comps")).where("comps > 1").select("key", F.col("main.comp").alias("main"))
    return scratch.write(now.join(mixed, "key"))


def _prefixes(texts: DataFrame, size: int, num: int, den: int, scratch: Scratch) -> DataFrame:
    """rep, h, n, pos: the places of a class's shared shingles, rare ones first,
    as far as they can be the first that two linked classes share; and mean, the
    mean frequency of its shingles.  Shingles of one class alone come before all
    others and take part in no pair, so they are only counted."""
    schema = arrow_schema("rep bigint, h bigint")

    def work(it):
        for batch in it:
            for part in slices(batch, "text", 2 << 20):
                sh, of = Words(*column_bytes(part.column(1))).shingles(size)
                each = [np.unique(sh[x:y]) for x, y in zip(of[:-1], of[1:])]
                rep = np.repeat(part.column(0).to_numpy(), [len(e) for e in each])
                yield pa.RecordBatch.from_arrays([pa.array(rep), pa.array(np.concatenate(each).view(np.int64))], schema=schema)

    every = scratch.write(texts.select("rep", "text").mapInArrow(tidy(work), "rep bigint, h bigint"))
    often = every.groupBy("h").agg(F.count("*").alias("c")).where("c > 1")
    shared = every.join(often, "h").join(texts.select("rep", "n"), "rep")
    by_rep = Window.partitionBy("rep")
    placed = shared.select("rep", "h", "n", (F.col("n") - F.count("*").over(by_rep) + F.row_number().over(by_rep.orderBy("c", "h")) - 1).alias("pos"), ((F.sum("c").over(by_rep) + F.col("n") - F.count("*").over(by_rep)) / F.col("n")).alias("mean"), F.row_number().over(by_rep.orderBy("c", "h")).alias("i"))
    can = F.lit(den) * (F.col("n") - F.col("pos")) >= F.lit(num) * F.col("n")
    return placed.where(can | (F.col("i") == 1)).select("rep", "h", "n", F.when(can, F.col("pos")).alias("pos"), "mean")


def _joined(comp: DataFrame, found: DataFrame, scratch: Scratch) -> DataFrame:
    """Components after more links: those of the graph of components, composed."""
    if found.limit(1).count() == 0:
        return comp
    to = lambda df, c: df.join(comp.toDF(c, "_c"), c, "left").withColumn(c, F.coalesce("_c", c)).drop("_c")
    up = components(to(to(found, "a"), "b"), scratch).toDF("comp", "_up")
    moved = comp.join(up, "comp", "left").select("rep", F.coalesce("_up", "comp").alias("comp"))
    fresh = up.select(F.col("comp").alias("rep"), F.col("_up").alias("comp"))
    return scratch.write(moved.union(fresh).groupBy("rep").agg(F.min("comp").alias("comp")))


def digest(docs: DataFrame, size: int = 4) -> DataFrame:
    c = clusters(docs, size)
    return c.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))
