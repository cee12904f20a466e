"""Resolution pyramid and the coarse-to-fine partition.

A raster of a level is (scene_id, y, x, cls-wise mean sem, mean emb); its edges
are 4-neighbour affinities between foreground cells.  ``partition_pyramid`` runs the
whole cascade of a scene inside one task after one shuffle.  The level steps
(``pool2``, ``pool_edges``, ``upsample2``, ``reclaim_rim``) are dataframe operators of their own.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .adopt import adopt_sync_arrays
from .contract import Graph
from .positional import positional_labels
from .streams import per_scene


def pool2(px: DataFrame, sem: int = 9, emb: int | None = None) -> DataFrame:
    """Next coarser level: means over 2x2 cells."""
    means = [F.array(*[F.avg(F.element_at("sem", i + 1)) for i in range(sem)]).alias("sem")]
    if emb:
        means.append(F.array(*[F.avg(F.element_at("emb", i + 1)) for i in range(emb)]).alias("emb"))
    return px.groupBy("scene_id", F.floor(F.col("y") / 2).cast("int").alias("y"), F.floor(F.col("x") / 2).cast("int").alias("x")).agg(*means)


def pool_edges(edges: DataFrame, width: int) -> DataFrame:
    """Mean of the fine edges that cross between two coarse cells."""
    half = (width + 1) // 2
    cell = lambda c: (F.floor(F.floor(F.col(c) / width) / 2) * half + F.floor(F.pmod(F.col(c), F.lit(width)) / 2)).cast("long")
    return edges.select("scene_id", cell("u").alias("u"), cell("v").alias("v"), "aff").where("u <> v").groupBy("scene_id", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).agg(F.avg("aff").alias("aff"))


def upsample2(labels: DataFrame, height: int, width: int) -> DataFrame:
    """Nearest doubling of (scene_id, y, x, label), clipped to height x width."""
    o = F.explode(F.array(*[F.struct(F.lit(dy).alias("dy"), F.lit(dx).alias("dx")) for dy in (0, 1) for dx in (0, 1)]))
    return labels.withColumn("o", o).select("scene_id", (2 * F.col("y") + F.col("o.dy")).cast("int").alias("y"), (2 * F.col("x") + F.col("o.dx")).cast("int").alias("x"), "label").where((F.col("y") < height) & (F.col("x") < width))


def reclaim_rim(labels: DataFrame, rim: str = "both") -> DataFrame:
    """Labels with object rims set to null; "inner" keeps the rim pixels of
    background (0).  The frame is no rim."""
    from .grid import rim_flag

    flagged = rim_flag(labels, "label", side=None)
    keep = (F.col("label") == 0) if rim == "inner" else F.lit(False)
    return flagged.select("scene_id", "y", "x", F.when(F.col("rim") & ~keep, F.lit(None)).otherwise(F.col("label")).alias("label"))


def rim_mask(lab: np.ndarray) -> np.ndarray:
    """Cells of a label raster with a 4-neighbour of another label."""
    m = np.zeros(lab.shape, bool)
    d = lab[1:] != lab[:-1]
    m[1:] |= d
    m[:-1] |= d
    d = lab[:, 1:] != lab[:, :-1]
    m[:, 1:] |= d
    m[:, :-1] |= d
    return m


PAIRS = 1 << 16  # pairs of segments compared at a time


def pair_affinity(sem: np.ndarray, emb: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Class similarity times embedding affinity of the rows' pairs (i, j)."""
    out = np.empty(len(i))
    own = np.where(sem > 0, sem * np.log2(np.where(sem > 0, sem, 1)), 0).sum(1)
    for a in range(0, len(i), PAIRS):
        p, q = i[a : a + PAIRS], j[a : a + PAIRS]
        m = (sem[p] + sem[q]) / 2
        mid = np.where(m > 0, m * np.log2(np.where(m > 0, m, 1)), 0).sum(1)
        js = 1 - ((own[p] + own[q]) / 2 - mid)
        out[a : a + PAIRS] = js * np.exp(-np.log(2.0) * ((emb[p] - emb[q]) ** 2).sum(1))
    return out


def group_segments(lab: np.ndarray, sem: np.ndarray, emb: np.ndarray, beta: float | None, t: float) -> np.ndarray:
    """Grouping of a label raster's segments (0 is background); beta None
    groups without positions.  One pass over the raster gives boxes and means."""
    ids, inv = np.unique(lab, return_inverse=True)
    lead = int(ids[0] == 0)
    if len(ids) - lead < 2 or beta == "none":
        return lab
    n, inv = len(ids), inv.reshape(lab.shape)
    ys, xs = np.indices(lab.shape)
    box = []
    for at in (ys, xs):
        low, high = np.full(n, at.max()), np.zeros(n, np.int64)
        np.minimum.at(low, inv, at)
        np.maximum.at(high, inv, at)
        box += [low, high]
    count = np.bincount(inv.ravel(), minlength=n)
    mean = lambda a: np.stack([np.bincount(inv.ravel(), a[..., c].ravel(), n) for c in range(a.shape[-1])], 1) / count[:, None]
    i, j = (k + lead for k in np.triu_indices(n - lead, 1))
    w = pair_affinity(mean(sem), mean(emb), i, j)
    boxes = {int(ids[k]): tuple(int(b[k]) for b in box) for k in range(lead, n)}
    to = positional_labels(boxes, ids[i], ids[j], w, 0.0 if beta is None else beta, t).labels()
    return np.array([to.get(int(x), 0) if x else 0 for x in ids])[inv]


def contract_level(lab: np.ndarray, right: np.ndarray, down: np.ndarray, fg: np.ndarray, t: float) -> np.ndarray:
    """Contraction of a level from a start labelling: 0 and non-foreground
    cells stay out, negative means unlabelled (a node of its own).  Cell ids
    are y * width + x + 1; segments are named by their smallest cell."""
    h, w = lab.shape
    cell = np.arange(1, h * w + 1).reshape(h, w)
    start = np.where(fg, np.where(lab > 0, lab + h * w, cell), 0)
    # a labelled segment is a node named by its smallest cell
    ids, first, inv = np.unique(start, return_index=True, return_inverse=True)
    start = np.where(ids > h * w, first + 1, ids)[inv].reshape(h, w)
    us, vs, ws = [], [], []
    for a, b, wt in ((start[:, :-1], start[:, 1:], right[:, :-1]), (start[:-1], start[1:], down[:-1])):
        ok = (a > 0) & (b > 0) & (a != b) & ~np.isnan(wt)
        us.append(np.minimum(a, b)[ok])
        vs.append(np.maximum(a, b)[ok])
        ws.append(wt[ok])
    u, v, x = (np.concatenate(z) for z in (us, vs, ws))
    key = u * (h * w + 1) + v
    k, inv = np.unique(key, return_inverse=True)
    mean = np.bincount(inv, x) / np.maximum(np.bincount(inv), 1)
    ids, inv = np.unique(start, return_inverse=True)
    g = Graph(ids[ids > 0], k // (h * w + 1), k % (h * w + 1), mean)
    to = g.run(t)
    return np.array([to[int(c)] if c else 0 for c in ids], np.int64)[inv].reshape(h, w)


def adopt_level(lab: np.ndarray, right, down, fg, t: float) -> np.ndarray:
    """Synchronous adoption on a raster: unlabelled foreground cells (negative)."""
    h, w = lab.shape
    cell = np.arange(h * w).reshape(h, w)
    inside = fg.ravel()
    us, vs, ws = [], [], []
    for a, b, wt in ((cell[:, :-1], cell[:, 1:], right[:, :-1]), (cell[:-1], cell[1:], down[:-1])):
        ok = inside[a] & inside[b] & ~np.isnan(wt)
        us.append(a[ok])
        vs.append(b[ok])
        ws.append(wt[ok])
    start = np.where(inside & (lab.ravel() > 0), lab.ravel(), 0).astype(np.int64)
    done, known = adopt_sync_arrays(start, start > 0, *(np.concatenate(x) for x in (us, vs, ws)), t)
    return np.where(known & inside, done, 0).reshape(h, w)


def _pool(a: np.ndarray) -> np.ndarray:
    """Means over 2x2 cells, odd ends on their own, nan ignored."""
    h, w = a.shape[:2]
    pad = np.full((h + h % 2, w + w % 2, *a.shape[2:]), np.nan)
    pad[:h, :w] = a
    blocks = pad.reshape(pad.shape[0] // 2, 2, pad.shape[1] // 2, 2, *a.shape[2:])
    n = (~np.isnan(blocks)).sum((1, 3))
    return np.where(n > 0, np.nansum(blocks, (1, 3)) / np.maximum(n, 1), np.nan)


def pooled_affinities(right: np.ndarray, down: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Affinities of the next coarser level: mean of the two crossing fine edges."""

    def one(a):  # a: affinity to the right neighbour
        h, w = a.shape
        cross = np.full((h + h % 2, (w + w % 2) // 2), np.nan)
        got = a[:, 1::2]
        cross[:h, : got.shape[1]] = got
        b = cross.reshape(-1, 2, cross.shape[1])
        n = (~np.isnan(b)).sum(1)
        return np.where(n > 0, np.nansum(b, 1) / np.maximum(n, 1), np.nan)

    return one(right), one(down.T).T


def cascade(sem, emb, right, down, levels: int = 4, finest: str = "contract", beta=0.5, t: float = 0.5) -> np.ndarray:
    """Labels of one scene: coarsest level first, each finer one starting from
    the doubled labels with their rims open.  beta: 0.5 groups by position,
    None groups without, "none" doesn't group."""
    pyr = [(sem, emb, right, down)]
    for _ in range(levels - 1):
        s, e, r, d = pyr[-1]
        pyr.append((_pool(s), _pool(e), *pooled_affinities(r, d)))
    lab = None
    for k in range(levels - 1, -1, -1):
        s, e, r, d = pyr[k]
        fg = s.argmax(-1) != 0
        if lab is None:
            lab = np.full(fg.shape, -1)
        else:
            up = lab.repeat(2, 0).repeat(2, 1)[: fg.shape[0], : fg.shape[1]]
            lab = np.where(rim_mask(up) | ((up == 0) & fg), -1, up)
            if k == 0 and finest == "adopt":
                return adopt_level(lab, r, d, fg, t)
        lab = contract_level(lab, r, d, fg, t)
        lab = group_segments(lab, s, e, beta, t)
    return lab


def raster_arrays(cols, side: int, emb: int, k: int = 9):
    """sem, emb, right and down of the cells of one scene."""
    at = cols["pixel"].astype(int)
    out = [np.zeros((side * side, k)), np.zeros((side * side, emb)), np.full(side * side, np.nan), np.full(side * side, np.nan)]
    for a, c in zip(out, ("sem", "emb", "right", "down")):
        a[at] = cols[c].reshape(len(at), *a.shape[1:])
    return [a.reshape(side, side, *a.shape[1:]) for a in out]


def partition_pyramid(px: DataFrame, edges: DataFrame, side: int, emb: int, levels: int = 4, finest: str = "contract", beta=0.5, threshold: float = 0.5) -> DataFrame:
    """(scene_id, pixel, label) of every foreground pixel, one task per scene.
    px: scene_id, pixel, sem, emb for all cells; edges: scene_id, u, v, aff."""
    e = edges.select("scene_id", F.col("u").alias("pixel"), F.col("v").alias("v"), "aff", F.array().cast("array<double>").alias("vec"))
    p = px.select("scene_id", "pixel", F.lit(-1).cast("long").alias("v"), F.lit(0.0).alias("aff"), F.concat("sem", "emb").alias("vec"))

    def kernel(scene, cols):
        cell = cols["v"] == -1
        sem = np.zeros((side, side, 9))
        em = np.zeros((side, side, emb))
        at = cols["pixel"][cell].astype(int)
        vec = cols["vec"].reshape(-1, 9 + emb)  # edges have none
        sem.reshape(-1, 9)[at] = vec[:, :9]
        em.reshape(-1, emb)[at] = vec[:, 9:]
        right, down = np.full((side, side), np.nan), np.full((side, side), np.nan)
        u, v, w = (cols[c][~cell] for c in ("pixel", "v", "aff"))
        u, v = u.astype(int), v.astype(int)
        step = v - u
        right.ravel()[u[step == 1]] = w[step == 1]
        down.ravel()[u[step == side]] = w[step == side]
        lab = cascade(sem, em, right, down, levels, finest, beta, threshold).ravel()
        keep = np.flatnonzero(lab > 0)
        return {"pixel": keep, "label": lab[keep]}

    return per_scene(p.union(e), kernel, "scene_id bigint, pixel bigint, label bigint", order=("pixel", "v"), flat=("vec",))
