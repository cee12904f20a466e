"""Contraction of segments by similarity damped with distance."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .contract import Graph
from .streams import per_scene


def damp(a: tuple, b: tuple, beta: float) -> float:
    """Damping of two boxes (y0, y1, x0, x1)."""
    out = 1.0
    for k in (0, 2):
        gap = abs((a[k] + a[k + 1]) / 2 - (b[k] + b[k + 1]) / 2)
        if gap:
            out *= min(1.0, 0.5 * max(a[k + 1] - a[k] + 1, b[k + 1] - b[k] + 1) / gap) ** beta
    return out


def positional_labels(boxes: dict[int, tuple], u, v, aff, beta: float, threshold: float) -> Graph:
    """Contracts; on each fusion boxes join in constant time and every edge of
    the fused segment is ranked by the damping of its new box."""
    boxes = dict(boxes)
    g = Graph(list(boxes), u, v, aff, weigh=lambda a, b, w: w * damp(boxes[a], boxes[b], beta))

    def merged(kept, gone):
        a, b = boxes[kept], boxes.pop(gone)
        boxes[kept] = (min(a[0], b[0]), max(a[1], b[1]), min(a[2], b[2]), max(a[3], b[3]))

    g.run(threshold, merged)
    return g


def contract_positional(segs: DataFrame, pairs: DataFrame, beta: float = 0.5, threshold: float = 0.5) -> DataFrame:
    """(scene_id, segment, label).  segs: scene_id, label, y0, y1, x0, x1;
    pairs: scene_id, u, v, aff.  Pairs at or below the threshold can't fuse
    first, but pull averages down, so all are needed."""
    empty = [F.lit(None).cast("double").alias("aff")]
    nodes = segs.select("scene_id", F.col("label").alias("u"), F.col("label").alias("v"), *empty, "y0", "y1", "x0", "x1")
    edges = pairs.select("scene_id", "u", "v", "aff", *[F.lit(0).cast("int").alias(c) for c in ("y0", "y1", "x0", "x1")])

    def kernel(scene, cols):
        loop = cols["u"] == cols["v"]
        boxes = {int(n): tuple(int(cols[c][i]) for c in ("y0", "y1", "x0", "x1")) for i, n in zip(np.flatnonzero(loop), cols["u"][loop])}
        e = ~loop
        g = positional_labels(boxes, cols["u"][e], cols["v"][e], cols["aff"][e], beta, threshold)
        lab = g.labels()
        return {"segment": list(lab), "label": list(lab.values())}

    return per_scene(nodes.unionByName(edges), kernel, "scene_id bigint, segment bigint, label bigint", order=("u", "v"))


def positional_recursive_sql(segs: str, pairs: str, beta: float, threshold: float, prefix: str = "") -> str:
    """The same in one recursive statement with both boxes on every edge row."""
    d = "1.0"
    for lo, hi in (("y0", "y1"), ("x0", "x1")):
        gap = f"abs(({lo}u+{hi}u)/2.0::DOUBLE-({lo}v+{hi}v)/2.0::DOUBLE)"
        d += f"*(CASE WHEN {gap}=0 THEN 1.0::DOUBLE ELSE pow(least(1.0::DOUBLE,0.5::DOUBLE*greatest({hi}u-{lo}u+1,{hi}v-{lo}v+1)/{gap}),{beta}::DOUBLE) END)"
    bx = ("y0", "y1", "x0", "x1")
    own = ",".join(f"{c}{e}" for e in "uv" for c in bx)
    win = ",".join(f"first_value(CASE WHEN kind=0 AND r>{threshold} THEN {c}{e} END) OVER w AS b{c}{e}" for e in "uv" for c in bx)
    joined = {c: f"{'least' if c.endswith('0') else 'greatest'}(b{c}u,b{c}v)" for c in bx}
    swap = f"(CASE WHEN u=bv THEN bu ELSE u END) > (CASE WHEN v=bv THEN bu ELSE v END)"
    at = lambda e, c: f"CASE WHEN {e} IN (bu,bv) THEN {joined[c]} ELSE {c}{e} END"
    moved = ",".join(f"CASE WHEN {swap} THEN {at('v' if e == 'u' else 'u', c)} ELSE {at(e, c)} END AS {c}{e}" for e in "uv" for c in bx)
    picks = ",".join(f"any_value({c}{e}) AS {c}{e}" for e in "uv" for c in bx)
    return f"""WITH RECURSIVE {prefix}, st AS (
 (SELECT 0::BIGINT AS step, p.scene_id, 0 AS kind, p.u, p.v, p.aff::DOUBLE AS s, {','.join(f'a.{c} AS {c}u' for c in bx)}, {','.join(f'b.{c} AS {c}v' for c in bx)}
   FROM {pairs} p JOIN {segs} a ON a.scene_id=p.scene_id AND a.label=p.u JOIN {segs} b ON b.scene_id=p.scene_id AND b.label=p.v
  UNION ALL SELECT 0::BIGINT, scene_id, 1, label, label, NULL, {','.join(['0'] * 8)} FROM {segs})
 UNION ALL
 (SELECT step+1, scene_id, kind, a, b, avg(s), {picks} FROM (
   SELECT step, scene_id, kind, s,
     CASE WHEN kind=1 THEN u ELSE least(CASE WHEN u=bv THEN bu ELSE u END, CASE WHEN v=bv THEN bu ELSE v END) END AS a,
     CASE WHEN kind=1 THEN CASE WHEN v=bv THEN bu ELSE v END ELSE greatest(CASE WHEN u=bv THEN bu ELSE u END, CASE WHEN v=bv THEN bu ELSE v END) END AS b, {moved}
   FROM (SELECT *, first_value(CASE WHEN kind=0 AND r>{threshold} THEN u END) OVER w AS bu, first_value(CASE WHEN kind=0 AND r>{threshold} THEN v END) OVER w AS bv, {win}
     FROM (SELECT *, s*{d} AS r FROM st) WINDOW w AS (PARTITION BY scene_id ORDER BY CASE WHEN kind=0 AND r>{threshold} THEN 0 ELSE 1 END, r DESC, u, v ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) q
   WHERE bu IS NOT NULL) z WHERE kind=1 OR a<>b GROUP BY step, scene_id, kind, a, b)
) SELECT scene_id, u AS segment, v AS label FROM (SELECT *, max(step) OVER (PARTITION BY scene_id) AS top FROM st) WHERE step=top AND kind=1"""
