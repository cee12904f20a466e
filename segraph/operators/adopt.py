"""Label adoption: unlabelled nodes take the label of their strongest labelled neighbour."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialise
from .streams import per_scene


def adopt_sync_arrays(label: np.ndarray, known: np.ndarray, u: np.ndarray, v: np.ndarray, w: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Labels and known flags after all rounds, in each of which every node reads
    the labels of the round before.  u and v are places in label."""
    label, known = label.copy(), known.copy()
    node, near, aff = np.concatenate([u, v]), np.concatenate([v, u]), np.concatenate([w, w])
    order = np.lexsort((near, -aff, node))  # a node's best neighbour first
    node, near, aff = node[order], near[order], aff[order]
    live = ~known[node]
    node, near, aff = node[live], near[live], aff[live]
    while len(node):
        seen = np.flatnonzero(known[near])
        first = seen[np.concatenate([[True], node[seen][1:] != node[seen][:-1]])] if len(seen) else seen
        first = first[aff[first] >= threshold]
        if not len(first):
            break
        label[node[first]], known[node[first]] = label[near[first]], True
        live = ~known[node]
        node, near, aff = node[live], near[live], aff[live]
    return label, known


def adopt(labels: DataFrame, edges: DataFrame, threshold: float = 0.5, order: str = "sync", seed: int = 0, background: int | None = 0, engine: str = "kernel") -> DataFrame:
    """(scene_id, node, label) with the null labels filled.

    order "sync": all nodes read the previous round; "seeded": nodes are
    visited in the order of a hash and see labels given before them in the
    same pass.  A neighbour at exactly the threshold counts.  Given labels
    never change.  What stays open becomes ``background`` (None leaves it).
    engine "rounds" (sync only) joins frontier and labels on the cluster and
    takes graphs of any size.
    """
    if engine == "rounds":
        return _rounds(labels, edges, threshold, background)
    # a flag tells which labels are given: a null would turn the labels into doubles, which can't hold them all
    given = (F.coalesce("label", F.lit(0)).cast("bigint").alias("label"), F.col("label").isNotNull().alias("known"))
    rows = labels.select("scene_id", F.col("node").alias("u"), F.col("node").alias("v"), F.lit(0.0).alias("aff"), *given).union(edges.select("scene_id", "u", "v", "aff", F.lit(0).cast("bigint"), F.lit(False)))

    def kernel(scene, cols):
        loop = cols["u"] == cols["v"]
        u, v, w = (cols[c][~loop] for c in ("u", "v", "aff"))
        if order == "sync":
            at = np.argsort(cols["u"][loop])
            node, lab, known = (cols[c][loop][at] for c in ("u", "label", "known"))
            lab, known = adopt_sync_arrays(lab, known.astype(bool), np.searchsorted(node, u), np.searchsorted(node, v), w, threshold)
            return {"node": node.tolist(), "label": [x if k else background for x, k in zip(lab.tolist(), known.tolist())]}
        lab = {n: x if k else None for n, x, k in zip(*(cols[c][loop].tolist() for c in ("u", "label", "known")))}
        es = zip(u.tolist(), v.tolist(), w.tolist())
        if lab:
            near: dict[int, list] = {x: [] for x in lab}
            for a, b, w in es:
                near[a].append((w, -b, b))
                near[b].append((w, -a, a))
            rank = lambda x: ((x * 7919 + scene * 10007 + seed * 65537) * 2654435761 % 2**32, x)
            open_ = sorted((x for x, v in lab.items() if v is None), key=rank)
            moved = True
            while open_ and moved:
                moved, still = False, []
                for x in open_:
                    best = max((t for t in near[x] if lab[t[2]] is not None), default=None)
                    if best and best[0] >= threshold:
                        lab[x], moved = lab[best[2]], True
                    else:
                        still.append(x)
                open_ = still
        return {"node": list(lab), "label": [background if v is None else v for v in lab.values()]}

    return per_scene(rows, kernel, "scene_id bigint, node bigint, label bigint", order=("u", "v"))


def _rounds(labels: DataFrame, edges: DataFrame, threshold: float, background) -> DataFrame:
    sym = edges.select("scene_id", F.col("u").alias("node"), F.col("v").alias("near"), "aff").union(edges.select("scene_id", F.col("v"), F.col("u"), "aff"))
    done = materialise(labels.where("label is not null").select("scene_id", "node", "label"), "adopt")
    open_ = materialise(labels.where("label is null").select("scene_id", "node"), "adopt")
    while True:
        at = sym.join(open_, ["scene_id", "node"], "left_semi").join(done.select("scene_id", F.col("node").alias("near"), "label"), ["scene_id", "near"])
        best = at.groupBy("scene_id", "node").agg(F.max_by(F.struct("label", "aff"), F.struct(F.col("aff"), -F.col("near"))).alias("b"))
        new = materialise(best.where(F.col("b.aff") >= threshold).select("scene_id", "node", F.col("b.label").alias("label")), "adopt")
        if new.limit(1).count() == 0:
            break
        done = materialise(done.union(new), "adopt")
        open_ = materialise(open_.join(new, ["scene_id", "node"], "left_anti"), "adopt")
    return done.union(open_.select("scene_id", "node", F.lit(background).cast("bigint").alias("label")))


def adopt_sql(labels: str, edges: str, threshold: float, rounds: int, prefix: str) -> str:
    """Synchronous adoption unrolled for ``rounds`` rounds."""
    parts = [f"sym AS (SELECT scene_id,u AS node,v AS near,aff FROM {edges} UNION ALL SELECT scene_id,v,u,aff FROM {edges})", f"l0 AS (SELECT scene_id,node,label FROM {labels})"]
    for k in range(rounds):
        parts.append(f"l{k + 1} AS (SELECT a.scene_id,a.node,coalesce(a.label,CASE WHEN b.w>={threshold} THEN b.lab END) AS label FROM l{k} a LEFT JOIN (SELECT s.scene_id,s.node,arg_max(n.label,(s.aff,-s.near)) AS lab,max(s.aff) AS w FROM sym s JOIN l{k} n ON n.scene_id=s.scene_id AND n.node=s.near AND n.label IS NOT NULL GROUP BY 1,2) b ON a.scene_id=b.scene_id AND a.node=b.node)")
    return f"WITH {prefix}, {', '.join(parts)} SELECT scene_id,node,coalesce(label,0)::BIGINT AS label FROM l{rounds}"
