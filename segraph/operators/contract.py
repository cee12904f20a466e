"""Greedy contraction of weighted graphs.

The best edge above the threshold is contracted again and again; parallel
edges combine by ``rule``, edges that only one end has carry over
(``exclusive="keep"``) or go (``"drop"``).  Ties: larger affinity, then smaller
lower id, then smaller higher id.  A segment is named by its smallest node.
"""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .streams import per_scene

RULES = ("avg", "mean_edges", "sum", "max", "min")


def combine(rule: str, a: tuple[float, int], b: tuple[float, int]) -> tuple[float, int]:
    """State (weight, edges behind it) of two parallel edges as one."""
    if rule == "avg":
        return (a[0] + b[0]) / 2, 1
    if rule == "mean_edges":
        return (a[0] * a[1] + b[0] * b[1]) / (a[1] + b[1]), a[1] + b[1]
    if rule == "sum":
        return a[0] + b[0], 1
    return (max if rule == "max" else min)(a[0], b[0]), 1


class Graph:
    """Adjacency with a lazily cleaned heap; ``weigh`` may scale an affinity
    into the value by which edges are ranked."""

    def __init__(self, nodes, u, v, aff, n=None, rule="avg", exclusive="keep", weigh=None):
        if rule not in RULES or exclusive not in ("keep", "drop"):
            raise ValueError(f"{rule}, {exclusive}")
        self.rule, self.exclusive = rule, exclusive
        self.weigh = weigh or (lambda a, b, w: w)
        self.adj: dict[int, dict[int, tuple[float, int]]] = {int(x): {} for x in nodes}
        self.into = {x: x for x in self.adj}
        n = np.ones(len(u), int) if n is None else n
        for a, b, w, c in zip(u.tolist(), v.tolist(), aff.tolist(), n.tolist()):
            if a == b:
                continue
            for x in (a, b):
                if x not in self.adj:
                    self.adj[x], self.into[x] = {}, x
            s = (w, int(c))
            if b in self.adj[a]:
                s = combine(rule, self.adj[a][b], s)
            self.adj[a][b] = self.adj[b][a] = s
        self.pushes = self.pops = 0
        self.trace: list[tuple[int, int, float]] = []

    def run(self, threshold: float, merged=None) -> dict[int, int]:
        """Contracts; ``merged(kept, gone)`` is told of each fusion before the
        edges are ranked anew.  Returns the label of every node."""
        adj, rule, weigh = self.adj, self.rule, self.weigh
        heap = [(-r, a, b) for a, near in adj.items() for b, (w, _) in near.items() if a < b and (r := weigh(a, b, w)) > threshold]
        heapq.heapify(heap)
        self.pushes += len(heap)
        while heap:
            r, a, b = heapq.heappop(heap)
            self.pops += 1
            s = adj.get(a, {}).get(b)
            if s is None or weigh(a, b, s[0]) != -r:
                continue
            self.trace.append((a, b, -r))
            gone, kept = adj.pop(b), adj[a]
            del kept[b], gone[a]
            self.into[b] = a
            if merged:
                merged(a, b)
            touched = []
            if self.exclusive == "drop":
                for x in [x for x in kept if x not in gone]:
                    del kept[x], adj[x][a]
            for x, t in gone.items():
                del adj[x][b]
                if x in kept:
                    t = combine(rule, kept[x], t)
                elif self.exclusive == "drop":
                    continue
                kept[x] = adj[x][a] = t
                touched.append(x)
            for x in kept if merged else touched:
                lo, hi = (a, x) if a < x else (x, a)
                if (w := weigh(lo, hi, kept[x][0])) > threshold:
                    heapq.heappush(heap, (-w, lo, hi))
                    self.pushes += 1
        return self.labels()

    def labels(self) -> dict[int, int]:
        return {x: self._root(x) for x in self.into}

    def _root(self, x: int) -> int:
        r = x
        while self.into[r] != r:
            r = self.into[r]
        while self.into[x] != r:
            self.into[x], x = r, self.into[x]
        return r


def _rows(edges: DataFrame, nodes: DataFrame | None, value: str) -> DataFrame:
    """Edges, and nodes as loops, in one relation, so that one shuffle carries both."""
    n = F.col("n").cast("bigint") if "n" in edges.columns else F.lit(1).cast("bigint")
    e = edges.select("scene_id", F.col("u").cast("bigint").alias("u"), F.col("v").cast("bigint").alias("v"), F.col(value).cast("double").alias("aff"), n.alias("n"))
    if nodes is None:
        return e
    return e.union(nodes.select("scene_id", F.col("node").cast("bigint"), (F.col("node") + 0).cast("bigint"), F.lit(0.0), F.lit(1).cast("bigint")))


def _graph(cols, rule, exclusive) -> Graph:
    loop = cols["u"] == cols["v"]
    e = ~loop
    return Graph(np.unique(np.concatenate([cols["u"], cols["v"]])), cols["u"][e], cols["v"][e], cols["aff"][e], cols["n"][e], rule, exclusive)


def contract(edges: DataFrame, threshold: float = 0.5, rule: str = "avg", exclusive: str = "keep", nodes: DataFrame | None = None, init: DataFrame | None = None, output: str = "labels", value: str = "aff") -> DataFrame:
    """Segments of every scene by the exact sequential kernel.

    edges (scene_id, u, v, aff[, n]); nodes (scene_id, node) adds isolated
    ones; init (scene_id, node, label) starts from a partition.  output:
    "labels" (scene_id, node, label), "trace" (scene_id, step, u, v, aff) or
    "counts" (scene_id, nodes, edges, contractions, pushes, pops).
    """
    if init is not None:
        from ..session import materialise
        from .grid import region_graph

        init = materialise(init.select("scene_id", "node", "label"), "init")
        start = region_graph(edges.withColumnRenamed(value, "aff"), init)
        seg = init.select("scene_id", F.col("label").alias("node")).distinct()
        top = contract(start, threshold, rule, exclusive, seg, None, output)
        if output != "labels":
            return top
        return init.select("scene_id", "node", F.col("label").alias("_s")).join(top.select("scene_id", F.col("node").alias("_s"), "label"), ["scene_id", "_s"]).select("scene_id", "node", "label")

    def kernel(scene, cols):
        g = _graph(cols, rule, exclusive)
        n_edges = sum(map(len, g.adj.values())) // 2
        labels = g.run(threshold)
        if output == "trace":
            return {"step": np.arange(1, len(g.trace) + 1), "u": [t[0] for t in g.trace], "v": [t[1] for t in g.trace], "aff": [t[2] for t in g.trace]}
        if output == "counts":
            return {"nodes": [len(labels)], "edges": [n_edges], "contractions": [len(g.trace)], "pushes": [g.pushes], "pops": [g.pops]}
        return {"node": list(labels), "label": list(labels.values())}

    ddl = {"labels": "scene_id bigint, node bigint, label bigint", "trace": "scene_id bigint, step bigint, u bigint, v bigint, aff double", "counts": "scene_id bigint, nodes bigint, edges bigint, contractions bigint, pushes bigint, pops bigint"}[output]
    return per_scene(_rows(edges, nodes, value), kernel, ddl, order=("u", "v"))


def recursive_arrays_sql(states: str, threshold: float) -> str:
    """Rule "avg" as a recursive statement in Spark SQL, whose recursive member
    takes no aggregate: a scene is one row (scene_id, e: array of (s, u, v),
    l: array of (node, label)) and a step rewrites its arrays."""
    return f"""WITH RECURSIVE st(scene_id, step, e, l) AS (
  SELECT scene_id, 0, e, l FROM {states}
  UNION ALL
  SELECT scene_id, step + 1,
    transform(array_distinct(transform(m, x -> struct(x.u AS u, x.v AS v))), k ->
      struct(aggregate(filter(m, x -> x.u = k.u AND x.v = k.v), 0.0D, (t, x) -> t + x.s) / size(filter(m, x -> x.u = k.u AND x.v = k.v)) AS s, k.u AS u, k.v AS v)),
    transform(l, x -> struct(x.node AS node, IF(x.label = bv, bu, x.label) AS label))
  FROM (SELECT scene_id, step, l, bu, bv, transform(filter(e, x -> NOT (x.u = bu AND x.v = bv)), x -> struct(x.s AS s, least(IF(x.u = bv, bu, x.u), IF(x.v = bv, bu, x.v)) AS u, greatest(IF(x.u = bv, bu, x.u), IF(x.v = bv, bu, x.v)) AS v)) AS m
    FROM (SELECT scene_id, step, e, l, -b.nu AS bu, -b.nv AS bv
      FROM (SELECT *, array_max(transform(filter(e, x -> x.s > {threshold}), x -> struct(x.s AS s, -x.u AS nu, -x.v AS nv))) AS b FROM st) q WHERE b IS NOT NULL) r) z
) SELECT scene_id, x.node AS node, x.label AS label FROM (SELECT scene_id, explode(max_by(l, step)) AS x FROM st GROUP BY scene_id) y"""


def recursive_sql(edges: str, nodes: str, threshold: float, rule: str = "avg", exclusive: str = "keep", prefix: str = "", last: str = "labels") -> str:
    """The same contraction as one recursive statement, a merge per scene and
    step, for any engine with WITH RECURSIVE; demo sizes.  edges and nodes are
    names of relations; prefix holds common table expressions before."""
    new = {"avg": "avg(s)", "mean_edges": "sum(s*c)/sum(c)", "sum": "sum(s)", "max": "max(s)", "min": "min(s)"}[rule]
    drop = "HAVING max(kind)=1 OR count(*)>1 OR max(CASE WHEN u=bu OR v=bu OR u=bv OR v=bv THEN 1 ELSE 0 END)=0" if exclusive == "drop" else ""
    tail = {
        "labels": "SELECT scene_id, u AS node, v AS label FROM (SELECT *, max(step) OVER (PARTITION BY scene_id) AS top FROM st) z WHERE step=top AND kind=1",
        "trace": "SELECT scene_id, step+1 AS step, u, v, s AS aff FROM (SELECT *, row_number() OVER (PARTITION BY scene_id, step ORDER BY s DESC, u, v) AS rn FROM st WHERE kind=0 AND s > " + f"{threshold}) z WHERE rn=1",
    }[last]
    return f"""WITH RECURSIVE {prefix + ',' if prefix else ''} st AS (
 (SELECT CAST(0 AS BIGINT) AS step, scene_id, 0 AS kind, u, v, CAST(aff AS DOUBLE) AS s, CAST(1 AS BIGINT) AS c FROM {edges}
  UNION ALL SELECT CAST(0 AS BIGINT), scene_id, 1, node, node, CAST(NULL AS DOUBLE), CAST(1 AS BIGINT) FROM {nodes})
 UNION ALL
 (SELECT step+1, scene_id, kind, a, b, {new}, CAST(sum(c) AS BIGINT) FROM (
   SELECT step, scene_id, kind, s, c, u, v, bu, bv,
     CASE WHEN kind=1 THEN u ELSE least(CASE WHEN u=bv THEN bu ELSE u END, CASE WHEN v=bv THEN bu ELSE v END) END AS a,
     CASE WHEN kind=1 THEN CASE WHEN v=bv THEN bu ELSE v END ELSE greatest(CASE WHEN u=bv THEN bu ELSE u END, CASE WHEN v=bv THEN bu ELSE v END) END AS b
   FROM (SELECT *,
      first_value(CASE WHEN kind=0 AND s>{threshold} THEN u END) OVER w AS bu,
      first_value(CASE WHEN kind=0 AND s>{threshold} THEN v END) OVER w AS bv
     FROM st WINDOW w AS (PARTITION BY scene_id ORDER BY CASE WHEN kind=0 AND s>{threshold} THEN 0 ELSE 1 END, s DESC, u, v ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) q
   WHERE bu IS NOT NULL) r
  WHERE kind=1 OR a<>b
  GROUP BY step, scene_id, kind, a, b {drop})
) {tail}"""
