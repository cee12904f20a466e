"""Baseline partitioners."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .affinity import to_cost
from .components import components
from .contract import contract
from .grid import region_graph


def superpixel_multicut(edges: DataFrame, nodes: DataFrame, rim_t: float = 0.7) -> DataFrame:
    """Superpixels from strong edges, then additive contraction of log-odds
    costs between them."""
    sp = components(edges, rim_t, nodes)
    rg = region_graph(edges, sp).select("scene_id", "u", "v", to_cost("aff", 0.5, "logodds").alias("aff"))
    seg = sp.select("scene_id", F.col("label").alias("node")).distinct()
    top = contract(rg, 0.0, "sum", "keep", seg)
    return sp.select("scene_id", "node", F.col("label").alias("_s")).join(top.select("scene_id", F.col("node").alias("_s"), "label"), ["scene_id", "_s"]).select("scene_id", "node", "label")


def level_by_size(inst: DataFrame, base: float = 8.0, levels: int = 4) -> DataFrame:
    """Pyramid level that fits a box: one more for each doubling over ``base``."""
    lv = F.floor(F.log2(F.sqrt(F.col("w") * F.col("h")) / base)) + 1
    return inst.withColumn("level", F.least(F.greatest(lv, F.lit(1)), F.lit(levels)).cast("int"))


def position_sensitive(px: DataFrame, boxes: DataFrame, k: int = 3, value=None) -> DataFrame:
    """(scene_id, box, cell, score): mean of value (a column over both inputs)
    over the k x k cells of each box.  px: scene_id, y, x; boxes: scene_id, box,
    y0, x0, h, w."""
    cells = boxes.withColumn("y", F.explode(F.sequence("y0", F.col("y0") + F.col("h") - 1))).withColumn("x", F.explode(F.sequence("x0", F.col("x0") + F.col("w") - 1)))
    j = cells.hint("merge").join(px, ["scene_id", "y", "x"])  # exploded rows must not be broadcast
    cell = F.floor((F.col("y") - F.col("y0")) * k / F.col("h")) * k + F.floor((F.col("x") - F.col("x0")) * k / F.col("w"))
    return j.groupBy("scene_id", "box", cell.cast("int").alias("cell")).agg(F.avg(F.col("value") if value is None else value).alias("score"))


def centre_offset(px: DataFrame, centres: DataFrame) -> DataFrame:
    """Pixels (py, px_ predicted centre) with the nearest centre of their scene."""
    j = px.join(centres, "scene_id")
    d = F.pow(F.col("py") - F.col("cy"), 2) + F.pow(F.col("px_") - F.col("cx"), 2)
    return j.groupBy("scene_id", "pixel").agg(F.min_by("label", F.struct(d.alias("d"), F.col("label"))).alias("label"))


def hough_assign(px: DataFrame, cell: int = 2, least: int = 3) -> DataFrame:
    """Votes of predicted centres on a grid; a pixel belongs to its own cell if
    that has ``least`` votes, else to none (0).  The label is the cell."""
    c = (F.floor(F.col("py") / cell) * 1000 + F.floor(F.col("px_") / cell)).cast("bigint")
    v = px.select("scene_id", "pixel", c.alias("cell"))
    n = v.groupBy("scene_id", "cell").agg(F.count("*").alias("n"))
    return v.join(n, ["scene_id", "cell"]).select("scene_id", "pixel", F.when(F.col("n") >= least, F.col("cell")).otherwise(F.lit(0)).alias("label"))


def seed_margin(px: DataFrame, t: float = 0.5, least: int = 2) -> DataFrame:
    """Greedy seeds by score: the best open pixel claims all open pixels with
    Gaussian affinity above t to its embedding.  px: scene_id, pixel, seed, emb."""
    import numpy as np

    from .streams import per_scene

    def kernel(scene, cols):
        pix, seed = cols["pixel"], cols["seed"]
        emb = np.array(list(cols["emb"]), float)
        lab = np.zeros(len(pix), np.int64)
        for i in np.lexsort((pix, -seed)):
            if lab[i]:
                continue
            near = (np.exp(-np.log(2) * ((emb - emb[i]) ** 2).sum(1)) > t) & (lab == 0)
            lab[near] = pix[near].min() + 1
            if near.sum() < least:
                lab[i] = pix[i] + 1
        return {"pixel": pix, "label": lab}

    return per_scene(px.select("scene_id", "pixel", "seed", "emb"), kernel, "scene_id bigint, pixel bigint, label bigint", order=("pixel",))


def embedding_cluster(px: DataFrame, t: float = 0.5, rounds: int = 5) -> DataFrame:
    """Mean-shift-like grouping: pixels join the first mean within reach, means
    move, pixels join anew."""
    import numpy as np

    from .streams import per_scene

    def kernel(scene, cols):
        pix = cols["pixel"]
        emb = np.array(list(cols["emb"]), float)
        means = np.zeros((0, emb.shape[1]))
        lab = np.full(len(pix), -1)
        for _ in range(rounds):
            for i in range(len(pix)):
                d = np.exp(-np.log(2) * ((means - emb[i]) ** 2).sum(1)) if len(means) else np.zeros(0)
                if len(d) and d.max() > t:
                    lab[i] = int(d.argmax())
                else:
                    means = np.vstack([means, emb[i]])
                    lab[i] = len(means) - 1
            used, lab = np.unique(lab, return_inverse=True)
            new = np.stack([emb[lab == k].mean(0) for k in range(len(used))])
            if new.shape == means.shape and np.allclose(new, means):
                break
            means = new
        first = {k: int(pix[lab == k].min()) for k in set(lab.tolist())}
        return {"pixel": pix, "label": [first[k] for k in lab.tolist()]}

    return per_scene(px.select("scene_id", "pixel", "emb"), kernel, "scene_id bigint, pixel bigint, label bigint", order=("pixel",))


def watershed(px: DataFrame, energy: str = "energy") -> DataFrame:
    """(scene_id, pixel, label): every pixel points at its lowest neighbour (or
    itself) by (energy, pixel); pointers jump until they rest at minima."""
    from ..session import materialise
    from .grid import grid_edges

    e = grid_edges(px, carry=(energy,))
    s = lambda p, q: e.select("scene_id", F.col(p).alias("pixel"), F.struct(F.col(f"{energy}_{q}").alias("e"), F.col(q).alias("p")).alias("to"))
    own = px.select("scene_id", "pixel", F.struct(F.col(energy).alias("e"), F.col("pixel").alias("p")).alias("to"))
    ptr = s("u", "v").union(s("v", "u")).union(own).groupBy("scene_id", "pixel").agg(F.min("to").alias("to")).select("scene_id", "pixel", F.col("to.p").alias("label"))
    while True:
        ptr = materialise(ptr, "watershed")
        nxt = ptr.join(ptr.select("scene_id", F.col("pixel").alias("label"), F.col("label").alias("_n")), ["scene_id", "label"])
        if nxt.where("label <> _n").limit(1).count() == 0:
            return ptr
        ptr = nxt.select("scene_id", "pixel", F.col("_n").alias("label"))


def ncut_value(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Normalised cut: summed over segments, cut weight over total weight."""
    a = labels.select("scene_id", F.col("node").alias("u"), F.col("label").alias("_a"))
    b = labels.select("scene_id", F.col("node").alias("v"), F.col("label").alias("_b"))
    j = edges.join(a, ["scene_id", "u"]).join(b, ["scene_id", "v"])
    cut = F.when(F.col("_a") != F.col("_b"), F.col("aff")).otherwise(0.0)
    d = j.select("scene_id", F.col("_a").alias("s"), "aff", cut.alias("c")).union(j.select("scene_id", F.col("_b"), "aff", cut))
    seg = d.groupBy("scene_id", "s").agg((F.sum("c") / F.sum("aff")).alias("r"))
    return seg.groupBy("scene_id").agg(F.sum("r").alias("ncut"))


def _laplacian(cols):
    import numpy as np

    nodes = np.unique(np.concatenate([cols["u"], cols["v"]]))
    w = np.zeros((len(nodes), len(nodes)))
    i, j = np.searchsorted(nodes, cols["u"]), np.searchsorted(nodes, cols["v"])
    e = i != j
    w[i[e], j[e]] = w[j[e], i[e]] = cols["aff"][e]
    d = np.maximum(w.sum(1), 1e-12)
    return nodes, w / np.sqrt(d[:, None] * d[None, :]), np.sqrt(d)


def normalised_cut(edges: DataFrame, iters: int = 200) -> DataFrame:
    """Two parts by the sign of the second eigenvector, from deflated power
    iteration, one scene a task."""
    import numpy as np

    from .streams import per_scene

    def kernel(scene, cols):
        nodes, m, d = _laplacian(cols)
        first = d / np.linalg.norm(d)
        x = np.cos(np.arange(len(nodes)) * 1.7 + 0.3)
        for _ in range(iters):
            x = x - first * (first @ x)
            x = m @ x + x
            x /= max(np.linalg.norm(x), 1e-300)
        side = (x - first * (first @ x)) / d >= 0
        ids = [int(nodes[side == s].min()) if (side == s).any() else 0 for s in (False, True)]
        return {"node": nodes, "label": [ids[int(s)] for s in side]}

    return per_scene(edges.select("scene_id", "u", "v", "aff"), kernel, "scene_id bigint, node bigint, label bigint", order=("u", "v"))


def spectral(edges: DataFrame, dims: int = 3, iters: int = 100) -> DataFrame:
    """Nodes grouped by the sign pattern of the leading eigenvectors after the first."""
    import numpy as np

    from .streams import per_scene

    def kernel(scene, cols):
        nodes, m, d = _laplacian(cols)
        k = min(dims + 1, len(nodes))
        q = np.cos(np.outer(np.arange(len(nodes)), np.arange(1, k + 1)) * 1.3)
        q[:, 0] = d
        for _ in range(iters):
            q, _ = np.linalg.qr(m @ q + q)
        code = (q[:, 1:] > 0) @ (1 << np.arange(k - 1)) if k > 1 else np.zeros(len(nodes), int)
        first = {c: int(nodes[code == c].min()) for c in set(code.tolist())}
        return {"node": nodes, "label": [first[c] for c in code.tolist()]}

    return per_scene(edges.select("scene_id", "u", "v", "aff"), kernel, "scene_id bigint, node bigint, label bigint", order=("u", "v"))


def gibbs_energy(px: DataFrame, edges: DataFrame, weight: float = 1.0, label: str = "cls") -> DataFrame:
    """Unary -ln p of the labels plus weight times the affinity of edges whose labels differ."""
    p = F.element_at("sem", (F.coalesce(label, F.lit(0)) + 1).cast("int"))
    un = px.groupBy("scene_id").agg(F.sum(-F.ln(F.greatest(p, F.lit(1e-7)))).alias("unary"))
    a, b = px.select("scene_id", F.col("pixel").alias("u"), F.col(label).alias("_a")), px.select("scene_id", F.col("pixel").alias("v"), F.col(label).alias("_b"))
    pw = edges.join(a, ["scene_id", "u"]).join(b, ["scene_id", "v"]).groupBy("scene_id").agg(F.sum(F.when(F.col("_a") != F.col("_b"), F.col("aff")).otherwise(0.0)).alias("pair"))
    return un.join(pw, "scene_id", "left").select("scene_id", (F.col("unary") + weight * F.coalesce("pair", F.lit(0.0))).alias("energy"))


def mean_field(px: DataFrame, edges: DataFrame, weight: float = 1.0, iters: int = 5) -> DataFrame:
    """Class of every pixel after mean-field rounds on the grid, a scene a task."""
    import numpy as np

    from .streams import per_scene

    p = px.select("scene_id", "pixel", F.lit(-1).cast("bigint").alias("v"), F.lit(0.0).alias("aff"), "sem")
    e = edges.select("scene_id", F.col("u").alias("pixel"), "v", "aff", F.array().cast("array<double>").alias("sem"))

    def kernel(scene, cols):
        node = cols["v"] == -1
        pix = cols["pixel"][node]
        un = np.log(np.maximum(np.array(list(cols["sem"][node]), float), 1e-7))
        u, v = np.searchsorted(pix, cols["pixel"][~node]), np.searchsorted(pix, cols["v"][~node])
        w = cols["aff"][~node]
        q = np.exp(un)
        for _ in range(iters):
            m = np.zeros_like(q)
            np.add.at(m, u, w[:, None] * q[v])
            np.add.at(m, v, w[:, None] * q[u])
            z = un + weight * m
            q = np.exp(z - z.max(1, keepdims=True))
            q /= q.sum(1, keepdims=True)
        return {"pixel": pix, "cls": q.argmax(1).astype(np.int32)}

    return per_scene(p.union(e), kernel, "scene_id bigint, pixel bigint, cls int", order=("v", "pixel"))


def flip_average(edges: DataFrame, width: int) -> DataFrame:
    """Mean of each affinity and that of the mirrored edge in the flipped pass
    (aff_flip, given in flipped coordinates)."""
    mirror = lambda c: (F.floor(F.col(c) / width) * width + width - 1 - F.pmod(F.col(c), F.lit(width))).cast("bigint")
    f = edges.select("scene_id", F.least(mirror("u"), mirror("v")).alias("u"), F.greatest(mirror("u"), mirror("v")).alias("v"), F.col("aff_flip").alias("aff"))
    return edges.select("scene_id", "u", "v", "aff").union(f).groupBy("scene_id", "u", "v").agg(F.avg("aff").alias("aff"))


def box_mask(px: DataFrame, boxes: DataFrame) -> DataFrame:
    """Pixels go to the smallest box of their class that covers them (ties: smaller box id)."""
    cells = boxes.withColumn("y", F.explode(F.sequence("y0", F.col("y0") + F.col("h") - 1))).withColumn("x", F.explode(F.sequence("x0", F.col("x0") + F.col("w") - 1)))
    j = px.hint("merge").join(cells.select("scene_id", "y", "x", "cls", "box", (F.col("h") * F.col("w")).alias("area")), ["scene_id", "y", "x", "cls"])
    return j.groupBy("scene_id", "pixel").agg(F.min(F.struct("area", "box")).alias("b")).select("scene_id", "pixel", F.col("b.box").alias("label"))


def box_affinity(edges: DataFrame, px: DataFrame, boxes: DataFrame, t: float = 0.5, nms: float = 0.5) -> DataFrame:
    """Contraction inside every box, its largest segment as mask, masks by
    falling size; those that overlap a kept one by more than nms go."""
    import numpy as np

    from .contract import Graph
    from .streams import per_scene

    nul = [F.lit(None).cast("bigint").alias(c) for c in ("y0", "x0", "h", "w")]
    p = px.select("scene_id", F.lit(0).alias("kind"), F.col("pixel").alias("a"), (F.col("y") * 1000 + F.col("x")).cast("bigint").alias("b"), F.lit(0.0).alias("aff"), *nul)
    e = edges.select("scene_id", F.lit(1).alias("kind"), F.col("u").alias("a"), F.col("v").alias("b"), "aff", *nul)
    x = boxes.select("scene_id", F.lit(2).alias("kind"), F.col("box").cast("bigint").alias("a"), F.lit(0).cast("bigint").alias("b"), F.lit(0.0).alias("aff"), *[F.col(c).cast("bigint") for c in ("y0", "x0", "h", "w")])

    def kernel(scene, cols):
        k = cols["kind"]
        at = {int(a): (int(b) // 1000, int(b) % 1000) for a, b in zip(cols["a"][k == 0], cols["b"][k == 0])}
        u, v, w = cols["a"][k == 1], cols["b"][k == 1], cols["aff"][k == 1]
        masks = []
        for i in np.flatnonzero(k == 2):
            y0, x0, h, wd = (int(cols[c][i]) for c in ("y0", "x0", "h", "w"))
            inside = {n for n, (y, x_) in at.items() if y0 <= y < y0 + h and x0 <= x_ < x0 + wd}
            ok = np.array([a in inside and b in inside for a, b in zip(u.tolist(), v.tolist())], bool)
            lab = Graph(inside, u[ok], v[ok], w[ok]).run(t) if inside else {}
            by: dict[int, set] = {}
            for n, s in lab.items():
                by.setdefault(s, set()).add(n)
            if by:
                masks.append((int(cols["a"][i]), max(by.values(), key=lambda s: (len(s), -min(s)))))
        masks.sort(key=lambda m: (-len(m[1]), m[0]))
        kept, out = [], {}
        for b, m in masks:
            if all(len(m & o) <= nms * len(m | o) for _, o in kept):
                kept.append((b, m))
                for n in m:
                    out.setdefault(n, b)
        return {"pixel": list(out), "label": list(out.values())}

    return per_scene(p.union(e).union(x), kernel, "scene_id bigint, pixel bigint, label bigint", order=("kind", "a", "b"))


def window_pyramid(coarse: DataFrame, coarse_edges: DataFrame, fine: DataFrame, fine_edges: DataFrame, height: int, width: int, t: float = 0.5) -> DataFrame:
    """Two-level cascade on wide-window edges without grouping.  coarse, fine:
    scene_id, y, x, pixel; result (scene_id, node, label) of the fine pixels."""
    from .pyramid import reclaim_rim, upsample2

    lab = contract(coarse_edges, t, nodes=coarse.select("scene_id", F.col("pixel").alias("node")))
    up = upsample2(coarse.join(lab.select("scene_id", F.col("node").alias("pixel"), "label"), ["scene_id", "pixel"]).select("scene_id", "y", "x", "label"), height, width)
    up = reclaim_rim(up)
    start = fine.join(up.withColumnRenamed("label", "_l"), ["scene_id", "y", "x"], "left")
    # segments are named by 10^6 + coarse label, open pixels by themselves
    init = start.select("scene_id", F.col("pixel").alias("node"), F.coalesce(F.col("_l") + 1000000, F.col("pixel")).cast("bigint").alias("label"))
    return contract(fine_edges, t, init=init)
