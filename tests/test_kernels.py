"""Worked examples and invariants of the partition kernels, without Spark."""

import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from segraph.fixtures.graphs import HAND, two_blocks
from segraph.operators.adopt import adopt_sync_arrays
from segraph.operators.contract import RULES, Graph
from segraph.operators.positional import damp, positional_labels
from segraph.operators.pyramid import cascade, contract_level, pooled_affinities, rim_mask


def run(edges, t=0.5, rule="avg", exclusive="keep", nodes=()):
    u, v, a = (np.array(x) for x in zip(*edges)) if edges else (np.zeros(0, int), np.zeros(0, int), np.zeros(0))
    g = Graph(sorted({*u.tolist(), *v.tolist(), *nodes}), u, v, a, None, rule, exclusive)
    return g.run(t), g


def hand(k):
    return [(u, v, a) for g, u, v, a in HAND + two_blocks() if g == k]


def groups(labels):
    out = {}
    for n, s in labels.items():
        out.setdefault(s, set()).add(n)
    return sorted(map(sorted, out.values()))


def test_weak_edge_pulls_the_mean_down():
    lab, g = run(hand(1))
    assert groups(lab) == [[1, 2], [3, 4]]
    assert [round(t[2], 6) for t in g.trace] == [0.9, 0.7]
    assert groups(run(hand(1), rule="max")[0]) == [[1, 2, 3, 4]]


def test_merge_order_matters_under_avg():
    assert len(groups(run(hand(2), 0.62)[0])) == 1


def test_threshold_is_strict_for_contraction_and_not_for_adoption():
    assert groups(run(hand(3))[0]) == [[1], [2]]
    big = 2**60 + 1
    one = lambda w: [x.tolist() for x in adopt_sync_arrays(np.array([big, 0]), np.array([True, False]), np.array([0]), np.array([1]), np.array([w]), 0.5)]
    assert one(0.5) == [[big, big], [True, True]] and one(0.49) == [[big, 0], [True, False]]
    rng = np.random.default_rng(6)
    for _ in range(20):
        n, m = 40, 90
        u, v = rng.integers(0, n, m), rng.integers(0, n, m)
        u, v = u[u != v], v[u != v]
        w, known = rng.integers(0, 8, len(u)) / 8, rng.random(n) < 0.2
        label, flag = dict(enumerate(np.where(known, np.arange(n) + 100, 0).tolist())), dict(enumerate(known.tolist()))
        while True:  # the same rounds, node by node
            new = {}
            for x in (x for x in flag if not flag[x]):
                near = [(a, -q, q) for p, q, a in [*zip(u, v, w), *zip(v, u, w)] if p == x and flag[int(q)]]
                if near and max(near)[0] >= 0.5:
                    new[x] = label[int(max(near)[2])]
            if not new:
                break
            label |= new
            flag |= dict.fromkeys(new, True)
        got, seen = adopt_sync_arrays(np.where(known, np.arange(n) + 100, 0), known, u, v, w, 0.5)
        assert got.tolist() == list(label.values()) and seen.tolist() == list(flag.values())


def test_literal_deletion_leaves_pairs():
    assert max(map(len, groups(run(hand(4), exclusive="drop")[0]))) <= 2
    assert len(groups(run(hand(4))[0])) == 1


@pytest.mark.parametrize("rule", RULES)
def test_no_edges_and_isolated_nodes(rule):
    assert run([], rule=rule, nodes=(3, 5))[0] == {3: 3, 5: 5}


edge_lists = st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9), st.floats(0, 1)), max_size=30).map(lambda es: [(a, b, w) for (a, b), w in {(min(a, b), max(a, b)): w for a, b, w in es if a != b}.items()])


@settings(max_examples=60, deadline=None)
@given(edge_lists, st.floats(0.2, 0.8))
def test_max_is_components_and_avg_refines_them(es, t):
    comp, _ = run([e for e in es if e[2] > t], -1.0, "max", nodes=range(10))
    full = run(es, t, "max", nodes=range(10))[0]
    assert full == comp
    for s in groups(run(es, t, "avg", nodes=range(10))[0]):
        assert len({comp[n] for n in s}) == 1


@settings(max_examples=60, deadline=None)
@given(edge_lists, st.sampled_from(["avg", "mean_edges", "max", "min"]))
def test_higher_threshold_refines(es, rule):
    lo, hi = run(es, 0.3, rule, nodes=range(10))[0], run(es, 0.6, rule, nodes=range(10))[0]
    for s in groups(hi):
        assert len({lo[n] for n in s}) == 1


@settings(max_examples=40, deadline=None)
@given(edge_lists, st.randoms())
def test_order_of_rows_does_not_matter(es, r):
    shuffled = list(es)
    r.shuffle(shuffled)
    assert run(es, nodes=range(10))[0] == run(shuffled, nodes=range(10))[0]


def test_damping_values():
    assert damp((0, 3, 0, 3), (0, 3, 4, 7), 0.5) == pytest.approx(0.5**0.5)
    assert damp((0, 3, 0, 3), (4, 7, 4, 7), 0.5) == pytest.approx(0.5)
    assert damp((0, 3, 0, 3), (0, 3, 0, 3), 0.5) == 1.0
    assert damp((0, 3, 0, 3), (9, 9, 9, 9), 0.0) == 1.0


def test_positions_off_is_plain_contraction():
    rng = np.random.default_rng(3)
    for _ in range(20):
        n = 7
        u, v = (np.array(x) for x in zip(*itertools.combinations(range(n), 2)))
        a = rng.random(len(u))
        boxes = {i: (int(y), int(y) + 2, int(x), int(x) + 2) for i, (y, x) in enumerate(rng.integers(0, 20, (n, 2)))}
        assert positional_labels(boxes, u, v, a, 0.0, 0.5).labels() == Graph(range(n), u, v, a).run(0.5)


def test_far_boxes_do_not_fuse():
    u, v, a = np.array([0]), np.array([1]), np.array([0.9])
    near = positional_labels({0: (0, 3, 0, 3), 1: (0, 3, 4, 7)}, u, v, a, 0.5, 0.5).labels()
    far = positional_labels({0: (0, 3, 0, 3), 1: (40, 43, 40, 43)}, u, v, a, 0.5, 0.5).labels()
    assert len(set(near.values())) == 1 and len(set(far.values())) == 2


def test_rim_of_two_blocks():
    lab = np.array([[1, 1, 2, 2]] * 4)
    assert rim_mask(lab).sum(1).tolist() == [2, 2, 2, 2]


def test_level_contraction_and_cascade_recover_clean_blocks():
    side = 8
    truth = np.zeros((side, side), int)
    truth[:, :4], truth[2:6, 5:] = 1, 2
    right, down = np.full((side, side), np.nan), np.full((side, side), np.nan)
    for a, b, out in ((np.s_[:, :-1], np.s_[:, 1:], right), (np.s_[:-1], np.s_[1:], down)):
        w = np.where(truth[a] == truth[b], 0.9, 0.1)
        w[(truth[a] == 0) | (truth[b] == 0)] = np.nan
        out[a] = w
    fg = truth > 0
    lab = contract_level(np.full((side, side), -1), right, down, fg, 0.5)
    assert set(lab[truth == 1]) == {1} and len(set(lab[truth == 2])) == 1
    sem = np.zeros((side, side, 9))
    sem[..., 0] = ~fg
    sem[..., 1], sem[..., 2] = truth == 1, truth == 2
    emb = truth[..., None].astype(float) * 3
    for finest in ("contract", "adopt"):
        got = cascade(sem, emb, right, down, 3, finest)
        assert all(len(set(got[truth == k])) == 1 for k in (1, 2)) and got[0, 0] != got[2, 5]


def test_pooled_affinity_is_the_mean_of_two():
    right = np.array([[0.1, 0.6, 0.2, np.nan], [0.3, 0.8, 0.4, np.nan]])
    r, _ = pooled_affinities(right, np.full((2, 4), np.nan))
    assert r[0, 0] == pytest.approx(0.7)


def test_every_embedding_is_a_query(spark, tmp_path):
    import numpy as np

    from segraph.fixtures.graphs import embedding_edges

    v = np.random.default_rng(4).normal(size=(700, 8)).astype("f4")
    v[620:660] = v[10]  # copies: ties by id
    spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id bigint, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    d = ((v[:, None].astype(float) - v[None]) ** 2).sum(2)
    np.fill_diagonal(d, np.inf)
    want = {(min(i, int(j)), max(i, int(j))) for i in range(700) for j in np.lexsort((np.arange(700), d[i]))[:10]}
    got = embedding_edges(spark, str(tmp_path), k=8, block=200).collect()
    assert {(r["u"], r["v"]) for r in got} == want and len(got) == len(want)
    assert all(abs(r["aff"] - 2.0 ** -d[r["u"], r["v"]]) < 1e-9 for r in got)


def test_large_groups_of_documents_stay_in_the_partition(spark, tmp_path):
    from segraph.plans import partitions

    base = " ".join(f"w{i}" for i in range(40))
    texts = [base] * 70 + [f"{base} tail{i}" for i in range(70)] + [" ".join(f"x{i}y{j}" for j in range(20)) for i in range(5)] + ["a b", "", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = partitions.docs_partition(spark, str(tmp_path)).collect()
    assert sorted((r["node"], r["label"]) for r in got) == [(i, 0) for i in range(140)]


def test_adoption_keeps_labels_beyond_doubles(spark):
    from segraph.operators.adopt import adopt

    big = 2**60 + 1
    labels = spark.createDataFrame([(1, 1, big), (1, 2, None), (1, 3, None)], "scene_id bigint, node bigint, label bigint")
    edges = spark.createDataFrame([(1, 1, 2, 0.9), (1, 2, 3, 0.4)], "scene_id bigint, u bigint, v bigint, aff double")
    for order in ("sync", "seeded"):
        assert sorted((r["node"], r["label"]) for r in adopt(labels, edges, order=order).collect()) == [(1, big), (2, big), (3, 0)]
    assert sorted((r["node"], r["label"]) for r in adopt(labels, edges, engine="rounds").collect()) == [(1, big), (2, big), (3, 0)]


def test_rounds_that_do_not_end_are_an_error(spark):
    from segraph.operators.rounds import contract_rounds

    nodes = spark.createDataFrame([(1, 1), (1, 2)], "scene_id bigint, node bigint")
    edges = spark.createDataFrame([(1, 1, 2, 0.9)], "scene_id bigint, u bigint, v bigint, aff double")
    with pytest.raises(RuntimeError):
        contract_rounds(edges, nodes, max_rounds=1)
    assert {r["label"] for r in contract_rounds(edges, nodes).collect()} == {1}
