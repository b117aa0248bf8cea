"""Worked examples and invariants of the graph kernel."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from vecrag.operators import kernel
from vecrag.operators.kernel import Graph, draw_level

POINTS = {0: (6, 9), 1: (4, 11), 2: (10, 6), 3: (4, 3), 4: (3, 5), 5: (2, 3), 6: (6, 4), 7: (7, 8)}


def example(ids, ef=4):
    return Graph.build(ids, np.array([POINTS[i] for i in ids], float), mode="incremental", m=3, alpha=1.2, ef_build=ef, levels=[0] * len(ids))


def names(graph, node):
    return {graph.ids[n] for n in graph.links[graph.at[node]][0]}


def check(graph):
    """Caps, no self, repeated or dangling links, all reachable, entry of the top level."""
    for at, levels in enumerate(graph.links):
        assert len(levels) == graph.levels[at] + 1
        for lv, links in enumerate(levels):
            assert at not in links and len(set(links)) == len(links)
            assert len(links) <= graph.cap(lv) + graph.overflow_count
            assert all(0 <= n < len(graph.ids) and graph.levels[n] >= lv for n in links)
    if graph.ids:
        assert graph.reachable() == set(range(len(graph.ids)))
        assert graph.levels[graph.entry] == graph.max_level == max(graph.levels)
    else:
        assert graph.entry == -1


def test_insertion_example():
    pts = np.array([POINTS[i] for i in range(8)], float)
    g = Graph(dim=2, m=3, alpha=1.2)
    for i in range(8):
        g._append(i, pts[i], 0)
    g.links = [[[]] for _ in range(8)]
    assert [g.ids[n] for n in g.prune(6, [2, 3, 4, 5], 3)] == [3, 2]
    assert {g.ids[n] for n in g.prune(7, [0, 1, 2, 6], 3)} == {0, 2, 6}
    grown = example(list(range(8)))
    check(grown)
    assert 2 in names(grown, 7) and 7 in names(grown, 2)


def test_deletion_example():
    g = example(range(6))
    g.delete_many([3, 4])
    check(g)
    assert set(g.ids) == {0, 1, 2, 5}
    assert 1 in names(g, 0) and 0 in names(g, 1)


def test_levels_are_a_function_of_the_id():
    levels = [draw_level(i, 16) for i in range(20000)]
    assert levels == [draw_level(i, 16) for i in range(20000)]
    assert abs(np.mean(np.array(levels) >= 1) - 1 / 16) < 0.01


@pytest.mark.parametrize("mode", ["batch", "incremental"])
def test_full_width_is_exact(mode):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(120, 8))
    g = Graph.build(list(range(120)), x, mode=mode)
    check(g)
    for q in rng.normal(size=(10, 8)):
        want = sorted(range(120), key=lambda i: (np.sqrt(((x[i] - q) ** 2).sum()), i))[:10]
        got, counted = g.search(q, 10, 120)
        assert [i for _, i in got] == want and counted >= 120


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 40), st.integers(0, 10_000))
def test_random_updates_keep_invariants(n, seed):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(60, 4))
    g = Graph.build(list(range(n)), x[:n].reshape(n, 4), mode="incremental", m=4)
    alive = set(range(n))
    for _ in range(30):
        i = int(rng.integers(60))
        if rng.random() < 0.5:
            g.insert(i, x[i])
            alive.add(i)
        else:
            assert g.delete(i) == (i in alive)
            alive.discard(i)
        g.repair()  # a pruned reverse link may have cut a node off
        check(g)
    assert set(g.ids) == alive


def test_edges():
    g = Graph(dim=2)
    assert g.search(np.zeros(2), 5, 10) == ([], 0)
    assert not g.delete(3)
    g.insert(1, [0, 0])
    assert g.search(np.zeros(2), 5, 10)[0] == [(0.0, 1)]
    g.insert(1, [1, 0])  # again: replaced
    assert len(g.ids) == 1 and g.search(np.zeros(2), 1, 1)[0] == [(1.0, 1)]
    g.delete(1)
    assert g.entry == -1
    g.insert(2, [0, 1])
    assert g.entry == 0
    assert g.search(np.zeros(2), 0, 5) == ([], 0)
    with pytest.raises(ValueError):
        g.insert(3, [1.0])
    with pytest.raises(ValueError):
        g.insert(3, [np.nan, 1.0])


def test_duplicate_vectors_order_by_id():
    g = Graph.build([5, 3, 9], np.ones((3, 4)))
    assert [i for _, i in g.search(np.ones(4), 3, 10)[0]] == [3, 5, 9]


def test_lazy_delete_and_purge():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(50, 4))
    g = Graph.build(list(range(50)), x)
    for i in range(0, 50, 2):
        g.delete(i, lazy=True)
    assert all(i % 2 for _, i in g.search(x[4], 10, 60)[0])
    assert g.purge() == 25
    check(g)
    assert all(i % 2 for i in g.ids)


def test_stored_form_round_trip():
    rng = np.random.default_rng(4)
    g = Graph.build(list(range(40)), rng.normal(size=(40, 4)).astype(np.float32))
    row = g.to_row()
    back = Graph.from_row(row)
    assert back.links == g.links and back.ids == g.ids and back.entry == g.entry
    again = back.to_row()
    assert {k: v for k, v in again.items() if k != "n_dist_build"} == {k: v for k, v in row.items() if k != "n_dist_build"}


def test_batch_links_equal_links_of_one_node_after_the_other(monkeypatch):
    rng = np.random.default_rng(12)
    hub = np.vstack([np.zeros((1, 16)), rng.normal(size=(900, 16))])
    for vecs in (hub[:2], hub[:70], hub, hub * 1e7):
        graph = kernel.Graph.build(range(len(vecs)), vecs)
        with monkeypatch.context() as m:
            m.setattr(kernel, "WIDEST", 0)
            m.setattr(kernel, "BLOCK_BYTES", 1 << 16)
            other = kernel.Graph.build(range(len(vecs)), vecs)
        assert graph.links == other.links
        seen = graph.reachable()
        assert len(seen) == len(vecs)


def test_links_are_chosen_alike_from_groups_and_for_a_part(monkeypatch):
    x = np.random.default_rng(5).normal(size=(900, 6))
    x[700:] = x[:200]  # equal vectors
    grouped = kernel.chosen_links(x, np.arange(900), 4, 6)
    monkeypatch.setattr(kernel, "GROUP", 1 << 20)
    whole = kernel.chosen_links(x, np.arange(900), 4, 6)
    assert all((a == b).all() for a, b in zip(grouped, whole, strict=True)) and max(map(len, whole)) == 4
    some = kernel.chosen_links(x, np.array([3, 500, 899]), 4, 6)
    assert [a.tolist() for a in some] == [whole[k].tolist() for k in (3, 500, 899)]
