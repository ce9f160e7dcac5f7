import random

import numpy as np
import pytest

from reachgraph.functions import kernels
from reachgraph.functions.kernels import Dag, components


def closure(edges, n, empty):
    out = set()
    for s in range(n):
        seen, todo = set(), [s]
        while todo:
            v = todo.pop()
            for a, b in edges:
                if a == v and b not in seen:
                    seen.add(b)
                    todo.append(b)
        out |= {(s, t) for t in seen | ({s} if empty else set())}
    return out


def test_reach_equals_search_on_random_graphs():
    rng = random.Random(5)
    for _ in range(400):
        n, m = rng.randint(1, 12), rng.randint(0, 24)
        edges = [(rng.randrange(n), rng.randrange(n)) for _ in range(m)]
        src, dst = (np.array([e[i] for e in edges], dtype=np.int64) for i in (0, 1))
        dag, v = Dag.of(src, dst, np.arange(n)), np.arange(n)
        for empty in (True, False):
            x, y = dag.reach(v, v, v, empty)
            assert set(zip(x.tolist(), y.tolist(), strict=True)) == closure(edges, n, empty)


def test_components_number_against_the_edges():
    src, dst = np.array([0, 1, 2, 3]), np.array([1, 0, 3, 4])
    comp = components(5, src, dst)
    assert comp[0] == comp[1] and len(set(comp.tolist())) == 4
    assert all(comp[a] >= comp[b] for a, b in zip(src, dst, strict=True))


def test_empty_graph():
    none = np.empty(0, dtype=np.int64)
    x, y = Dag.of(none, none).reach(none, none, none)
    assert len(x) == len(y) == 0


def test_sparse_graphs_are_walked_without_bit_rows(monkeypatch):
    rng = np.random.default_rng(5)
    dag = Dag.of(rng.integers(0, 3000, 2000), rng.integers(0, 3000, 2000))
    ask = lambda: set(zip(*(side.tolist() for side in dag.reach(dag.verts, dag.verts, dag.verts, empty_path=False)), strict=True))
    monkeypatch.setattr(kernels, "WALK_PAIRS", 0)
    by_rows = ask()
    monkeypatch.setattr(kernels, "WALK_PAIRS", 1 << 20)
    monkeypatch.setattr(Dag, "spread", lambda *_: pytest.fail("bit rows"))
    assert ask() == by_rows and len(by_rows) > 2000
