import random

import pytest

from reachgraph.operators.condensed import CondensedIndex, flooded
from reachgraph.operators.reach_index import ReachIndex
from reachgraph.plans.engine import Graph
from tests.test_reach_index import MICRO, search


def _world():
    rng = random.Random(5)
    hub = [(rng.randrange(40), rng.randrange(40)) for _ in range(70)]  # one large component with what leads in and out
    return hub + [(50, 51), (51, 50), (51, 52), (52, 52), (60, 61), (61, 62), (52, 3), (3, 60)]


@pytest.mark.parametrize("name", [*MICRO, "world"])
def test_condensed_pairs_equal_search(spark, name):
    edges = _world() if name == "world" else MICRO[name][0]
    e = spark.createDataFrame(edges, "s long, t long")
    v = spark.createDataFrame([(x,) for x in {x for p in edges for x in p} | {99}] + [(None,)], "v long")
    ix, want = CondensedIndex.build(e), search(edges)
    rows = [(r.x, r.y) for r in ix.set_reach(v, v, "+", plus="cycle").collect()]
    assert len(rows) == len(set(rows)) and set(rows) == want
    assert {(r.x, r.y) for r in ix.set_reach(v, v, "+").collect()} == {p for p in want if p[0] != p[1]}
    star = [(r.x, r.y) for r in ix.set_reach(v, v, "*").collect()]
    assert sorted(star) == sorted(want | {(r.v, r.v) for r in v.collect() if r.v is not None})
    assert {r.v for r in ix.on_cycles(v).collect()} == {x for x, y in want if x == y}
    if isinstance(ix, CondensedIndex):
        pairs = v.select("v").toDF("a").crossJoin(v.toDF("b"))
        for plus in ("distinct", "cycle"):
            met = [(r.a, r.b) for r in ix.meets(pairs, "a", "b", plus=plus).collect()]
            assert sorted(met) == sorted(p for p in want if plus == "cycle" or p[0] != p[1])
        assert sorted((r.a, r.b) for r in ix.meets(pairs, "a", "b", "*").collect()) == sorted(star)


def test_hub_is_taken_out_of_the_index(spark):
    n = 300
    ring = [(i, (i + 1) % n) for i in range(n)]
    ix = CondensedIndex.build(spark.createDataFrame(ring + [(1000, 0), (5, 2000)], "s long, t long"))
    assert ix.inner.edges.isEmpty()  # before, 300 vertices that all lead everywhere lay in all shards
    v = spark.createDataFrame([(1000,), (7,), (2000,)], "v long")
    assert {(r.x, r.y) for r in ix.set_reach(v, v).collect()} == {(1000, 7), (1000, 2000), (7, 2000)}


@pytest.mark.parametrize("most", [0, 10**6])
def test_what_is_left_is_sent_whole_or_laid_out(spark, monkeypatch, most):
    from reachgraph.operators import condensed

    monkeypatch.setattr(condensed, "SENT_EDGES", most)
    ix = CondensedIndex.build(spark.createDataFrame(_world(), "s long, t long"))
    v = spark.createDataFrame([(x,) for x in range(70)], "v long")
    assert {(r.x, r.y) for r in ix.set_reach(v, v, "+", plus="cycle").collect()} == search(_world())
    assert ("inner" in ix.__dict__) == (most == 0)  # before, shards and a boundary were always built
    monkeypatch.setattr(condensed, "SENT_ROWS", 3)
    assert {(r.x, r.y) for r in ix.set_reach(v, v, "+", plus="cycle").collect()} == search(_world())


def test_acyclic_and_large_graphs_get_a_plain_index(spark):
    assert isinstance(CondensedIndex.build(spark.createDataFrame([(1, 2)], "s long, t long")), ReachIndex)
    assert isinstance(CondensedIndex.build(spark.createDataFrame([(1, 2), (2, 1)], "s long, t long"), task_edges=1), ReachIndex)


def test_rows_with_both_ends_are_checked_without_all_pairs(spark):
    n = 200
    near = spark.createDataFrame([(i, (i + 1) % n) for i in range(n)], "s long, o long")
    of = spark.createDataFrame([(i, 5000 + i // 2) for i in range(n)], "s long, o long")
    g = Graph(spark, {"near": lambda: near, "of": lambda: of}, lambda c: None)
    got = {(r.x, r.y) for r in g.match("SELECT ?x ?y WHERE { ?x of ?p . ?y of ?p . ?x near+ ?y }").collect()}
    assert got == {(i, i ^ 1) for i in range(n)}


def test_sides_of_many_equal_rows_are_connected_by_the_predicate(spark, monkeypatch):
    from reachgraph.plans import engine

    near = spark.createDataFrame([(i, i + 1) for i in range(0, 60, 3)] + [(i + 1, i + 2) for i in range(0, 60, 6)], "s long, o long")
    of = spark.createDataFrame([(i, 5000 + i % 2) for i in range(60)], "s long, o long")
    kind = spark.createDataFrame([(i, 9000) for i in range(60)], "s long, o long")
    got = []
    for most in (0, 10**9):
        monkeypatch.setattr(engine, "CROWD", most)
        g = Graph(spark, {"near": lambda: near, "of": lambda: of, "kind": lambda: kind}, lambda c: 9000)
        got.append(sorted((r.x, r.y) for r in g.match('SELECT ?x ?y WHERE { ?x kind "k" . ?x of ?b . ?y of ?b . ?x near+ ?y }').collect()))
    assert got[0] == got[1] == [(i, i + 2) for i in range(0, 60, 6)]


@pytest.mark.parametrize(("marks", "plus"), [("+*", "distinct"), ("*+", "cycle"), ("++", "distinct")])
def test_middle_that_no_one_asks_for_is_never_joined(spark, monkeypatch, marks, plus):
    from reachgraph.plans import engine
    from reachgraph.plans.engine import _Run

    edges = _world()
    kinds = [(v, 9000 + (v % 4 if v % 5 else 2)) for v in range(70)] + [(v, 9002) for v in (0, 3, 99)] + [(v, 9001) for v in (51, 52, 98, 99)] + [(v, 9003) for v in (52, 61, 99)]  # some in two classes, some on no edge
    near, kind = spark.createDataFrame(edges, "s long, o long"), spark.createDataFrame(kinds, "s long, o long")
    of = lambda k: {v for v, c in kinds if c == k}
    pairs = search(edges)
    legs = [pairs if m == "+" and plus == "cycle" else {p for p in pairs if p[0] != p[1]} | ({(v, v) for v in range(100)} if m == "*" else set()) for m in marks]
    want = {(a, c) for a, b in legs[0] if a in of(9001) and b in of(9002) for d, c in legs[1] if d == b and c in of(9003)}
    monkeypatch.setattr(engine, "CROWD", -1)
    g = Graph(spark, {"near": lambda: near, "kind": lambda: kind}, lambda c: int(c.text), plus=plus)
    text = 'SELECT DISTINCT ?a ?c WHERE {{ ?a kind "9001" . ?a near{} ?b . ?b kind "9002" . ?b near{} ?c . ?c kind "9003" }}'.format(*marks)
    got = [(r.a, r.c) for r in g.match(text).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    assert any("over" in name for name in g._indexes)
    asked, pairs_of = [], _Run.pairs
    monkeypatch.setattr(_Run, "pairs", lambda self, x, y, c: asked.append(c) or pairs_of(self, x, y, c))
    apart = text.replace("9001", "9004")  # a class that shares no vertex with the middle, as the last does not with the second
    kind = spark.createDataFrame([(v, c) for v, c in kinds if c == 9002] + [(v, 9004) for v in range(70) if v not in of(9002)] + [(v, 9003) for v in range(70) if v not in of(9002)], "s long, o long")
    g = Graph(spark, {"near": lambda: near, "kind": lambda: kind}, lambda c: int(c.text), plus=plus)
    rest = {v for v in range(70) if v not in of(9002)}
    met = {(a, c) for a, b in legs[0] if a in rest and b in of(9002) for d, c in legs[1] if d == b and c in rest}
    got = [(r.a, r.c) for r in g.match(apart).collect()]
    assert len(got) == len(set(got)) and set(got) == met and not asked  # before, the pairs of both predicates were joined


def test_middle_that_is_asked_for_is_kept(spark, monkeypatch):
    from reachgraph.plans import engine

    monkeypatch.setattr(engine, "CROWD", -1)
    near = spark.createDataFrame([(1, 2), (2, 1), (2, 3), (3, 4)], "s long, o long")
    kind = spark.createDataFrame([(1, 7), (2, 8), (3, 8), (4, 9)], "s long, o long")
    g = Graph(spark, {"near": lambda: near, "kind": lambda: kind}, lambda c: int(c.text))
    text = 'SELECT DISTINCT ?a ?b ?c WHERE { ?a kind "7" . ?a near+ ?b . ?b kind "8" . ?b near+ ?c . ?c kind "9" }'
    assert sorted(map(tuple, g.match(text).collect())) == [(1, 2, 4), (1, 3, 4)]
    assert [tuple(r) for r in g.match(text.replace("?b ?c WHERE", "?c WHERE")).collect()] == [(1, 4)]
    assert sorted(map(tuple, g.match(text.replace("DISTINCT ?a ?b", "?a")).collect())) == [(1, 4), (1, 4)]
    wide = near.selectExpr("s + (1L << 62) AS s", "o + (1L << 62) AS o")
    g = Graph(spark, {"near": lambda: wide, "kind": lambda: kind.selectExpr("s + (1L << 62) AS s", "o")}, lambda c: int(c.text))
    assert [tuple(r) for r in g.match(text.replace("?b ?c WHERE", "?c WHERE")).collect()] == [(1 + (1 << 62), 4 + (1 << 62))]


def test_nearest_vectors_are_found_slice_by_slice(spark, monkeypatch, tmp_path):
    import numpy as np

    from reachgraph.sources import graphs

    rng = np.random.default_rng(3)
    vectors = rng.normal(size=(60, 5)).round(1)
    vectors[40:] = vectors[:20]  # ties
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(vectors)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").coalesce(2).write.parquet(f"{tmp_path}/embeddings.parquet")
    monkeypatch.setattr(graphs, "CELLS", 150)
    e, want = np.array([r[1] for r in rows], dtype=np.float32).astype(np.float64), set()
    for i in range(60):
        like = [(-round(float(sum(e[i] * e[j])) / float(np.sqrt(sum(e[j] * e[j]))), 12), j) for j in range(60) if j != i and e[j].any()]
        want |= {(i, j) for _, j in sorted(like)[:3]}
    run, most = graphs._nearest, []

    def watched(ids, matrix, neighbours):
        most.append(len(ids))
        return run(ids, matrix, neighbours)

    monkeypatch.setattr(graphs, "_nearest", watched)
    assert {(r.s, r.t) for r in graphs.near_edges(spark, str(tmp_path)).collect()} == want and most == [60]
