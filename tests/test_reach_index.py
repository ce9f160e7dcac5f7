import random

import pytest

from reachgraph.operators.baselines import closure, frontier_reach, recursive_cte_reach, vertex_centric_reach
from reachgraph.operators.partition import ComponentPartitioner, HashPartitioner, LocalityPartitioner, RangePartitioner, check_partition
from reachgraph.operators.reach_index import ReachIndex

MICRO = {
    # edges, shard of each vertex, (pairs that must hold, pairs that must not)
    "chain": ([(1, 2), (2, 3), (3, 4)], {1: 0, 2: 0, 3: 1, 4: 1}, [(1, 4)], [(4, 1)]),
    "dual": ([(1, 2), (2, 3), (2, 4), (3, 4), (3, 5)], {1: 0, 2: 1, 3: 1, 4: 2, 5: 3}, [(1, 5)], [(5, 1)]),
    "entry classes": ([(1, 3), (2, 4), (3, 5), (4, 5), (5, 6), (4, 7)], {1: 0, 2: 0, 3: 1, 4: 1, 5: 1, 7: 1, 6: 2}, [(2, 7), (1, 6)], [(1, 7)]),
    "exit classes": ([(1, 9), (9, 2), (9, 3), (8, 2), (2, 6), (3, 7)], {1: 0, 2: 1, 3: 1, 8: 1, 9: 1, 6: 2, 7: 3}, [(8, 6), (1, 6), (1, 7)], [(8, 7)]),
    "re-enter": ([(1, 2), (2, 3), (3, 4)], {1: 0, 4: 0, 2: 1, 3: 1}, [(1, 4)], [(4, 2)]),
    "two cycles": ([(1, 2), (2, 1), (2, 3), (3, 4), (4, 3)], {1: 0, 3: 0, 2: 1, 4: 1}, [(1, 4), (1, 1)], [(3, 1)]),
    "self-loop": ([(1, 1), (1, 2)], {1: 0, 2: 1}, [(1, 1), (1, 2)], [(2, 2)]),
    "diamond": ([(1, 2), (1, 3), (2, 4), (3, 4)], {1: 0, 2: 1, 3: 2, 4: 0}, [(1, 4)], [(2, 3)]),
}


class Given:
    """Shards by a table."""

    def __init__(self, spark, shard):
        self.df = spark.createDataFrame(list(shard.items()), "v long, part int")

    def parts(self, edges):
        return self.df


def search(edges):
    out = set()
    for s in {e[0] for e in edges}:
        seen, todo = set(), [s]
        while todo:
            v = todo.pop()
            new = {b for a, b in edges if a == v} - seen
            seen |= new
            todo += new
        out |= {(s, t) for t in seen}
    return out


@pytest.mark.parametrize("name", MICRO)
@pytest.mark.parametrize("options", [{}, {"compress": False}, {"layout": "compound"}], ids=["classes", "plain", "compound"])
def test_micro_graphs(spark, name, options):
    edges, shard, yes, no = MICRO[name]
    e = spark.createDataFrame(edges, "s long, t long")
    v = spark.createDataFrame([(x,) for x in shard], "v long")
    ix = ReachIndex.build(e, partitioner=Given(spark, shard), **options)
    got = {(r.x, r.y) for r in ix.set_reach(v, v, "+", plus="cycle").collect()}
    assert got == search(edges)
    assert set(yes) <= got and not set(no) & got
    distinct = {(r.x, r.y) for r in ix.set_reach(v, v, "+").collect()}
    assert distinct == {p for p in got if p[0] != p[1]}


@pytest.fixture(scope="module")
def world(spark):
    rng = random.Random(11)
    edges = []
    for g in range(25):
        n = rng.randint(2, 20)
        edges += [(g * 100 + rng.randrange(n), g * 100 + rng.randrange(n)) for _ in range(rng.randint(n // 2, 2 * n))]
    return edges, spark.createDataFrame(edges, "s long, t long")


@pytest.mark.parametrize("make", [lambda: HashPartitioner(1), lambda: HashPartitioner(5), lambda: ComponentPartitioner(3), lambda: LocalityPartitioner(3, 2), lambda: RangePartitioner(3)])
def test_partitioners_give_the_same_pairs(spark, world, make):
    edges, e = world
    part = make()
    assert check_partition(part.parts(e), e).count() == 0
    v = spark.createDataFrame([(x,) for x in {x for p in edges for x in p} | {9999}], "v long")
    ix = ReachIndex.build(e, partitioner=part)
    assert {(r.x, r.y) for r in ix.set_reach(v, v, "+", plus="cycle").collect()} == search(edges)
    star = {(r.x, r.y) for r in ix.set_reach(v, v, "*").collect()}
    assert star == search(edges) | {(x, x) for p in edges for x in p} | {(9999, 9999)}
    assert (9999, 9999) not in {(r.x, r.y) for r in ix.set_reach(v, v, "*", zero_scope="vertices").collect()}
    opt = {(r.x, r.y) for r in ix.set_reach(v, v, "?").collect()}
    assert opt <= star and set(edges) <= opt


def test_baselines_agree(spark, world):
    edges, e = world
    v = spark.createDataFrame([(x,) for x in sorted({p[0] for p in edges})[::3]], "v long")
    expected = {p for p in search(edges) if p[0] in {r.v for r in v.collect()}}
    for pairs in (frontier_reach(e, v, plus="cycle"), vertex_centric_reach(e, v, plus="cycle"), closure(e, "doubling").join(v.withColumnRenamed("v", "x"), "x")):
        assert {(r.x, r.y) for r in pairs.collect()} == expected
    chain = spark.createDataFrame([(i, i + 1) for i in range(30)], "s long, t long")
    one = spark.createDataFrame([(0,)], "v long")
    assert recursive_cte_reach(spark, chain, one).count() == 30


def test_one_exchange_whatever_the_diameter(spark):
    from reachgraph.measures import rounds

    chain = spark.createDataFrame([(i, i + 1) for i in range(60)], "s long, t long")
    ix, counts = ReachIndex.build(chain, 4), []
    one = spark.createDataFrame([(0,)], "v long")
    ends = chain.selectExpr("t AS v")
    assert rounds(ix, one, ends) == 1
    short = chain.where("s < 10")
    assert rounds(ReachIndex.build(short, 4, max_boundary=0), one, short.selectExpr("t AS v")) > 5
    assert frontier_reach(chain, one, counts=counts).count() == 60 == ix.set_reach(one, chain.selectExpr("t AS v"), "+").count()
    assert len(counts) > 50


def test_nulls_and_empty_tables(spark):
    e = spark.createDataFrame([(1, None), (None, 2), (1, 2), (1, 2)], "s long, t long")
    v = spark.createDataFrame([(1,), (2,), (None,), (1,)], "v long")
    assert ReachIndex.build(e, 2).set_reach(v, v, "+").collect() == [(1, 2)]
    none = spark.createDataFrame([], "s long, t long")
    assert ReachIndex.build(none, 2).set_reach(v, v, "+").count() == 0
    assert ReachIndex.build(none, 2).set_reach(v, v, "*").count() == 2


def test_auto_partitioner_keeps_chains_whole(spark):
    from reachgraph.measures import rounds

    chains = spark.createDataFrame([(c * 100 + i, c * 100 + i + 1) for c in range(40) for i in range(30)], "s long, t long")
    ix = ReachIndex.build(chains)
    assert ix.cut.count() == 0 and check_partition(ix.parts, chains).count() == 0
    v = chains.selectExpr("s AS v")
    assert ix.set_reach(v, v, "+").count() == 40 * 30 * 29 // 2
    assert rounds(ix, v, v) <= 1
    one = spark.createDataFrame([(i, i + 1) for i in range(90)], "s long, t long")
    assert ReachIndex.build(one).parts is None  # one component for all shards


def test_saved_and_backward_indexes_give_the_same_pairs(spark, world, tmp_path):
    edges, e = world
    v = spark.createDataFrame([(x,) for x in {x for p in edges for x in p}], "v long")
    few = v.where("v % 7 = 0")
    for make in (lambda: HashPartitioner(4), lambda: ComponentPartitioner(3)):
        ix = ReachIndex.build(e, 4, make())
        again = ReachIndex.load(spark, ix.save(str(tmp_path / "ix")))
        expected = {(r.x, r.y) for r in ix.set_reach(v, few, "+", plus="cycle").collect()}
        assert expected == {p for p in search(edges) if p[1] % 7 == 0}
        assert {(r.x, r.y) for r in again.set_reach(v, few, "+", plus="cycle").collect()} == expected
        for direction in ("backward", "auto"):
            assert {(r.x, r.y) for r in ix.set_reach(v, few, "+", plus="cycle", direction=direction).collect()} == expected
        star = {(r.x, r.y) for r in ix.set_reach(v, few, "*").collect()}
        assert {(r.x, r.y) for r in ix.set_reach(v, few, "*", direction="backward").collect()} == star


def test_components_in_a_task_and_by_rounds(spark, world):
    from reachgraph.operators.partition import weak_components

    _, e = world
    assert sorted(map(tuple, weak_components(e).collect())) == sorted(map(tuple, weak_components(e, task_edges=0).collect()))


@pytest.mark.parametrize("options", [{}, {"layout": "compound"}, {"max_boundary": 0}], ids=["shared", "compound", "joins"])
def test_on_cycles_finds_the_vertices_that_reach_themselves(spark, world, options):
    edges, e = world
    v = spark.createDataFrame([(x,) for x in {x for p in edges for x in p} | {9999}], "v long")
    ix = ReachIndex.build(e, 3, **options)
    assert {r.v for r in ix.on_cycles(v).collect()} == {x for x, y in search(edges) if x == y}


def test_what_departs_is_named_by_classes(spark):
    n = 300
    ring = spark.createDataFrame([(i, (i + 1) % n) for i in range(n)], "s long, t long")
    v = ring.selectExpr("s AS v")
    for ix in (ReachIndex.build(ring, 1), ReachIndex.build(ring, 3)):
        assert ix._depart(v, v).count() <= 5 * n  # and not one row per pair
        assert ix.set_reach(v, v, "+", plus="cycle").count() == n * n


def test_unrolled_chains_reach_any_length(spark):
    from reachgraph.operators.baselines import unrolled_reach

    chain = spark.createDataFrame([(i, i + 1) for i in range(7)] + [(7, 3)], "s long, t long")
    one = spark.createDataFrame([(0,)], "v long")
    got = unrolled_reach(chain, one, chain.selectExpr("t AS v"), most=None, unroll=2)
    assert sorted(r.y for r in got.collect()) == list(range(1, 8))


def test_boundary_is_the_smaller_of_plain_and_compressed(spark):
    rng = random.Random(4)
    edges = {(rng.randrange(400), rng.randrange(400)) for _ in range(350)}
    df = spark.createDataFrame([(a, b) for a, b in edges if a != b], "s long, t long")
    small, plain = ReachIndex.build(df, 4), ReachIndex.build(df, 4, compress=False)
    assert small.boundary.count() <= plain.boundary.count()
    v = df.selectExpr("s AS v").union(df.selectExpr("t")).distinct()
    assert set(map(tuple, small.set_reach(v, v, "+", plus="cycle").collect())) == search([(a, b) for a, b in edges if a != b])
