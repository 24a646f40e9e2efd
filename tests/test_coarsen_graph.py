"""Independent sets, restriction, coarsening and graph functions against brute force."""

import pytest

from layermul.functions.sqlapi import product_sql, register, sql_multiply
from layermul.matrix import SparseMatrix
from layermul.operators import coarsen, graph, vector
from layermul.plans.multiply import catalyst
from layermul.semiring import MIN_SECOND
from layermul.sources import io
from layermul.sources.generators import rmat


def undirected(spark, edges, n):
    return SparseMatrix.rows_of(spark, [(a, b, 1) for x, y in edges for a, b in ((x, y), (y, x))], n, n)


GRAPHS = {
    "star": ([(0, k) for k in range(1, 6)], 6),
    "path": ([(k, k + 1) for k in range(6)], 7),
    "two_parts": ([(0, 1), (1, 2), (3, 4)], 5),
    "isolated": ([(0, 1)], 4),
    "self_loop": ([(0, 0), (0, 1)], 3),
}


def within(edges, n, hops):
    near = {v: {v} for v in range(n)}
    beside = {v: {v} for v in range(n)}
    for a, b in edges:
        beside[a].add(b)
        beside[b].add(a)
    for _ in range(hops):
        near = {v: set().union(*(beside[u] for u in near[v])) for v in range(n)}
    return near


@pytest.mark.parametrize("name", GRAPHS)
@pytest.mark.parametrize("hops", [1, 2])
def test_independent_sets(spark, name, hops):
    edges, n = GRAPHS[name]
    a = undirected(spark, edges, n)
    s = coarsen.independent_set(a, hops=hops)
    members = {r["i"] for r in s.collect()}
    near = within(edges, n, hops)
    assert all(near[v] & members for v in range(n)) and all(near[v] & members == {v} for v in members)
    assert coarsen.verify_independent_set(a, s, hops).first()["violations"] == 0
    if name == "star" and hops == 2:
        assert len(members) == 1


def test_restriction_and_coarsening(spark):
    edges, n = GRAPHS["path"]
    a = undirected(spark, edges, n)
    r = coarsen.restriction(a, coarsen.mis2(a))
    assert coarsen.verify_restriction(r).first()["violations"] == 0 and r.nnz() == n
    cells = lambda m: {(x["i"], x["j"]): x["v"] for x in m.df.collect()}
    both = cells(coarsen.galerkin(a, r, "left"))
    assert both == cells(coarsen.galerkin(a, r, "right")) == cells(coarsen.galerkin(a, r, "auto")) == cells(coarsen.contract(a, r.df.selectExpr("i", "j AS c"), r.ncols))
    assert sum(both.values()) == 2 * len(edges)
    weights = coarsen.restriction(a, coarsen.mis2(a), average=True).df.groupBy("j").sum("v").collect()
    assert all(abs(w[1] - 1) < 1e-9 for w in weights)
    assert coarsen.hierarchy(a, 2)[-1][0].nrows <= n


def test_triangles_cycles_and_paths(spark):
    edges = [(0, 1), (1, 2), (0, 2), (2, 3)]
    a = undirected(spark, edges, 5)
    assert graph.triangles(a).first()["triangles"] == 1
    ring = SparseMatrix.rows_of(spark, [(0, 1, 2), (1, 2, 3), (2, 0, 4)], 3, 3)
    assert [r["vertices"] for r in graph.cycle_lengths(ring, 3).orderBy("length").collect()] == [0, 0, 3]
    assert graph.has_cycle(ring, 3) and not graph.has_cycle(ring, 2)
    assert {(r["i"], r["j"]): r["v"] for r in graph.khop_costs(ring, 2).df.collect()} == {(0, 2): 5, (1, 0): 7, (2, 1): 6}
    assert {(r["i"], r["j"]): r["v"] for r in graph.widest_paths(ring, 2).df.collect()} == {(0, 2): 2, (1, 0): 3, (2, 1): 2}


def test_betweenness_of_a_path(spark):
    a = undirected(spark, GRAPHS["path"][0], 7)
    got = {r["i"]: r["v"] for r in graph.betweenness(a, list(range(7))).collect() if r["v"]}
    assert got == {k: 2.0 * k * (6 - k) for k in range(1, 6)}


def test_betweenness_of_long_paths_raises(spark):
    a = undirected(spark, GRAPHS["path"][0], 7)
    assert {r["i"]: r["v"] for r in graph.betweenness(a, [0], longest=6).collect()} == {k: 6.0 - k for k in range(1, 6)}
    with pytest.raises(ValueError):
        graph.betweenness(a, [0], longest=5)


def test_clusters(spark):
    a = undirected(spark, [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5)], 6)
    c = {r["i"]: r["c"] for r in graph.flow_clusters(a, rounds=6).collect()}
    assert len({c[0], c[1], c[2]}) == 1 and len({c[3], c[4], c[5]}) == 1 and c[0] != c[3]
    p = {r["i"]: r["v"] for r in graph.peer_pressure(a, rounds=3).collect()}
    assert p == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 3}


def test_schur_complement(spark):
    m = SparseMatrix.rows_of(spark, [(0, 0, 2), (1, 1, 4), (0, 2, 6), (1, 2, 8), (2, 0, 1), (2, 1, 1), (2, 2, 10)], 3, 3)
    assert [tuple(r) for r in graph.schur_diagonal(m, 2).df.collect()] == [(0, 0, 10 - 6 / 2 - 8 / 4)]


def test_vectors(spark):
    v = spark.createDataFrame([(0, 5), (2, 1)], "i bigint, v bigint")
    a = SparseMatrix.rows_of(spark, [(0, 0, 9), (0, 2, 9), (1, 1, 9)], 3, 3)
    assert [tuple(r) for r in vector.mxv(a, v, MIN_SECOND).collect()] == [(0, 1)]
    w = spark.createDataFrame([(2, 10)], "i bigint, v bigint")
    assert sorted(map(tuple, vector.ewise_add(v, w).collect())) == [(0, 5), (2, 11)]
    assert [tuple(r) for r in vector.ewise_mult(v, w).collect()] == [(2, 10)] and [tuple(r) for r in vector.mask_out(v, w).collect()] == [(0, 5)]


def test_io_and_sql(spark, tmp_path):
    a = rmat(spark, "community", 5)
    want = sorted(map(tuple, a.df.collect()))
    io.write_coo_text(a, f"{tmp_path}/coo")
    back = io.read_coo_text(spark, f"{tmp_path}/coo")
    assert sorted(map(tuple, back.df.collect())) == want and (back.nrows, back.ncols) == (32, 32)
    io.save_bucketed(a, "bucketed_a", 4)
    assert sorted(map(tuple, spark.table("bucketed_a").select("i", "j", "v").collect())) == want
    register(spark, sql_a=a)
    assert sorted(map(tuple, sql_multiply(spark, "sql_a", "sql_a").collect())) == sorted(map(tuple, catalyst(a, a).df.collect()))
    assert "JOIN sql_a b" in product_sql("sql_a", "sql_a")
