"""Registered queries return the whole result, against brute force on small tables."""

import random
import re
from collections import Counter

import duckdb
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from layermul.matrix import SparseMatrix
from layermul.operators import folded
from layermul.plans.multiply import multiply
from layermul.sources import datasets
from layermul.workloads import checksum, oracle_sql, queries

LITTLE = "/root/testdata/sf0.001"


def rows_of(product):
    """checksum() of {(i, j): v}."""
    out = {}
    for (i, j), v in product.items():
        n, total, mix = out.get(i, (0, 0, 0))
        out[i] = (n + 1, total + v, mix + v * (j % 97))
    return out


def run(spark, name, at):
    return {r[0]: tuple(r[1:]) for r in queries()[name](spark, str(at)).collect()}


def test_words_of_many_documents_stay_in_the_product(spark, tmp_path):
    texts = [f"The w{chr(97 + k % 26)} the {'rare' if k % 9 == 0 else 'x'}-{chr(97 + k // 26)}" for k in range(70)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    words = [Counter(re.findall("[a-z]+", t.lower())) for t in texts]
    rank = {w: r for r, w in enumerate(sorted(set().union(*words)))}
    assert sum("the" in w for w in words) > 50
    assert run(spark, "matrix_doc_token_whole", tmp_path) == rows_of({(i, rank[w]): v for i, c in enumerate(words) for w, v in c.items()})
    product = {(i, j): sum(v * b[w] for w, v in a.items()) for i, a in enumerate(words) for j, b in enumerate(words)}
    assert run(spark, "mm_doc_token_whole", tmp_path) == rows_of({c: v for c, v in product.items() if v})


def test_rows_folded_in_their_cells(spark, monkeypatch):
    r = random.Random(3)
    cells = lambda n, m, most: {(r.randrange(n), r.randrange(m) if r.random() < 0.7 else 0): r.randint(1, most) for _ in range(900)}
    monkeypatch.setattr(folded, "BLOCK_ENTRIES", 150)
    for most, at in ((3, 400), (10**5, 0), (10**8, 10**9)):  # exact in 24 bits, in 53, in neither; both ways, scattered, dense
        a, b = cells(70, 200, most), cells(200, 90, most)
        product = Counter()
        for (i, k), v in a.items():
            for j in range(90):
                product[i, j] += v * b.get((k, j), 0)
        product = rows_of({c: v for c, v in product.items() if v})
        if most == 3:
            one, two = (SparseMatrix.rows_of(spark, [(i, j, v) for (i, j), v in m.items()], n, k) for m, n, k in ((a, 70, 200), (b, 200, 90)))
            assert {x[0]: tuple(x[1:]) for x in folded.folded_rows(one, two).collect()} == product
        monkeypatch.setattr(folded, "SCATTERED", at)
        for tile, at_once in ((1 << 24, 1 << 21), (200, 50), (1, 1)):
            monkeypatch.setattr(folded, "TILE", tile)
            monkeypatch.setattr(folded, "AT_ONCE", at_once)
            left, right = block_of([(i, k, v) for (i, k), v in a.items()]), block_of([(j, k, v) for (k, j), v in b.items()])
            got = [x for batch in folded._folds(left, right, 97) for x in zip(*(c.to_pylist() for c in batch.columns), strict=True)]
            assert {x[0]: x[1:] for x in got} == product and len(got) == len(product)
    with pytest.raises(ValueError, match="positive"):
        block_of([(1, 1, 0)])


def test_groups_of_alike_rows_in_a_block(spark, monkeypatch):
    """Two kinds of rows fall apart, and products by dense rows, by spans and one by one are those of all rows."""
    r = random.Random(6)
    for name, value in (("GROUPS", 3), ("GROUP_ROWS", 8), ("SCATTERED", 3)):
        monkeypatch.setattr(folded, name, value)
    for most in (2, 10**5, 10**8):  # in 24 bits, in 53, in neither
        a, b = ({(i if i < n - 1 else None, r.randrange(40) + 40 * (i % 2) if r.random() < 0.8 else r.randrange(80, 300)): r.randint(1, most) for i in range(n) for _ in range(12)} for n in (60, 45))
        twice = [(i, k, v) for (i, k), v in a.items()] + [(0, 5, 1), (0, 5, 1)]
        left, right = block_of(twice), block_of([(j, k, v) for (j, k), v in b.items()])
        kinds = [set(left.ids[lo:hi][left.known[lo:hi]] % 2) for lo, hi in zip(left.groups, left.groups[1:], strict=False)]
        assert len(left.ids) == 60 and len(kinds) == 3 and any(len(k) == 1 for k in kinds)
        product = Counter()
        for i, k, v in twice:
            for j in {j for j, _ in b}:
                product[i, j] += v * b.get((j, k), 0)
        want = {}
        for turn in (lambda i, j: (i, j)), (lambda i, j: (j, i)):
            for (i, j), v in product.items():
                i, j = turn(i, j)
                n, total, mix = want.get((turn(0, 1), i), (0, 0, None))
                want[turn(0, 1), i] = (n + (v > 0), total + v, mix if j is None or not v else (mix or 0) + v * (j % 97))
        for tile, at_once, step in ((1 << 22, 1 << 21, 1 << 17), (100, 7, 50), (1, 1, 1)):
            for k, v in (("TILE", tile), ("AT_ONCE", at_once), ("SLICE", step)):
                monkeypatch.setattr(folded, k, v)
            for listed in (1, 3, 10**6):
                monkeypatch.setattr(folded, "LISTED", listed)
                batches = [[x for x in zip(*(c.to_pylist() for c in batch.columns), strict=True)] for batch in folded._folds(left, right, 97, True)]
                assert {((0, 1), x[0]): x[1:] for rows in batches[:-1] for x in rows} | {((1, 0), x[0]): x[1:] for x in batches[-1]} == {k: v for k, v in want.items() if v[0]}


def test_every_block_has_its_own_file(spark, monkeypatch):
    monkeypatch.setattr(folded, "BLOCK_ENTRIES", 30)
    blocks = folded._blocks(spark.range(90).selectExpr("id AS i", "array(id, id + 1) AS ks", "array(1L, 2L) AS vs"), 180, "test")
    assert blocks.count() == len({f for f, in blocks.select(F.input_file_name()).collect()}) == 6


def block_of(entries):
    """A block of entries (i, k, v), each a list of its own."""
    i, k, v = (list(x) for x in zip(*entries, strict=True))
    rows = pa.table({"i": pa.array(i, pa.int64()), "ks": pa.array([[x] for x in k], pa.list_(pa.int64())), "vs": pa.array([[x] for x in v], pa.list_(pa.int64()))})
    return folded._Block.of(*(c[0].as_py() for c in folded._packed((pa.scalar(0, pa.int32()),), rows).columns[1:]))


def test_mirrored_cells_of_a_square_product(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(folded, "BLOCK_ENTRIES", 20)
    r = random.Random(4)
    spark.createDataFrame([(r.choice([k, k, None]), " ".join(r.choice("abcdefgh") * r.randint(1, 3) for _ in range(9))) for k in range(60)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    m = datasets.doc_token(spark, str(tmp_path))
    assert run(spark, "mm_doc_token_whole", tmp_path) == {x[0]: tuple(x[1:]) for x in checksum(multiply(m, m.t, plan="catalyst")).collect()}


def test_document_product_keeps_no_entries(spark):
    plan = queries()["mm_doc_token_whole"](spark, LITTLE)._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate [i#" in plan and ", j#" not in plan  # sums of rows leave the cells, entries don't
    assert run(spark, "mm_doc_token_whole", LITTLE) == {x[0]: x[1:] for x in duckdb_rows("mm_doc_token_whole", LITTLE)}


def test_document_product_on_odd_rows(spark, tmp_path, monkeypatch):
    rows = [(None, "a b b"), (3, "b c"), (3, "b d"), (4, None), (5, ""), (None, "d"), (6, "Zz\u212a zz"), (100, "A, a; e")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    m = datasets.doc_token(spark, str(tmp_path))
    want = {r[0]: tuple(r[1:]) for r in checksum(multiply(m, m.t, plan="catalyst")).collect()}
    assert len(want) == 4 and run(spark, "mm_doc_token_whole", tmp_path) == want
    monkeypatch.setattr(datasets.F, "xxhash64", lambda *c: F.lit(7).cast("bigint"))  # all words clash
    assert run(spark, "mm_doc_token_whole", tmp_path) == want


def duckdb_rows(name, at):
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW documents AS SELECT * FROM '{at}/documents.parquet'")
        return db.execute(oracle_sql()[name]).fetchall()


def test_rectangular_product_has_all_rows(spark):
    cust = {}
    orders = {r["o_orderkey"]: r["o_custkey"] for r in spark.read.parquet(f"{LITTLE}/orders.parquet").select("o_orderkey", "o_custkey").collect()}
    for order, part, n in spark.read.parquet(f"{LITTLE}/lineitem.parquet").selectExpr("l_orderkey", "l_partkey", "cast(l_quantity as bigint)").collect():
        if order in orders:
            cust.setdefault(orders[order], Counter())[part] += n
    product = Counter()
    for bought in cust.values():
        for i, x in bought.items():
            for j, y in bought.items():
                product[i, j] += x * y
    got = run(spark, "mm_grid2d_rect_whole", LITTLE)
    assert got == rows_of(product) and any(i % 10 for i in got)


def test_panels_cover_every_column(spark, tmp_path):
    spark.createDataFrame([(p,) for p in (5, 74_000, 74_001, 90_123)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    got = {k: v[0] for k, v in run(spark, "op_join_range_panels", tmp_path).items()}
    cells = [p + d for p in (5, 74_000, 74_001, 90_123) for d in (0, 1, -1, 50, -50) if 0 <= p + d <= 90_123 and (abs(d) != 1 or p // 50 == (p + d) // 50)]
    assert got == Counter(j // 37 for j in cells)


def test_betweenness_is_of_the_whole_graph(spark):
    near, want = {}, Counter()
    for i, j in datasets.next_part_sym(spark, LITTLE).df.select("i", "j").collect():
        near.setdefault(i, []).append(j)
    for source in (0, 3):
        far, paths, order = {source: 0}, Counter({source: 1}), [source]
        for x in order:
            for y in near.get(x, []):
                if y not in far:
                    far[y] = far[x] + 1
                    order.append(y)
                if far[y] == far[x] + 1:
                    paths[y] += paths[x]
        through = Counter()
        for x in reversed(order):
            for y in near.get(x, []):
                if far[y] == far[x] + 1:
                    through[x] += paths[x] / paths[y] * (1 + through[y])
            if x != source:
                want[x] += through[x]
    got = {r["i"]: r["v"] for r in queries()["betweenness"](spark, LITTLE).collect()}
    assert len(want) > 100 and all(abs(got.get(i, 0) - v) < 1e-6 for i, v in want.items()) and set(got) <= set(want)


def test_vector_search_has_all_pairs_of_its_queries(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(datasets, "_QUERIES", 2)  # several passes
    r = random.Random(5)
    vectors = {i: [r.uniform(-1, 1) for _ in range(8)] for i in range(450)} | {7: None, 300: [0.9] * 8, 301: [0.9] * 8}
    spark.createDataFrame(list(vectors.items()), "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    held = {k: [round(x * 1000) for x in v or []] for k, v in spark.read.parquet(f"{tmp_path}/embeddings.parquet").collect()}
    product = {(i, j): sum(x * y for x, y in zip(held[i], held[j], strict=False)) for i in range(0, 450, 100) for j in held if i != j}
    want = rows_of({c: v for c, v in product.items() if v > 300_000})
    assert want and run(spark, "matrix_vec_sim", tmp_path) == want


@pytest.mark.parametrize("name", ["comm_model", "kway_merge_16", "kway_merge_cell_16x16", "kway_merge_cell_4x4", "memory_factor_2d", "memory_factor_c16", "memory_factor_c4", "mm_grid3d_hubs", "mm_grid3d_pair_community", "mm_grid3d_pair_skewed", "mm_grid3d_pair_uniform", "mm_grid3d_rmat_community"])
def test_measures_and_merges_follow_given_tables(spark, tmp_path, name):
    """Half of the parts, lines and events give another result, equal to the SQL's."""
    con = duckdb.connect()
    for t, rule in (("part", "p_partkey < 100"), ("lineitem", "l_partkey < 100"), ("events", "user_id % 2 = 0")):
        spark.read.parquet(f"{LITTLE}/{t}.parquet").where(rule).write.parquet(f"{tmp_path}/{t}.parquet")
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    query = queries()[name]
    got = query(spark, str(tmp_path))
    want = con.execute(oracle_sql()[name])
    names, rows = [c[0] for c in want.description], sorted(want.fetchall())
    assert rows and sorted(tuple(r) for r in got.select(*names).collect()) == rows
    assert sorted(tuple(r) for r in query(spark, LITTLE).select(*names).collect()) != rows
