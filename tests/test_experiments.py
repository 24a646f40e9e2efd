"""The experiment runners, on small inputs: rows are complete and counts show the reported behaviour."""

from layermul import experiments as ex
from layermul.plans.grid import Grid
from layermul.sources.datasets import mesh_part
from layermul.sources.generators import rmat

SF = "/root/testdata/sf0.001"


def test_layers_trade_words(spark):
    m = rmat(spark, "skewed", 8)
    rows = list(ex.run_square(m, [Grid(4, 4, 1), Grid(2, 2, 4), Grid(1, 1, 16)], "skewed8"))
    words = {(r["pl"], r["phase"]): r["value"] for r in rows if r["metric"] == "words"}
    assert words[1, "a_broadcast"] > words[4, "a_broadcast"] > words[16, "a_broadcast"] == 0
    assert 0 == words[1, "c_exchange"] < words[4, "c_exchange"] < words[16, "c_exchange"]
    held = {r["pl"]: r["value"] for r in rows if r["metric"] == "memory_factor"}
    assert 1 == held[1] < held[4] < held[16]


def test_permutation_balances_the_mesh(spark):
    out = {r["plan"]: r["value"] for r in ex.run_permutation_ablation(mesh_part(spark, SF), "mesh")}
    assert out["permuted"] < out["given"]


def test_other_runners(spark):
    m = mesh_part(spark, SF)
    for rows in (ex.run_galerkin(m, "mesh"), ex.run_library_comparison(m, "mesh"), ex.run_restriction(m, "mesh"), ex.run_pair(spark, "uniform", 6, [Grid(2, 2, 2)])):
        rows = list(rows)
        assert rows and all(r["value"] >= 0 for r in rows)
