"""Queries against DuckDB on the small tables. Method queries run at the size their SQL is unrolled for."""

import pytest
from conftest import MEDIUM
from oracle import connect, same

from rareblock.workloads import building, comparing, method, relational

CHOSEN = [
    (building, ("identity_part", "index_orders", "token_two_attr", "tok_qgrams", "minhash_docs", "lsh_docs_6_7", "lsh_curve")),
    (method, ("rib_part", "rib_part_propagate", "rib_part_sketch", "rib_part_bucket", "rib_part_published", "rib_orders", "rib_pivot_customer", "rib_token_docs", "twins_docs", "pack_part", "bitmap_bits", "link_docs_benchmark", "twins_stall_lineitem", "rib_rounds_report")),
    (comparing, ("meta_ejs_part", "meta_rcnp_part", "meta_wnp_part", "meta_cep_part", "meta_wep_part", "meta_broadcast_part", "compare_methods_part", "compare_at_point_part", "sensitivity_part", "scaling_ladder_part", "ablate_token_vs_lsh", "cluster_docs", "scaling_fit", "cost_model")),
    (relational, ("join_range", "join_asof", "st_session", "win_range", "set_except", "fn_html")),
]


@pytest.fixture(scope="module")
def con():
    return connect(MEDIUM)


@pytest.mark.parametrize("module,name", [(m, n) for m, names in CHOSEN for n in names], ids=lambda x: x if isinstance(x, str) else "")
def test_equals_sql(spark, con, module, name):
    same(module.QUERIES[name](spark, MEDIUM), con, module.ORACLE_SQL[name])


def test_sketch_split_keeps_fit_keys(spark):
    by = {r["class"]: r for r in method.QUERIES["rough_split_docs"](spark, MEDIUM).collect()}
    assert by["fit"]["over"] == 0
    lost = {r["mode"]: r["lost"] for r in method.QUERIES["shrink_exact_vs_est"](spark, MEDIUM).collect()}
    assert lost["exact"] == 0 <= lost["estimate"]
