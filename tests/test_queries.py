"""Queries against DuckDB on the smallest tables. The whole registry runs in the driver at a larger size."""

import pytest

from gnnspark.queries import registry

QUICK = "udf_forward graph_cust_part graph_user_hops graph_page_links graph_geo_tree prop_sym prop_sym_directed split_shares label_planted batches ns_two_hop ns_replace gcn_block fastgcn_draw_iid block_fastgcn_d block_ladies_fd debias_coef cache_probs_walk2 cache_nodes gather_missing sched_bounded_q2 sched_pipelined queue_size grad_one_step update_schedule divergence_curve sync_period_published roc_auc f1_micro_macro utilisation early_stop_point wl_period_cost asof_model_version interval_overlap set_ops stream_session stream_grad_queue stream_late".split()


@pytest.mark.parametrize("name", QUICK)
def test_query(spark, sf, duck, same, name):
    same(registry.queries()[name](spark, sf), duck.sql(registry.oracles()[name]))


def test_registry_is_complete():
    q, o = registry.queries(), registry.oracles()
    assert set(o) <= set(q) and len(q) > 150


def test_entry_survives_without_llm():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    code = "import sys; sys.modules['gnnspark.llm'] = None; import __spark_entry__ as e; assert not any(k.startswith('op1_') for k in e.queries()); print(len(e.queries()))"
    done = subprocess.run([sys.executable, "-c", code], cwd=root, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
