import os

import pytest

import __spark_entry__ as entry

from .compare import compare, connect

SF = "/root/testdata/sf0.001"
ORACLES = entry.contract.ORACLES
#: One of each family; LINKWHY_ALL=1 runs every query (the driver's correctness run does too).
SOME = {"kb_edges_activity", "kb_edges_content", "kb_summary", "path_patterns_activation", "explanations_n3_lineage", "match_selected", "measure_walk_n3", "local_position", "topk_monocount_frontier", "topk_size_local", "dcg_scores", "op_session_pairs", "stream_edges", "stream_co_occurrence"}
NAMES = sorted(ORACLES if os.environ.get("LINKWHY_ALL") else SOME)


@pytest.fixture(scope="module")
def con():
    return connect(SF)


@pytest.mark.parametrize("name", NAMES)
def test_query_agrees_with_sql(spark, con, name):
    what, ours, theirs = compare(entry.contract.QUERIES[name](spark, SF), con, ORACLES[name])
    assert not what, (what, ours, theirs)


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert 0 < len(rows) <= 10 and [r["rank"] for r in rows] == sorted(r["rank"] for r in rows)


def test_names():
    assert set(entry.oracle_sql()) <= set(entry.queries())
