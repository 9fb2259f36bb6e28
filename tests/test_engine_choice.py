"""The engine is the caller's choice, at any size, and the measures name it."""

import pytest

from streamcut.plans import api
from streamcut.registry import QUERIES

DIR = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def edges(spark):
    return spark.createDataFrame([(u, v) for u in range(40) for v in range(u % 7 + 1)], "src long, dst long")


def test_size_does_not_choose_the_engine(edges, monkeypatch):
    monkeypatch.setattr(api, "EXACT_EDGES", 0, raising=False)
    rows = [sorted((r.src, r.dst, r.part) for r in api.partition(edges, "greedy_indegree", 4, **o).placed.collect()) for o in ({}, {"engine": "exact"})]
    assert rows[0] == rows[1]
    with pytest.raises(ValueError):
        api.partition(edges, "greedy_indegree", 4, engine="auto")


def test_measures_name_the_engine(edges):
    for method, opts, want in (
        ("greedy_indegree", {}, ("exact", 0)), ("greedy_indegree", {"engine": "sharded", "shards": 3}, ("sharded", 3)),
        ("greedy_indegree", {"engine": "snapshot", "batch": 50}, ("snapshot", 0)), ("edge_hash", {}, ("stateless", 0)),
    ):
        row = api.partition(edges, method, 4, **opts).metrics().first()
        assert (row.engine, row.shards) == want


def test_approximate_queries_give_their_gap(spark):
    row = QUERIES["greedy_sharded_word_next_conv"](spark, DIR).first()
    assert row.engine == "sharded" and row.shards == 4 and row.engine_gap > -1
