"""The complete miner stores and shuffles patterns, not embeddings."""

import pytest

from patternwalk import workloads
from patternwalk.model import pack
from patternwalk.operators import complete as B
from patternwalk.sources import builders

SF = "/root/testdata/sf0.001"
QUERIES = ["complete_growth", "complete_closed", "complete_maximal", "pattern_lattice_walk", "w1_complete_by_size", "w2_complete_by_support", "complete_levelwise"]


@pytest.mark.parametrize("name", QUERIES)
def test_only_patterns_are_stored(spark, monkeypatch, name):
    stored, cut = [], B.cut
    monkeypatch.setattr(B, "cut", lambda df, what, **k: (stored.append((what, df.columns)), cut(df, what, **k))[1])
    workloads.QUERIES[name](spark, SF).count()
    assert stored and not any("es" in columns or "raw" in columns for _, columns in stored)


def test_distinct_label_graphs_are_made_without_a_shuffle(spark, monkeypatch):
    packed = builders.token_adj_packed(spark, SF)
    plan = packed._jdf.queryExecution().optimizedPlan().toString()
    assert not any(x in plan for x in ("Join", "Aggregate", "Window", "Sort"))
    longer = pack(builders.token_adj(spark, SF))
    columns = ["gid", "vids", "vlab", "ea", "eb", "elab"]
    assert sorted(map(str, packed.select(*columns).collect())) == sorted(map(str, longer.select(*columns).collect()))
    stored, cut = [], B.cut
    monkeypatch.setattr(B, "cut", lambda df, what, **k: (stored.append(what), cut(df, what, **k))[1])
    found = {(r.code, r.support) for r in B.mine_distinct_labels(packed, 20).collect()}
    assert "grown" not in stored and found == {(r.code, r.support) for r in B.mine_distinct_labels(builders.token_adj(spark, SF), 20).collect()}
