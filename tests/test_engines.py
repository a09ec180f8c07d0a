"""Which engine a graph of a size takes."""

from incwalk.plans.walks import Spec, _is_local


def test_graphs_of_four_million_edges_are_broadcast():
    assert _is_local(None, Spec(), 3_600_000)
    assert not _is_local(None, Spec(), 4_000_001)
    assert not _is_local(None, Spec(engine="rounds"), 10)
