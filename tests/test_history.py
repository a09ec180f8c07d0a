"""Walks that a task takes through all batches give the ledger of the store that goes from batch to batch."""

import numpy as np
import pytest

from incwalk.plans import history, update
from incwalk.plans.walks import Spec


@pytest.mark.parametrize("kind", ["pagerank", "alternating"])
def test_ledger_is_that_of_the_store(spark, kind, monkeypatch):
    rng = np.random.default_rng(7)
    pairs = sorted({(int(a), int(b)) for a, b in zip(rng.integers(0, 25, 110), rng.integers(5, 35, 110), strict=True) if a != b})  # 25 on have no edge out, 0 to 4 none in
    e = spark.createDataFrame([(a, b, int(o)) for (a, b), o in zip(pairs, rng.integers(0, 30, len(pairs)), strict=True)], "src long, dst long, ord long")
    spec, cuts = Spec(reps=2, seed=5, kind=kind), [20, len(pairs) // 2, len(pairs) - 3]
    with monkeypatch.context() as m:
        m.setattr(history, "NODES", 7)
        m.setattr(update.WalkStore, "create", None)  # no table is written a batch
        got = update.replay(e, spec, cuts)
    with monkeypatch.context() as m:
        m.setattr(update, "on_broadcast", lambda *a: False)
        asked = update.replay(e, spec, cuts)
    assert got.schema.simpleString() == asked.schema.simpleString()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, asked.collect()))


def test_no_arrivals(spark):
    none = spark.createDataFrame([], "src long, dst long, ord long")
    assert update.replay(none, Spec(), update.whole_history(0)).count() == 0
