"""Cuts of long histories."""

import pytest
from pyspark.sql import functions as F

from incwalk.operators import snapshot_queries as S
from incwalk.operators.snapshot_queries import before_cut


def test_cuts_hold_beyond_32_bits(spark):
    m = 40_000_000  # 80 * m is no 32-bit integer
    x = spark.createDataFrame([(1, 80), (32_000_000, 80), (32_000_001, 80), (20_000_000, 50), (20_000_001, 50)], "t long, cut int")
    assert [r["old"] for r in x.select("t", before_cut("cut", m).alias("old")).collect()] == [True, True, False, True, False]


def test_arrivals_on_arrays_are_those_of_the_joins(spark, monkeypatch):
    rows = [(0, 1, 1), (1, 0, 2), (1, 2, 3), (2, 0, 4), (0, 2, 5), (2, 7, 6), (8, 0, 7), (0, 7, 8), (9, 1, 9), (0, 9, 10)]
    e = spark.createDataFrame(rows, "src long, dst long, ord long")
    monkeypatch.setattr(S, "edges", lambda *a: e)
    of = (("x", False, (40, 80)), ("x", True, (50,)))
    one, other = ({r["g"]: (r["m"], r["arrivals"], pytest.approx(r["mx"])) for r in x.collect()} for x in (S._arrivals_on_arrays(e, of), S._arrivals_joined(S.snapshots(spark, "", of))))
    assert one == {g: (m, n, mx.expected) for g, (m, n, mx) in other.items()} and set(one) == {"x 40", "x 80", "x permuted 50"}
