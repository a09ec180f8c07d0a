"""Digests that are taken together are those of hashlib."""

import numpy as np
import pytest

from incwalk.functions import coins


@pytest.mark.parametrize("many", [1, 1023, 1024, 20_000])
@pytest.mark.parametrize("width", [1, 10**17, 10**40])  # the last makes messages of more than a block
def test_coins_together(many, width):
    rng = np.random.default_rng(many)
    walks = [f"{int(x) * width}:{int(y)}" for x, y in zip(rng.integers(0, 9, many), rng.integers(0, 10**6, many), strict=True)]
    pos = rng.integers(0, 3000, many)
    a, b = coins.python_coins(7, "wave-again", walks, 12, pos)
    assert list(zip(a.tolist(), b.tolist(), strict=True)) == [coins.python_coin(7, "wave-again", w, 12, p) for w, p in zip(walks, pos.tolist(), strict=True)]


def test_large_batches_go_together(monkeypatch):
    monkeypatch.setattr(coins.hashlib, "md5", None)
    assert len(coins.python_coins(1, "build", [f"{i}:0" for i in range(2000)], 0, np.zeros(2000, int))[0]) == 2000
