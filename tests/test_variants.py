"""Parts of the new options that need no session."""

from __future__ import annotations

import pytest

from tileaqp.plans.engine import neyman_rates
from tileaqp.plans.estimators import Moments, Stratum
from tileaqp.plans.geometry import CELL_BITS, Tile
from tileaqp.plans.model import IndexConfig


def stratum(tile: int, pop: int, n: int, variance: float) -> Stratum:
    return Stratum(tile, "full", pop, 2, {"v": 0}, {"v": Moments(n, 1.0, variance * (n - 1))})


def test_shares_follow_population_times_spread():
    got = neyman_rates([stratum(1, 1000, 10, 1.0), stratum(2, 1000, 10, 9.0)], ("v",), 0.1)
    assert got[1] == pytest.approx(0.05) and got[2] == pytest.approx(0.15)


def test_what_a_full_stratum_leaves_goes_to_the_others():
    got = neyman_rates([stratum(1, 100, 10, 10000.0), stratum(2, 900, 10, 1.0)], ("v",), 0.2)
    assert got[1] == 1.0 and got[2] == pytest.approx(100 / 900)


def test_without_a_variance_the_common_rate_stays():
    assert neyman_rates([stratum(1, 100, 1, 0.0), stratum(2, 900, 10, 1.0)], ("v",), 0.2) == {}


@pytest.mark.parametrize("n", [4, 16, 64])
def test_parts_cover_the_tile(n):
    t = Tile(0, None, 0, 3, 0, 1 << CELL_BITS, 10)
    parts = t.parts(n)
    assert len(parts) == n and parts[0][0] == t.zlo and parts[-1][1] == t.zhi and all(a[1] == b[0] for a, b in zip(parts, parts[1:], strict=False))
    assert n == 4 ** IndexConfig(fan_out=n).split_levels


def test_other_fan_outs_are_refused():
    with pytest.raises(ValueError):
        IndexConfig(fan_out=9)
