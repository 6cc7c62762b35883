import pytest

from congraph.measures import summary


def test_summary_of_three_patterns():
    got = summary([10.0, 4.0, 1.0], [1.0, 2.0, 4.0])
    assert (got["wins_join"], got["wins_topdown"]) == (2, 1)
    assert got["total"] == pytest.approx(15 / 7) and got["median"] == 2
    assert got["best"] == 10 and got["worst"] == 0.25
    assert got["hmean"] == pytest.approx(3 / (0.1 + 0.5 + 4)) and got["gmean"] == pytest.approx(5 ** (1 / 3))
