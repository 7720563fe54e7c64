import pytest

from cdfblend.plans.planner import Tier, choose

TIERS = [Tier("user_hour", ("user_id", "hour"), 100, lambda: None), Tier("hour", ("hour",), 10, lambda: None), Tier("user", ("user_id",), 20, lambda: None), Tier("day", ("day",), 3, lambda: None)]


@pytest.mark.parametrize("keys,filters,name", [(["day"], [], "day"), (["hour"], [], "hour"), (["month"], ["hour"], "hour"), (["user_id"], [], "user"), (["user_id"], ["day"], "user_hour"), ([], [], "day")])
def test_choice(keys, filters, name):
    assert choose(TIERS, keys, filters).name == name


def test_nothing_covers():
    with pytest.raises(ValueError):
        choose(TIERS, ["region"])
