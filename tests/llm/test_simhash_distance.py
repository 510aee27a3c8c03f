import pytest

from ptree_rules.llm.simhash import near_groups, one_of_each_group


@pytest.mark.parametrize("operator", [near_groups, one_of_each_group])
def test_a_distance_beyond_the_keys_is_refused(none, operator):
    with pytest.raises(ValueError, match="3 differing bits, not 4"):
        operator(none, distance=4)
