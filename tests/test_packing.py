import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from spangrid.operators.maintain import merge_plan, split_sizes
from spangrid.operators.measures import most_groups
from spangrid.operators.packing import groups_of_runs

KEYS = [1, 2, 4, 4, 7, 8, 10, *[13] * 11, 14, 15, 16, 17, 19, 21, 23]


def sizes(keys, budget):
    values, counts = np.unique(np.array(keys), return_counts=True)
    g = groups_of_runs(counts, budget)
    return [int(counts[g == i].sum()) for i in range(int(g.max()) + 1)] if len(g) else []


def test_the_worked_packing():
    assert sizes(KEYS, 9) == [7, 11, 7]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 30), max_size=120), st.integers(1, 40))
def test_what_a_packing_is(keys, budget):
    """Keys stay whole; a group is within the budget or one key; its next key would have gone beyond it."""
    got = sizes(keys, budget)
    order, at = sorted(keys), 0
    assert sum(got) == len(keys)
    for n in got:
        group, rest = order[at : at + n], order[at + n :]
        assert not rest or rest[0] != group[-1]
        assert n <= budget or len(set(group)) == 1
        assert not rest or n + rest.count(rest[0]) > budget
        at += n
    assert all(a + b > budget for a, b in zip(got, got[1:]))
    assert len(got) <= most_groups(len(keys), budget)


def test_no_budget():
    with pytest.raises(ValueError):
        groups_of_runs(np.array([1]), 0)


def test_splits():
    assert split_sizes(np.array([1, 2, 1, 1]), 4).tolist() == [0, 0, 1, 1]  # 2, 3, 3 | 4, 5
    assert split_sizes(np.array([1, 3, 1]), 4).tolist() == [0, 1, 2]  # a run that would overflow stands for itself


def test_merges():
    assert merge_plan([1, 2, 3], {0}, 4) == [[0, 1], [2]]
    assert merge_plan([1, 3], {0}, 4) == [[0], [1]]
    assert merge_plan([3, 4], {0}, 8, 8) == [[0, 1]]
    assert merge_plan([4, 4], {0}, 8, 8) == [[0], [1]]
