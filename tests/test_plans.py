"""Worked examples of the schedule and the layout, without Spark."""

from hypothesis import given
from hypothesis import strategies as st

from kdforest.operators.tree import choose_splits, collapse
from kdforest.plans import schedule, veb


def test_level_splits():
    assert [veb.split_levels(n) for n in range(2, 11)] == [(1, 1), (1, 2), (2, 2), (1, 4), (2, 4), (3, 4), (4, 4), (1, 8), (2, 8)]


def test_layout_of_eight_points():
    p = veb.positions(4)
    assert sorted(p) == list(range(15)) and p[:3] == (0, 1, 2)
    assert [p[i - 1] for i in range(4, 8)] == [3, 6, 9, 12]


def test_layout_is_a_bijection():
    for levels in range(1, 11):
        assert sorted(veb.positions(levels)) == list(range((1 << levels) - 1))


def test_levels_for():
    assert [veb.levels_for(n) for n in (1, 2, 5, 8)] == [1, 2, 3, 4]
    assert veb.levels_for(16, 16) == 1 and veb.levels_for(17, 16) == 2


def test_states_of_four_inserts():
    for x in (3, 4, 1024):
        mask = buffered = 0
        seen = []
        for b in (x, x + 1, x + 1, x - 1):
            p = schedule.plan_insert(mask, buffered, x, b)
            mask, buffered = p.mask, p.buffer
            seen.append((mask, buffered))
        assert seen == [(1, 0), (2, 1), (3, 2), (4, 1)]


def test_cascade_and_merge():
    assert schedule.plan_insert(7, 3, 4, 1).mask == 8
    p = schedule.plan_insert(0b0101, 0, 4, 24)
    assert (p.mask, p.vanish, p.appear) == (0b1011, (2,), (1, 3)) and schedule.shares(40, [8, 32]) == [0, 8, 40]


@given(st.lists(st.integers(0, 5000), max_size=30), st.integers(1, 300))
def test_insert_only_closed_form(batches, x):
    mask = buffered = 0
    for b in batches:
        p = schedule.plan_insert(mask, buffered, x, b)
        mask, buffered = p.mask, p.buffer
    assert (mask, buffered) == divmod(sum(batches), x)


def test_collapse():
    assert collapse({4: 0, 5: 0, 6: 2, 7: 1}, {1, 2, 3}) == {3: (6, 7)}
    assert collapse({2: 0, 3: 0}, {1}) is None and collapse({2: 1, 3: 0}, {1}) == 2


def test_splits_of_equal_points():
    cell = {"tree": 0, "node": 1, "n": 100, "lo0": 1.0, "hi0": 1.0, "lo1": 2.0, "hi1": 2.0}
    assert choose_splits([cell], 2, "spatial", 16) == []
    assert choose_splits([cell | {"hi1": 4.0}], 2, "spatial", 16) == [(0, 1, 1, 3.0)]
