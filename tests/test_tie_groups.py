"""Ties that expire in groups are those that expire one by one."""

import random

import numpy as np

from graphdrift.streaming import front


def one_by_one(state, batch, idle, watermark):
    """The rule in plain Python, a tie at a time."""
    told, new = [], {}
    for a, b, t in batch:
        new.setdefault((a, b), []).append(t)
    for tie, times in new.items():
        last = state.get(tie)
        for t in sorted(times):
            if last is None or t - last > idle:
                if last is not None:
                    told.append(("del_edge", *tie, last + idle))
                told.append(("add_edge", *tie, t))
            last = t if last is None else max(last, t)
        state[tie] = last
    for tie, last in list(state.items()):
        if tie not in new and (last + idle) // 1000 + 1 <= watermark:
            told.append(("del_edge", *tie, last + idle))
            del state[tie]
    return told


def test_groups_are_ties_one_by_one():
    random.seed(8)
    held, state, now, idle = np.zeros((0, 3), np.int64), {}, 0, 5000
    for _ in range(300):
        batch = [(random.randrange(3), 3 + random.randrange(3), max(0, now + random.randrange(-6000, 6000))) for _ in range(random.randrange(5))]
        watermark = max(0, now // 1000 - 2)
        want = one_by_one(state, batch, idle, watermark)
        held, told, gone = front.expire_and_take(held, np.array(batch, np.int64).reshape(-1, 3), idle, watermark)
        got = [("add_edge", *r) for r in told.tolist()] + [("del_edge", *r) for r in gone.tolist()]
        assert sorted(got) == sorted(want) and {(a, b): t for a, b, t in held.tolist()} == state
        now += random.randrange(4000)


def test_a_tie_is_no_call_of_its_own():
    calls = np.array([(a, 10_000 + a, 7) for a in range(5000)], np.int64)
    held, told, gone = front.expire_and_take(np.zeros((0, 3), np.int64), calls, 10, 0)
    assert len(held) == len(told) == 5000 and not len(gone)
