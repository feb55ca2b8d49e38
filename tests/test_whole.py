"""Queries of the item-at-a-time summary over whole tables, against a plain pass."""

import pytest

import __spark_entry__ as entry
from conftest import DATA


def plain_pass(items, k):
    """{item: (est, err)}; the smallest (est, item) is taken over."""
    held = {}
    for i in items:
        if i in held:
            held[i] = (held[i][0] + 1, held[i][1])
        elif len(held) < k:
            held[i] = (1, 0)
        else:
            low = min(held, key=lambda x: (held[x][0], x))
            held[i] = (held[low][0] + 1, held.pop(low)[0])
    return held


@pytest.fixture(scope="module")
def items(duck):
    return [r[0] for r in duck.sql("SELECT floor(value)::BIGINT FROM events WHERE value IS NOT NULL ORDER BY event_id").fetchall()]


def test_whole_pass(spark, items):
    q = entry.queries()
    want = plain_pass(items, 10)
    got = q["ss_sequential_events_k10_whole"](spark, DATA).collect()
    assert {r.item: (r.est, r.err) for r in got} == want
    assert sum(r.est for r in got) == len(items) > 300
    assert {r.item: r.est for r in q["ss_sequential_noerr_whole"](spark, DATA).collect()} == {i: e for i, (e, _) in want.items()}


def test_whole_blocks(spark, items):
    got = {r.block_id: tuple(r)[1:] for r in entry.queries()["ss_local_sequential_whole"](spark, DATA).collect()}
    n = len(items)
    want = {}
    for b in range(8):
        part = items[b * n // 8 : (b + 1) * n // 8]
        est = [e for e, _ in plain_pass(part, 12).values()]
        want[b] = (len(part), 12, len(est), min(est) if len(est) == 12 else 0, sum(est))
    assert got == want and sum(r[0] for r in got.values()) == n
