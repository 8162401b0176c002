"""Bags of whiskers against brute force."""

import itertools

import pytest

from levcut.operators import probes
from levcut.runtime import TooLarge


def _brute(kinds):
    best = {}
    for take in itertools.product(*(range(n + 1) for _, _, n in kinds)):
        s, j, v = (sum(t * x for t, x in zip(take, column, strict=True)) for column in ([k[0] for k in kinds], [1] * len(kinds), [k[1] for k in kinds]))
        if s:
            best[s] = min(best.get(s, 9.0), j / v)
    return best


@pytest.mark.parametrize("kinds", [[(20, 300.0, 3), (30, 300.0, 2), (60, 305.0, 1), (1, 1.0, 1)], [(2, 3.0, 5), (3, 11.0, 4), (5, 9.0, 3), (7, 40.0, 2), (1, 1.0, 6)]])
def test_bag_is_exact(spark, kinds):
    rows = [(s, v) for s, v, n in kinds for _ in range(n)]
    got = {r["size"]: r["phi"] for r in probes.bag(spark.createDataFrame(rows, "size long, vol double")).collect()}
    assert got == pytest.approx(_brute(kinds))


def test_bag_of_large_whiskers_is_whole_or_refused(spark):
    summary = spark.createDataFrame([(5000, 9999.0), (3, 5.0)], "size long, vol double")
    assert {r["size"] for r in probes.bag(summary).collect()} == {3, 5000, 5003}
    with pytest.raises(TooLarge):
        probes.bag(summary, most_total=5000)


def test_bag_of_many_nodes(spark):
    """Three large whiskers and a few small ones: every total size, by trying all unions."""
    from itertools import product

    rows = [(150_000, 299_999.0)] * 3 + [(2, 3.0)] * 3 + [(3, 7.0)] * 2
    got = {r["size"]: (r["phi"], r["whiskers"], r["vol"]) for r in probes.bag(spark.createDataFrame(rows, "size long, vol double")).collect()}
    want = {}
    for a, b, c in product(range(4), range(4), range(3)):
        if j := a + b + c:
            size, vol = 150_000 * a + 2 * b + 3 * c, 299_999 * a + 3 * b + 7 * c
            want[size] = min(want.get(size, (9.0, 0, 0)), (j / vol, j, vol))
    assert got == want
