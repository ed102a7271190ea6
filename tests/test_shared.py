"""Counts of shared attributes: joins and block products against plain sums."""

from collections import Counter, defaultdict

import pytest

from mutualgraph.operators import shared

ROWS = [(p, u, f"x{a}", 1 + (u * a) % 3) for p in (5, 7) for u in range(60) for a in range(40) if (u * 31 + a * 17 + p) % (2 + a) == 0]


@pytest.mark.parametrize("share", [1, 8, 1000])
@pytest.mark.parametrize("half", [False, True])
def test_shared_counts(spark, monkeypatch, share, half):
    for name, value in (("HEAVY_SHARE", share), ("BLOCK", 16), ("PIECE", 5), ("ROWS", 300)):
        monkeypatch.setattr(shared, name, value)
    rows = [*ROWS, (5, None, "x1", 4), (5, 3, None, 4)]
    held = shared.held(spark.createDataFrame(rows, "path int, user_id long, attr string, cnt long"))
    by = defaultdict(list)
    for p, u, a, c in ROWS:
        by[p, a].append((u, c))
    for own in (False, True):
        want = Counter()
        for (p, _), users in by.items():
            for u, c in users:
                for v, d in users:
                    if (own or u != v) and (not half or u <= v):
                        want[u, v, p] += c * d
        got = Counter()
        for r in shared.shared_counts(held, half, own).collect():
            got[r["src"], r["dst"], r["path"]] += r["cnt"]
        assert got == want
        out = Counter()
        for (u, v, p), n in want.items():
            out[u, p] += n
            if half and u != v:
                out[v, p] += n
        assert {(r["user_id"], r["path"]): r["out"] for r in shared.shared_marginals(held, own).collect() if r["out"]} == dict(out)


def test_no_rows(spark):
    held = shared.held(spark.createDataFrame([], "path int, user_id long, attr string, cnt long"))
    assert shared.shared_counts(held).count() == 0 and shared.shared_marginals(held).count() == 0
