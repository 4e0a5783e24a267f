"""Deletes of the dynamic filter: what is left is never missed, however many blocks have split and merged."""

import random

import pytest

from rangesieve.operators.dynamic import ShardFilter


@pytest.mark.parametrize("widening", ["none", "per_doubling"])
@pytest.mark.parametrize("skewed", [True, False])
def test_merges_keep_shared_entries(skewed, widening):
    t, r, width = 16, 4, 32
    for seed in range(4):
        rng = random.Random(seed)
        draw = lambda: (int(rng.random() ** 3 * 4000) << 16) + rng.randrange(1, 1 << 10) if skewed else rng.randrange(1, (1 << width) - 1)  # noqa: B023, E731
        living = {draw() for _ in range(40)}
        f = ShardFilter.build(sorted(living), 0, (1 << width) - 1, t, r, width, widening=widening)
        for _ in range(8):
            late = {draw() for _ in range(190)} - living
            for x in sorted(late):
                f.insert(x)
            living |= late
            gone = rng.sample(sorted(living), len(living) // 6)
            for x in sorted(gone):
                f.delete(x)
            living -= set(gone)
            f = ShardFilter.from_rows(f.rows(0, 0), t, r, width, widening=widening)
            assert [x for x in living if not f.positive(x, x)] == []
