"""The rows that op4's routing trees make: with the fingerprints, not with a power of them."""

import numpy as np
import pytest

pytest.importorskip("cutloom.llm")
from cutloom.llm import simhash  # noqa: E402


def test_no_pair_is_left_to_no_part():
    """Any way to spread up to ``radius`` bits over the parts lies within the reach of one."""
    for radius in range(9):
        parts = simhash.searched(radius)
        reach = {p: simhash.reach(0, radius, p) for p in parts}
        least = sum(reach.get(p, -1) + 1 for p in range(simhash.PARTS))  # bits of the closest pair beyond every reach
        assert least == radius + 1


def test_placed_rows_grow_with_the_fingerprints():
    """However many shards there are: one row in each of three trees and one for each value within a bit in the first."""
    fps = np.unique(np.random.default_rng(9).integers(0, 1 << 63, 64_000, dtype=np.uint64) * np.uint64(2) + np.uint64(1))
    for n, members in ((4_000, 500), (60_000, 500), (60_000, 100)):
        some, parts = fps[np.random.default_rng(1).permutation(len(fps))[:n]], simhash.searched(4)
        sent = [rows for p in parts for rows in simhash.route(some, p, simhash.grown(some, p, members)[0], 4)]
        assert sum(int(home.sum()) for _, _, home in sent) == len(parts) * n
        assert sum(len(rows) for _, rows, _ in sent) <= (len(parts) - 1 + simhash.PART_BITS + 1) * n


def test_pairs_across_quarters():
    """Pairs that differ in one to four bits, in every spread over the quarters that random choice finds."""
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    near = base.copy()
    for i in range(len(near)):
        for bit in rng.choice(64, 1 + i % 4, replace=False):
            near[i] ^= np.uint64(1) << np.uint64(bit)
    fps = np.concatenate([base, near])
    full = simhash.Forest(len(fps))
    full.link(*np.nonzero(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 4))
    found = simhash.Forest(len(fps))
    for part in simhash.searched(4):
        for _, some, home in simhash.route(fps, part, simhash.grown(fps, part, 20)[0], 4):
            simhash.tree_links(fps, part, some[home], some, 4, found, leaf=4)
    assert (found.roots() == full.roots()).all()
