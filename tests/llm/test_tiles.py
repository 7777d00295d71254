"""Tiles of a family against all pairs of its sets."""

import numpy as np

from cellbalance.llm import ngram_join


def test_tile_links_join_what_is_similar():
    rng = np.random.default_rng(7)
    base = np.unique(rng.integers(1, 1 << 60, 60, dtype=np.uint64))
    sets = [np.unique(np.concatenate([base[rng.random(len(base)) < 0.93], rng.integers(1, 1 << 60, 4, dtype=np.uint64)])) for _ in range(40)]
    rank = ngram_join.Order([(int(h), 3) for h in base.view(np.int64)[:20]]).rank_of
    for chunks in (1, 2):
        members = [(i, i, i % chunks, s) for i, s in enumerate(sets)]
        similar = [(a, b) for a in range(40) for b in range(a) if a % chunks != b % chunks or chunks == 1 if 5 * len(np.intersect1d(sets[a], sets[b])) >= 4 * len(np.union1d(sets[a], sets[b]))]
        assert similar and len(similar) < 40 * 39 / 2

        def groups(links):
            label = list(range(40))
            for a, b in links:
                old, new = label[a], label[b]
                label = [new if x == old else x for x in label]
            return {frozenset(i for i in range(40) if label[i] == x) for x in label}

        found = ngram_join.tile_links(members, rank)
        assert groups(found) == groups(similar) and len(found) == 40 - len(groups(similar))
