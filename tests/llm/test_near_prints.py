"""The near-copy stage proposes pairs by its fingerprints, and by nothing else."""

import itertools

import numpy as np
import pyarrow as pa
import pytest

from regionfilter.llm import near
from regionfilter.llm.simhash import fingerprint_of


def _sets(rng, pairs, n, shared):
    """Pairs of sets of n hashes, of which they share some; each set is unlike all other pairs' sets."""
    out = []
    for _ in range(pairs):
        both = rng.integers(0, 1 << 63, shared, dtype=np.uint64)
        out += [np.unique(np.concatenate([both, rng.integers(0, 1 << 63, n - shared, dtype=np.uint64)])) for _ in range(2)]
    return out


def _searched(sets, crowded=near.CROWDED, n=None):
    """What the search proposes for sets, numbered from 0: pairs with whether a hub is in them, and crowded buckets."""
    prints = np.array([near.wide_fingerprint(s) for s in sets], dtype=np.uint64).view(np.int64)
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(sets)), pa.int64()), pa.array([len(s) for s in sets], pa.int32()), *(pa.array(prints[:, i].copy()) for i in range(near.WORDS))], ["node", "n", *near._FP])
    moved = pa.Table.from_batches(near._moved(iter([batch]))).to_pylist()
    pairs, buckets, run = {}, {}, near._searched(n or len(sets), 0.8, crowded)
    schema = pa.schema([("block", pa.int32()), ("value", pa.int32()), ("prints", pa.binary())])
    for _, rows in itertools.groupby(moved, lambda r: (r["block"], r["value"])):
        for a, b, first, bucket in zip(*run(pa.Table.from_pylist(list(rows), schema)).to_pydict().values()):
            if bucket is None:
                assert a < b
                pairs[a, b] = pairs.get((a, b), False) or first
            else:
                buckets.setdefault(bucket, set()).add(a)
    return pairs, buckets


def test_fingerprint_by_definition():
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 5, 254, 255, 256, 700):
        grams = np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64))
        words = [[], [], [], []]
        for g in map(int, grams):
            words[0].append(g)
            for k in (1, 2, 3):
                h = g * int(near._ODD[0, k]) % (1 << 64)
                h = (h ^ h >> 32) * int(near._ODD[1, k]) % (1 << 64)
                words[k].append(h ^ h >> 29)
        want = [sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in w) > len(w)) for w in words]
        assert near.wide_fingerprint(grams).tolist() == want and want[0] == fingerprint_of(grams)


@pytest.mark.parametrize(("n", "shared"), [(90, 80), (180, 160), (9, 8)])
@pytest.mark.parametrize("nodes", [None, 200_000])
def test_fingerprints_alone_find_pairs_at_the_bound(n, shared, nodes):
    """At a similarity of 0.8 fingerprints differ in about 38 of 256 bits; all such pairs are proposed, and no others."""
    sets = _sets(np.random.default_rng(n), 150, n, shared)
    pairs, buckets = _searched(sets, n=nodes)
    assert set(pairs) == {(2 * k, 2 * k + 1) for k in range(150)} and not buckets
    assert all(pairs.values())  # of two nodes both are hubs


def test_no_fingerprint_near_no_pair(monkeypatch):
    """Equal sets but for one hash are not proposed once their fingerprints are told to be unlike."""
    sets = _sets(np.random.default_rng(2), 20, 100, 99)
    assert len(_searched(sets)[0]) == 20
    rng = np.random.default_rng(3)
    monkeypatch.setattr(near, "wide_fingerprint", lambda s: rng.integers(0, 1 << 63, near.WORDS, dtype=np.uint64))
    assert _searched(sets) == ({}, {})


@pytest.mark.parametrize("crowded", [2, 16, 1 << 30])
def test_all_pairs_of_a_family_are_proposed_or_in_one_bucket(crowded):
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    family = [np.unique(np.concatenate([base, rng.integers(0, 1 << 63, 10, dtype=np.uint64)])) for _ in range(40)]
    pairs, buckets = _searched(family + _sets(rng, 20, 90, 5), crowded)
    assert all(b < 40 for _, b in pairs)  # a bucket may hold others by chance
    for a, b in itertools.combinations(range(40), 2):
        assert (a, b) in pairs or any({a, b} <= x for x in buckets.values())
    assert bool(buckets) == (crowded < 40)


def test_small_sets_are_searched_by_more_indexes():
    """Four and five shingles of which four are shared: 0.8, but about 48 bits differ."""
    rng, sets = np.random.default_rng(5), []
    for _ in range(300):
        five = np.unique(rng.integers(0, 1 << 63, 5, dtype=np.uint64))
        sets += [five, np.delete(five, rng.integers(5))]
    assert {(2 * k, 2 * k + 1) for k in range(300)} <= set(_searched(sets, n=200_000)[0])


def test_a_group_of_any_size_brings_two_choices_a_node():
    """The pairs to count out grow with the nodes of a group of near copies, not with its square."""
    rng = np.random.default_rng(6)
    base = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    for m in (40, 200):
        sets = [np.unique(np.concatenate([base, rng.integers(0, 1 << 63, 10, dtype=np.uint64)])) for _ in range(m)]
        prints = np.array([near.wide_fingerprint(s) for s in sets], dtype=np.uint64).view(np.int64)
        batch = pa.RecordBatch.from_arrays([pa.array(range(m), pa.int64()), pa.array([len(s) for s in sets], pa.int32()), *(pa.array(prints[:, i].copy()) for i in range(near.WORDS))], ["node", "n", *near._FP])
        moved = pa.Table.from_batches(near._moved(iter([batch]))).to_pylist()
        schema = pa.schema([("block", pa.int32()), ("value", pa.int32()), ("prints", pa.binary())])
        packed = [near._chosen(m, 0, 0.8, near.CROWDED, 1)(pa.Table.from_pylist([r], schema)) for r in moved]
        pairs = near._best(pa.concat_tables(packed)).to_pydict()
        assert m - 1 <= len(pairs["a"]) <= 2 * m and set(pairs["a"]) | set(pairs["b"]) == set(range(m))
