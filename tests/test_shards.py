"""Rules that walk over the edges in shards: the parts of a plain search, in few rounds."""

import random

import pytest


def plain_growth(ids, edges, p):
    """node: part by breadth-first search, a ring at a time."""
    near = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b), near.setdefault(b, set()).add(a)
    low, high, want = min(ids), max(ids), {}
    for j in reversed(range(p)):
        want[min(i for i in ids if i >= low + (high - low) * j // p)] = j
    ring = dict(want)
    while ring:
        found = {}
        for a, j in ring.items():
            for b in near.get(a, set()) - want.keys():
                found[b] = min(j, found.get(b, j))
        want |= (ring := found)
    return {i: want.get(i, i % p) for i in ids}


def frames(spark, ids, edges):
    return spark.createDataFrame([(i,) for i in ids], "atom_id long"), spark.createDataFrame(edges, "src long, dst long")


def test_growth_has_no_round_for_each_ring(spark):
    """A path of 400 nodes in one shard: before, a table was written for each of its rings."""
    from halograph.graph.partition import growth_partition
    from halograph.graph.scratch import Scratch

    ids, scratch = list(range(400)), Scratch(spark)
    edges = [(i, i + 1) for i in ids[:-1]]
    got = growth_partition(*frames(spark, ids, edges), 2, scratch)
    assert {r.atom_id: r.part_id for r in got.collect()} == plain_growth(ids, edges, 2)
    assert scratch.n <= 4


@pytest.mark.parametrize("shard_nodes", [15, 1000])
def test_growth_over_shards_is_that_of_a_plain_search(spark, shard_nodes):
    """Identifiers with gaps and below zero, islands, loops, edges twice, an end that is no atom."""
    from halograph.graph.partition import growth_partition
    from halograph.graph.scratch import Scratch

    r = random.Random(5)
    ids = r.sample(range(-500, 3000), 150)
    edges = [(r.choice(ids), r.choice(ids)) for _ in range(170)]
    edges += [*edges[:5], (ids[0], ids[0]), (ids[0], 9999), (9999, ids[1])]
    got = growth_partition(*frames(spark, ids, edges), 4, Scratch(spark), shard_nodes)
    assert {r.atom_id: r.part_id for r in got.collect()} == plain_growth(ids, edges, 4)


def plain_vector(ids, edges, rounds):
    near = {}
    for a, b in edges:
        if a != b:
            near.setdefault(a, set()).add(b), near.setdefault(b, set()).add(a)
    v = {i: i * 7919 % 1_000_003 / 1_000_003 - 0.5 for i in ids}
    for _ in range(rounds):
        moved = {}
        for i in ids:
            heard = [v[j] for j in near.get(i, ()) if j in v]
            moved[i] = v[i] / 2 + (sum(heard) / len(near[i]) if heard else v[i]) / 2
        weight = {i: len(near.get(i, ())) for i in ids}
        mean = sum(moved[i] * weight[i] for i in ids) / max(1, sum(weight.values()))
        scale = (sum(x * x for x in moved.values()) / len(ids)) ** 0.5
        v = {i: (x - mean) / scale for i, x in moved.items()}
    return v


@pytest.mark.parametrize("shard_nodes", [15, 1000])
def test_eigenvector_over_shards_is_that_of_a_plain_sum(spark, shard_nodes):
    from halograph.graph.scratch import Scratch
    from halograph.graph.shards import Shards

    r = random.Random(7)
    ids = r.sample(range(-500, 3000), 120)
    edges = [(r.choice(ids), r.choice(ids)) for _ in range(200)] + [(ids[0], 9999), (9999, ids[1]), (ids[3], 8000)]
    got = {x.atom_id: x.v for x in Shards(*frames(spark, ids, edges), Scratch(spark), shard_nodes).eigenvector(5).collect()}
    want = plain_vector(ids, edges, 5)
    assert got.keys() == want.keys() and all(abs(got[i] - want[i]) < 1e-9 for i in ids)
