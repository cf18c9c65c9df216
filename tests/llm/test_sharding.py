import random
import zlib

import pytest

from seqcount.llm import sharding


def brute_best_fit(sizes, capacity):
    left = []
    for s in sorted(sizes, reverse=True):
        fits = [i for i, r in enumerate(left) if r >= s]
        if fits:
            best = min(fits, key=lambda i: (left[i], i))
        else:
            left.append(max(capacity, s))
            best = len(left) - 1
        left[best] -= s
    return sorted(left)


def test_tree_is_an_ordered_set():
    rng, tree, keys = random.Random(8), sharding.Tree(), set()
    for _ in range(4000):
        key = (rng.randint(0, 300), rng.randint(0, 3))
        if key in keys and rng.random() < 0.7:
            tree.remove(key)
            keys.discard(key)
        elif key not in keys:
            tree.add(key)
            keys.add(key)
        ask = (rng.randint(-5, 310), -1)
        assert tree.ceiling(ask) == min((k for k in keys if k >= ask), default=None)

    def depth(node):
        return 0 if not node else 1 + max(depth(node.left), depth(node.right))

    assert depth(tree.root) < 40


def test_runs_of_equal_sizes_pack_like_single_items():
    rng = random.Random(5)
    for _ in range(200):
        sizes = [rng.choice([1, 2, 3, 5, 8, 13, 40]) for _ in range(rng.randint(0, 80))]
        capacity = rng.randint(13, 60)
        histogram = [(s, sizes.count(s)) for s in set(sizes)]
        spans = sharding.pack(histogram, capacity)
        used = {}
        for size, a, b, shard in spans:
            used[shard] = used.get(shard, 0) + size * (b - a)
        bound = {s: max(capacity, max(x for x, _, _, sh in spans if sh == s)) for s in used}
        assert sorted(bound[s] - u for s, u in used.items()) == brute_best_fit(sizes, capacity)
        assert sum(b - a for _, a, b, _ in spans) == len(sizes)


@pytest.mark.parametrize("histogram", [[], [(16, 1)], [(16, 1000)], [(1_000_000, 1), (100, 500)], [(7, 3), (5, 4)]])
def test_even_packing_stays_within_the_shards(histogram):
    spans = sharding.pack_evenly(histogram, 40)
    assert {x for *_, x in spans} <= set(range(40))
    assert sum(b - a for _, a, b, _ in spans) == sum(c for _, c in histogram)


def test_shards_of_rows(spark):
    rng = random.Random(11)
    rows = [(i, "w" * rng.randint(0, 300)) for i in range(800)] + [(900 + i, "hot" * 50) for i in range(200)] + [(None, None), (5, "again"), (5, "again"), (2000, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(9).selectExpr("doc_id", "text", "0 as shard", "1 as n")
    got = sharding.shard_by_bytes(docs, 7).collect()
    assert sorted((repr(r["rid"]), r["size"], r["crc"]) for r in got) == sorted((repr(d), len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for d, t in rows)
    slots, loads, homes = {}, {}, {}
    texts = {}
    for d, t in rows:
        texts.setdefault(zlib.crc32((t or "").encode()), set()).add(t or "")
    for r in got:
        slots.setdefault(r["shard"], []).append(r["slot"])
        loads[r["shard"]] = loads.get(r["shard"], 0) + r["size"]
        homes.setdefault(r["crc"], set()).add(r["shard"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert all(len(h) == 1 for h in homes.values())
    hot = 200 * (150 + 16)
    others = [v for v in loads.values() if v != max(loads.values())] if max(loads.values()) == hot else list(loads.values())
    assert max(others) - min(others) <= 0.05 * max(others)
    assert sorted(map(tuple, got), key=repr) == sorted(map(tuple, sharding.shard_by_bytes(docs.repartition(3), 7).collect()), key=repr)
    assert sharding.shard_by_bytes(docs.limit(0), 7).count() == 0
