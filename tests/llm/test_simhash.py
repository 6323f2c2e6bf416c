import random

import numpy as np
import pytest
import xxhash

from annspark.llm import simhash as H


def slow(text):
    w = (text or "").encode().lower().split()
    s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else ([b" ".join(w)] if w else [])
    hs = [xxhash.xxh64_intdigest(x, seed=42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)) if hs else 0


def classes(fps):
    up = list(range(len(fps)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(fps)):
        for b in range(a):
            if (fps[a] ^ fps[b]).bit_count() <= 2:
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return [find(i) for i in range(len(fps))]


def cluster(n, seed, flips=3):
    rng = random.Random(seed)
    base = rng.getrandbits(64)
    out = set()
    while len(out) < n:
        v = base
        for _ in range(rng.randint(0, flips)):
            v ^= 1 << rng.randrange(21, 64)
        out.add(v)
    return np.array(sorted(out), np.uint64)


def linked(values, pairs):
    up = {int(v): int(v) for v in values}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in zip(*pairs):
        x, y = find(int(a)), find(int(b))
        up[max(x, y)] = min(x, y)
    return [find(int(v)) for v in values]


@pytest.mark.parametrize("n", [2, 30, 200, 700, 1500])
def test_shard_trees_agree_with_brute_force(n):
    values = cluster(n, n)
    want = [int(values[i]) for i in classes([int(v) for v in values])]
    tree = H.shard_links(values)
    assert linked(values, tree) == want and len(tree[0]) < n


def fast_classes(values):
    """Smallest value reachable, by distances from each value to all."""
    up = {v: v for v in values.tolist()}

    def find(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for v in values:
        for w in values[np.bitwise_count(values ^ v) <= 2].tolist():
            x, y = find(int(v)), find(w)
            up[max(x, y)] = min(x, y)
    return {v: find(v) for v in up}


@pytest.mark.parametrize("limit", [1024, 8])
def test_large_shards_are_split_and_keep_their_trees(spark, monkeypatch, limit):
    monkeypatch.setattr(H, "SHARD_VALUES", limit)
    rng = np.random.default_rng(6)
    near = [cluster(1300, 1, 3), cluster(1300, 2, 6), rng.integers(0, 2**63, 300).astype(np.uint64)]
    values = np.unique(np.concatenate(near) & np.uint64(2**63 - 1))
    df = spark.createDataFrame([(int(v),) for v in values], "fp long")
    sizes = H.shards(df).groupBy("fixed", "key").count().collect()
    least = 21 if limit == 1024 else 50
    assert all(r["count"] <= limit or (r.fixed & (1 << 64) - 1).bit_count() >= least for r in sizes)
    assert len({(r.fixed & (1 << 64) - 1).bit_count() for r in sizes}) > 2
    got = {r.node: r.root for r in H.components(H.link_forest(df)).collect()}
    assert {v: got.get(v, v) for v in values.tolist()} == fast_classes(values)


def test_bk_tree_finds_all_within_radius():
    values = cluster(400, 5, 8)
    got = {(int(a), int(b)) for q, t in H.BKTree(values).within(values) for a, b in zip(q, t)}
    want = {(int(a), int(b)) for a in values for b in values if (int(a) ^ int(b)).bit_count() <= 2}
    assert got == want


def test_fingerprints_and_classes(spark, docs_of, folder_of):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(50)]
    rows = []
    for g in range(12):
        base = [rng.choice(words) for _ in range(400)]
        for c in range(rng.randint(1, 6)):
            t = list(base)
            if c:
                t[rng.randrange(400)] = "changed"
            rows.append((len(rows) * 3 % 101, " ".join(t).upper() if c % 2 else " ".join(t), "en", "s"))
    rows += [(200, None, "en", "s"), (201, "", "en", "s"), (202, "One two", "en", "s"), (203, "one TWO ", "en", "s"), (204, "é É", None, None)]
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in H.op6_simhash_near_dedup(spark, folder_of("documents", docs_of(rows))).collect()}
    rows.sort()
    fps = [slow(r[1]) for r in rows]
    want = {r[0]: (f"{fps[i]:016x}", rows[c][0]) for i, (r, c) in enumerate(zip(rows, classes(fps)))}
    assert got == want and got[201][1] == 200 and got[203][1] == 202


def test_long_chain_is_one_class(spark):
    values = [0]
    for b in range(60):
        values.append(values[-1] ^ (3 << b) if b % 2 == 0 else values[-1] ^ (1 << b))
    values = sorted(set(v & (2**63 - 1) for v in values))
    df = spark.createDataFrame([(v,) for v in values], "fp long")
    got = {r.node: r.root for r in H.components(H.link_forest(df)).collect()}
    want = classes(values)
    assert all(got.get(v, v) == values[want[i]] for i, v in enumerate(values))


def test_edges(edge, empty):
    rows = H.near_duplicate_classes(edge).collect()
    assert len(rows) == 10 and {r.component_id for r in rows if r.doc_id in (1, 2, 3)} == {1} and {r.component_id for r in rows if r.doc_id == 5} == {4}
    assert H.near_duplicate_classes(empty).count() == 0 and H.keep_representatives(empty).count() == 0
    kept = H.keep_representatives(edge)
    assert kept.columns == edge.columns and sorted((r.doc_id if r.doc_id is not None else -1) for r in kept.collect()) == [-1, 1, 4, 6, 7, 8]


def test_repeated_ids_stay_once(docs_of):
    docs = docs_of([(1, "a b c d", "en", "s")] * 3 + [(2, "a b c d", "en", "s")])
    assert [r.doc_id for r in H.keep_representatives(docs).collect()] == [1]


def test_rows_of_one_id_in_different_classes_all_stay(docs_of):
    other, third = "quite another text that has nothing in common", "some third text which stands alone here"
    docs = docs_of([(1, "a b c d", "en", "s"), (1, other, "en", "s"), (2, "a b c d", "en", "s"), (3, other, "en", "s"), (None, third, "en", "s"), (None, third, "en", "t"), (None, "a b c d", "en", "s"), (4, "fourth", "en", "s")])
    got = H.keep_representatives(docs)
    assert got.columns == docs.columns and sorted((r.doc_id or 0, r.text) for r in got.collect()) == [(0, third), (1, "a b c d"), (1, other), (4, "fourth")]


def test_extra_columns_with_the_names_used_inside(spark):
    names = ["fp", "row", "root", "kept_id", "own_id", "own_text", "own_hash", "own_fp", "component_id", "rows_of_id", "a.b"]
    rows = [(i, t, *names) for i, t in ((1, "a b c"), (1, "d e f"), (2, "a b c"), (None, "g h i"), (3, "k l m"))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, " + ", ".join(f"`{n}` string" for n in names))
    assert sorted(map(tuple, H.keep_representatives(docs).collect()), key=str) == sorted([r for r in rows if r[0] != 2], key=str)
