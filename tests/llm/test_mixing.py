import re
from collections import Counter, defaultdict

import pytest
import xxhash
from pyspark.sql import functions as F

from annspark.llm import mixing as M

ROWS = [(i, " ".join(f"w{i}x{j}" for j in range(1 + (i * 37) % 400)), "en", ["a", "b", "é", "z", None][min(4, i % 11 // 2)]) for i in range(160)]
ROWS += [(900, None, "en", "a"), (901, "  ", "en", "q"), (902, "dup row", "en", "b"), (902, "dup row", "en", "b"), (903, "tiny", "en", "tiny")]


def size(t):
    return len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))


def water(sizes):
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + ([None] if None in sizes else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    total, capped = sum(sizes.values()), set()
    while True:
        left = total - sum(3 * sizes[s] for s in capped)
        free = sum(weight[s] for s in names if s not in capped)
        target = {s: 3 * sizes[s] if s in capped else left * weight[s] / free for s in names}
        over = {s for s in names if s not in capped and target[s] > 3 * sizes[s] + 1e-9}
        if not over:
            return target
        capped |= over


def spark_hash(*values):
    """The engine's hash of some longs."""
    h = 42
    for v in values:
        h = xxhash.xxh64_intdigest(v.to_bytes(8, "little", signed=True), h)
    return h - (1 << 64) if h >= 1 << 63 else h


def java_mod(x, n):
    return x % n if x >= 0 or x % n == 0 else x % n - n


def shuffled(x, n, *key):
    for r in range(1, M.ROUNDS + 1):
        partner = (spark_hash(*key, r) % n - x) % n
        x = x if java_mod(spark_hash(*key, r, max(x, partner)), 2) == 0 else partner
    return x


def whole_draw(streams, target, block_words, shard_slots, tolerance, seed):
    """Brute force: {(source, shard): draws of the slots}, and how often each (source, word) is taken; slot by slot."""
    names = sorted((s for s in streams if s is not None), key=lambda s: s.encode()) + ([None] if None in streams else [])
    need, blocks, words = {}, {}, {}
    for s in names:
        size = len(streams[s])
        blocks[s] = [streams[s][i : i + block_words] for i in range(0, size, block_words)]
        words[s] = int(target[s] + 0.5) if size else 0
        need[s] = words[s] // size * len(blocks[s]) + -(-(words[s] % size) // block_words) if size else 0
    slots = [s for s in names for _ in range(need[s])]
    counts, rows = Counter(), defaultdict(list)
    for g in range(len(slots)):
        s = slots[spark_hash(seed, g // shard_slots, g % shard_slots) % len(slots)]
        counts[s, g // shard_slots] += 1
        rows[s].append(g // shard_slots)
    slack = {s: int(need[s] * tolerance) for s in names}
    given = []
    for s in names:
        most = min(need[s] + slack[s], 3 * len(blocks[s]))
        given += rows[s][most:]
        rows[s] = rows[s][:most]
    wants = [s for s in names for _ in range(need[s] - slack[s] - len(rows[s]))]
    extra = [g // shard_slots for g in range(len(slots), len(slots) + max(0, len(wants) - len(given)))]
    tops = {s: max(0, need[s] - max(len(rows[s]), need[s] - slack[s])) for s in names}
    wants += [s for s in names for _ in range(tops[s])]
    for shard, s in zip(given + extra, wants):
        rows[s].append(shard)
    taken = Counter()
    for n, s in enumerate(names):
        whole = len(streams[s]) // block_words
        for i in range(len(rows[s])):
            turn, at = divmod(i, len(blocks[s]))
            block = blocks[s][shuffled(at, whole, seed, n, turn) if at < whole else at]
            if i == need[s] - 1 == len(rows[s]) - 1 and words[s] % len(streams[s]):
                block = block[: words[s] % len(streams[s]) - block_words * (-(-(words[s] % len(streams[s])) // block_words) - 1)]
            taken.update((s, w) for w in block)
    return counts, taken, {s: len(rows[s]) for s in names}


@pytest.mark.parametrize("block_words,shard_slots,tolerance,seed", [(64, 1024, 0.008, 20_011), (3, 7, 0.05, 5), (3, 7, 0.05, 6), (5, 64, 0.0, 1)])
def test_the_whole_draw_by_brute_force(spark, docs_of, block_words, shard_slots, tolerance, seed):
    rows = [(i, t, "en", s) for i, t, _, s in ROWS if i not in (902,)]
    plan = M.Plan(docs_of(rows), block_words, seed, shard_slots, tolerance)
    streams, name = defaultdict(list), {r.sid: r.source for r in plan.sources.collect()}
    for r in plan.placed.orderBy("sid", "first").collect():
        assert r.first == len(streams[name[r.sid]]) or not r.size
        streams[name[r.sid]] += [(r.doc_id, j) for j in range(r.size)]
    target = water({s: len(w) for s, w in streams.items()} | {"q": 0})
    counts, taken, draws = whole_draw({s: streams.get(s, []) for s in target}, target, block_words, shard_slots, tolerance, seed)
    assert {(name[r.sid], r.shard): r.n for r in plan.shard_counts().collect()} == counts
    assert {r.source: r.draws for r in plan.totals.collect()} == draws
    want = Counter()
    for (_, (i, _)), n in taken.items():
        want[i] += n
    assert {r.doc_id: r.taken for r in plan.taken().collect() if r.taken} == want


def test_seeds_change_the_draws_and_what_is_taken(spark, docs_of):
    plans = [M.Plan(docs_of(ROWS), 4, seed, 64) for seed in (1, 2)]
    counts = [{(r.sid, r.shard): r.n for r in p.shard_counts().collect()} for p in plans]
    taken = [sorted((r.doc_id, r.taken) for r in p.taken().collect()) for p in plans]
    draws = [{r.sid: r.draws for r in p.totals.collect()} for p in plans]
    assert counts[0] != counts[1] and taken[0] != taken[1] and draws[0] != draws[1]


def test_shard_length_changes_what_is_taken(spark, docs_of):
    taken = [sorted((r.doc_id, r.taken) for r in M.Plan(docs_of(ROWS), 4, 1, n).taken().collect()) for n in (64, 7)]
    assert taken[0] != taken[1]


def test_targets_and_takes(spark, docs_of, folder_of):
    d = folder_of("documents", docs_of(ROWS))
    got = sorted((tuple(r) for r in M.op7_mix_sources(spark, d).collect()), key=str)
    assert got == sorted((tuple(r) for r in M.op7_mix_sources(spark, d).collect()), key=str)
    sizes = defaultdict(int)
    for _, t, _, s in ROWS:
        sizes[s] += size(t)
    target = water(sizes)
    source = {i: s for i, _, _, s in ROWS}
    taken = Counter()
    assert len(got) == len(ROWS)
    for i, n, ssize, tgt, took, draws, low, high in got:
        assert n in {size(t) for j, t, *_ in ROWS if j == i} and ssize == sizes[source[i]] and tgt == pytest.approx(target[source[i]]) and 0 <= took <= 3 * n
        assert (low is None) == (draws == 0) and (took == 0 or draws > 0) and (low is None or low <= high)
        taken[source[i]] += took
    for s in sizes:
        assert abs(taken[s] - target[s]) <= max(1, 0.01 * target[s]), s


def test_rows_that_differ_in_any_column_stay_apart(spark):
    rows = [(1, "one two three", "en", s, 13, x) for s in "abc" for x in (0.5, 1.5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, x double")
    out = {(r.source, r.x) for r in M.mix_documents(docs).collect()}
    plan = M.Plan(docs)
    took = {(r.sid, r.tie) for r in plan.taken().collect() if r.taken}
    assert len(out) == len(took) and {s for s, _ in out} == {"a", "b"} | ({"c"} if any(s == 2 for s, _ in took) else set())


def test_extra_columns_with_the_names_used_inside(spark):
    names = ["row", "key", "hash", "uses", "use", "parts", "shard", "tie", "sid", "first", "pass", "block", "cut", "size", "words", "_source", "target", "source_size", "a.b", "m"]
    rows = [(i, "one two three four", "en", "s", 18, *[f"{n}{i}" for n in names[:-1]], {"k": i}) for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{n}` string" for n in names[:-1]) + ", m map<string,int>")
    got = M.mix_documents(docs, shard_column="out").collect()
    assert sorted(tuple(r)[:-1] for r in got) == sorted(rows) and {r.out for r in got} == {0}


def test_permutations_are_bijections(spark):
    for n in (1, 2, 7, 100, 1000):
        got = [r.p for r in spark.range(n).select(M.permuted("id", f"{n}L", "5L").alias("p")).collect()]
        assert sorted(got) == list(range(n))
    assert got != list(range(1000)) and sum(abs(a - i) for i, a in enumerate(got)) > 200_000


def test_shards_vary_like_draws(spark, docs_of):
    plan = M.Plan(docs_of(ROWS), block_words=4)
    by = defaultdict(list)
    for r in plan.shard_counts().collect():
        by[r.sid].append(r.n)
    slots = plan.slots()
    assert slots.count() == sum(r.draws for r in plan.totals.collect()) and slots.select("shard", "slot").distinct().count() == slots.count()
    assert any(len(set(v[:-1])) > 1 for v in by.values() if len(v) > 2)


def test_mixed_documents_hold_what_is_taken(spark, docs_of):
    docs = docs_of(ROWS)
    plan = M.Plan(docs)
    taken = Counter()
    for r in plan.taken().collect():
        taken[r.doc_id] += r.taken
    out = M.mix_documents(docs)
    assert out.columns == docs.columns
    rows, words = out.collect(), Counter()
    texts = {i: t for i, t, *_ in ROWS}
    for r in rows:
        words[r.doc_id] += size(r.text)
        own = set(texts[r.doc_id].split())
        assert r.text == texts[r.doc_id] or set(r.text.split()) <= own and r.n_chars == len(r.text)
    assert +words == +taken


def test_edges(edge, empty, spark, folder_of):
    assert M.op7_mix_sources(spark, folder_of("documents", edge)).count() == 10
    assert M.op7_mix_sources(spark, folder_of("documents", empty)).count() == 0
    assert M.mix_documents(empty).count() == 0
    blank = edge.where("doc_id IN (1, 2)")
    assert [(r.target, r.taken) for r in M.Plan(blank).taken().collect()] == [(0.0, 0), (0.0, 0)]
