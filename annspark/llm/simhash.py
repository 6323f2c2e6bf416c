"""SimHash near-duplicate classes found with BK-trees.

Every whole text gets a 64-bit fingerprint over its 3-word shingles. Texts link
when fingerprints differ in at most two bits, and classes are the connected
components of the links.

The search never compares all fingerprints. Two fingerprints within two bits
agree on one of three fixed bit blocks, so each distinct fingerprint goes to
three shards, one for each block, keyed by the bits it has there. A shard over
SHARD_VALUES values is split the same way: its free bits fall into three blocks
again, and each of its values goes to three smaller shards. After three splits a
shard has at most 14 free bits and so at most 16,384 values, which bounds every
task. Every shard builds a BK-tree, whose children are keyed by their Hamming
distance to the parent, and follows only edges within the radius. The trees live
in the task that owns the shard and aren't broadcast, because their total size
grows with the corpus. Each shard returns a spanning forest of its links (at
most one row per fingerprint), never the pairs, so copies are not expanded.

Defined cases: a null text is an empty text; no words give fingerprint zero,
which links like any other; fewer than three words are one shingle; repeated
rows share a fingerprint and so a class; rows without a doc_id count towards
links but never name a class, whose id is null only if all its ids are null.
Rows that repeat a doc_id but are in different classes are different documents.
Extra columns are ignored by the classes and kept by the filter, whatever their
names; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from annspark.llm.rows import packed, row_hash, unpacked
from annspark.plans.session import ship_package, stage
from annspark.plans.skew import join_hot_apart
from annspark.sources.tables import table

SHINGLE_WORDS = 3
SEED = 42
RADIUS = 2
#: Three blocks: two differing bits leave at least one block equal.
PARTS = RADIUS + 1
#: A shard with more values is split, up to so many times.
SHARD_VALUES, SPLITS = 1024, 3


def fingerprint(text: str | None) -> int:
    """The unsigned 64-bit SimHash of one text."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) < SHINGLE_WORDS:
        shingles = [b" ".join(words)]
    else:
        shingles = list(map(b" ".join, zip(words, words[1:], words[2:])))
    digest = xxhash.xxh64_intdigest
    total = np.zeros(64, np.int64)
    for at in range(0, len(shingles), 65536):
        part = shingles[at : at + 65536]
        h = np.fromiter((digest(s, SEED) for s in part), np.uint64, len(part))
        total += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * total > len(shingles)).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view(np.uint64)[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        fp = np.array([fingerprint(x.as_py()) for x in batch.column(1)], np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp, pa.int64())], ["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp) of each row; fp is the fingerprint's 64 bits as a signed long."""
    ship_package(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_fingerprints, "doc_id long, fp long")


class BKTree:
    """A BK-tree over distinct unsigned 64-bit values.

    Children hang on their integer distance to the parent. Nodes are added in
    bulk: the first value is the root, and the rest split by distance to it.
    """

    __slots__ = ("root", "children")

    def __init__(self, values: np.ndarray):
        self.children: dict[int, BKTree] = {}
        self.root = values[0] if len(values) else None
        rest = values[1:]
        if len(rest):
            gap = np.bitwise_count(rest ^ self.root)
            for d in set(gap.tolist()):
                self.children[d] = BKTree(rest[gap == d])

    def within(self, queries: np.ndarray, radius: int = RADIUS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (query values, tree values) at most ``radius`` apart, in bulk."""
        if not len(queries) or self.root is None:
            return
        gap = np.bitwise_count(queries ^ self.root).astype(np.int16)
        near = queries[gap <= radius]
        if len(near):
            yield near, np.full(len(near), self.root)
        for d, child in self.children.items():
            yield from child.within(queries[np.abs(gap - d) <= radius], radius)


class Forest:
    """Union-find over positions, smallest position as root."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> None:
        a, b = self.find(a), self.find(b)
        if a != b:
            self.up[max(a, b)] = min(a, b)


def shard_links(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links among the sorted distinct values of one shard."""
    n = len(values)
    forest = Forest(n)
    for q, t in BKTree(values).within(values):
        for a, b in zip(np.searchsorted(values, q).tolist(), np.searchsorted(values, t).tolist()):
            forest.join(a, b)
    roots = np.array([forest.find(x) for x in range(n)], np.int64)
    linked = np.flatnonzero(roots != np.arange(n))
    return values[linked], values[roots[linked]]


def _links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (fixed, key, fp): one shard after another, across batches."""
    held: list[np.ndarray] = []
    now: tuple[int, int] | None = None

    def out(parts: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        values = np.unique(np.concatenate(parts)) if parts else np.empty(0, np.uint64)
        if len(values) > 1:
            a, b = shard_links(values)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    for batch in batches:
        if not batch.num_rows:
            continue
        fixed, key, fp = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
        edges = np.flatnonzero((fixed[1:] != fixed[:-1]) | (key[1:] != key[:-1])) + 1
        starts, ends = np.concatenate([[0], edges]), np.concatenate([edges, [len(fp)]])
        lone = ends - starts == 1
        for i in np.flatnonzero(~lone | (starts == 0) | (ends == len(fp))):
            s, e = int(starts[i]), int(ends[i])
            shard = (int(fixed[s]), int(key[s]))
            if shard != now:
                yield from out(held)
                now, held = shard, []
            held.append(fp[s:e].astype(np.int64).view(np.uint64))
    yield from out(held)


def parts_of(fixed: int) -> list[int]:
    """The masks of the shards that a shard with the fixed bits ``fixed`` is split into: each fixes a third of the free bits more."""
    free = [b for b in range(64) if not fixed >> b & 1]
    cuts = [len(free) * i // PARTS for i in range(PARTS + 1)]
    masks = [fixed | sum(1 << b for b in free[s:e]) for s, e in zip(cuts, cuts[1:])]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _split(rows: DataFrame, masks: list[int]) -> DataFrame:
    """(fixed, key, fp): each row's value in the shards of ``masks``."""
    part = F.explode(F.array(*[F.lit(m).cast("long") for m in masks])).alias("fixed")
    return rows.select("fp", part).select("fixed", F.col("fixed").bitwiseAND(F.col("fp")).alias("key"), "fp")


def shards(distinct: DataFrame) -> DataFrame:
    """(fixed, key, fp): every value of ``distinct(fp)`` in its shards, none with more values than a task can hold."""
    masks, rows, done = parts_of(0), _split(distinct, parts_of(0)), None
    for _ in range(SPLITS):
        large = stage(rows.groupBy("fixed", "key").agg(F.count("*").alias("n")).where(F.col("n") > SHARD_VALUES).drop("n"), "large-shards")
        if not large.take(1):
            break
        fine = rows.join(large, ["fixed", "key"], "left_anti")
        done = fine if done is None else done.unionByName(fine)
        inside = rows.join(large, ["fixed", "key"], "left_semi")
        finer = [_split(inside.where(F.col("fixed") == m), parts_of(m & (1 << 64) - 1)) for m in masks]
        masks = [p for m in masks for p in parts_of(m & (1 << 64) - 1)]
        rows = finer[0]
        for more in finer[1:]:
            rows = rows.unionByName(more)
        rows = stage(rows, "shards")
    return rows if done is None else done.unionByName(rows)


def link_forest(distinct: DataFrame) -> DataFrame:
    """Links (a, b) between different fingerprints that span every class of ``distinct(fp)``."""
    ship_package(distinct.sparkSession)
    return shards(distinct).repartition("fixed", "key").sortWithinPartitions("fixed", "key", "fp").mapInArrow(_links, "a long, b long")


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``links(a, b)``: root is the smallest node reachable.

    Alternating star contraction: each round points every node at the smallest
    node next to it, first among larger neighbours and then among smaller ones,
    until the edge set stands still. Each round is written to the shared folder.
    """
    edges = stage(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")

    def star(e: DataFrame, large: bool) -> DataFrame:
        if large:
            both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        else:
            both = e.select("u", "v")
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        joined = both.join(low, "u")
        if large:
            moved = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        else:
            moved = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        return moved.where("u <> v").distinct()

    def state(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    before = state(edges)
    for _ in range(rounds):
        if not before[0]:
            break
        edges = stage(star(star(edges, True), False), "links")
        after = state(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("the links did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def near_duplicate_classes(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, root, component_id) for each row of ``docs``: root is the class's smallest fingerprint, component_id its smallest doc_id."""
    each = stage(fingerprints(docs), "fingerprints")
    nodes = stage(each.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count("*").alias("n")), "nodes")
    roots = stage(components(link_forest(nodes.select("fp"))), "roots")
    linked = roots.withColumnRenamed("node", "fp").unionByName(roots.select(F.col("root").alias("fp"), "root").distinct())
    linked = nodes.join(linked, "fp").select("fp", "root", "low")
    low = linked.groupBy("root").agg(F.min("low").alias("class_low"))
    classes = nodes.join(linked.join(low, "root").select("fp", "root", "class_low"), "fp", "left")
    classes = classes.select("fp", "n", F.coalesce("root", "fp").alias("root"), F.coalesce("class_low", "low").alias("component_id"))
    return join_hot_apart(each, stage(classes, "classes"), "fp", "n").select("doc_id", "fp", "root", "component_id")


@F.arrow_udf(LongType())
def _fingerprint_of(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
    for batch in texts:
        yield pa.array(np.array([fingerprint(t.as_py()) for t in batch], np.uint64).view(np.int64), pa.int64())


def keep_representatives(docs: DataFrame) -> DataFrame:
    """One document of each class, all columns of ``docs``.

    The row with the class's smallest doc_id stays. Of rows that repeat that id
    within a class, and of a class without any id, the row with the least hash
    stays; rows that repeat an id in different classes all stay.
    """
    classes = stage(near_duplicate_classes(docs), "classes")
    kept = classes.where(F.col("doc_id").eqNullSafe(F.col("component_id")))
    ids = stage(kept.groupBy("doc_id").agg(F.count("*").alias("rows_of_id")), "kept")
    alone = F.col("doc_id").isNotNull() & (F.col("rows_of_id") == 1)
    once, more = ids.where(alone).select(F.col("doc_id").alias("kept_id")), ids.where(~alone).select(F.col("doc_id").alias("kept_id"))
    rows = docs.select(packed(docs), F.col("doc_id").cast("long").alias("own_id"), F.col("text").cast("string").alias("own_text"), row_hash(docs).alias("own_hash"))
    # The table of kept ids grows with the corpus, so it's merged at every size and never broadcast.
    out = rows.join(once.hint("merge"), F.col("own_id") == F.col("kept_id"), "left_semi").select("row")
    if more.take(1):
        repeated = rows.join(more, F.col("own_id").eqNullSafe(F.col("kept_id")), "left_semi").withColumn("own_fp", _fingerprint_of("own_text"))
        of = kept.join(more, F.col("doc_id").eqNullSafe(F.col("kept_id")), "left_semi").select("doc_id", "fp", "root").distinct()
        owned = repeated.join(of, F.col("own_id").eqNullSafe(F.col("doc_id")) & (F.col("own_fp") == F.col("fp")))
        out = out.unionByName(owned.groupBy("own_id", "root").agg(F.min_by("row", "own_hash").alias("row")).select("row"))
    return out.select(*unpacked(out, docs.columns))


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: doc_id, fingerprint (16 hex digits), component_id."""
    found = near_duplicate_classes(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
