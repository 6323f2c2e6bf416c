"""Mixing sources to target weights, in fixed-length blocks of words.

Each source's texts form one stream of words, in an order that depends on ids
alone, cut into blocks of BLOCK_WORDS; what is left at its end is a remainder
block. The mixture is a sequence of slots, and each output shard is a run of
SHARD_SLOTS slots. Every slot draws its source by a seeded hash with the
sources' shares as chances, so a shard's counts are a multinomial draw. A
source's draws are numbered shard by shard; the number gives a pass and, through
a permutation for each source and pass, a block (a pass ends with the remainder
block). Blocks then join texts by index.

The draws decide how much of each source is taken. Free draws miss small targets
by chance and could pass the limit of three repeats, so totals are corrected: a
source keeps at most TOLERANCE more draws than it needs, and never more than
three passes. Its draws beyond that, which lie in the last shards, go to the
sources that are short, and if those need more, slots are added at the end. A
source that gets exactly what it needs has its last block cut, so that it ends
on its target to the word.

Permutations are swap-or-not shuffles over exactly n places (any n), written as
built-in expressions of the place: nothing is sorted and nothing is kept. Word
offsets are prefix sums over salted parts of each source, and draws are numbered
within groups of shards first, so a source with a third of all rows is still
many parts.

Targets: a source's share goes by weight (5, 2, 1 repeating in code-point order,
null last) but stops at MAX_REPEATS times its size, and what is above goes to
the others by weight. That is a water level, found with running sums over the
table of sources, one row each.

Defined cases: null and empty texts have size 0 and are never taken; a null
source is a source like any other; rows that repeat in all columns are counted
each, and rows that differ in any column stay apart; ties in the order are
between equal rows; extra columns, whatever their names, are kept by the mixed
documents; an empty table gives no rows. Reruns give the same rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.llm.rows import packed, row_hash, unpacked
from annspark.plans.session import stage
from annspark.sources.tables import table

WEIGHTS = (5.0, 2.0, 1.0)
MAX_REPEATS = 3
BLOCK_WORDS = 64
SHARD_SLOTS = 1024
SEED = 20_011
#: A source's draws may differ from what it needs by this share.
TOLERANCE = 0.008
#: Rounds of a swap-or-not shuffle.
ROUNDS = 24
#: About so many rows are summed by one task.
ROWS_PER_SALT = 20_000
LEAST_SALTS = 64
#: A source's draws are numbered in groups of so many shards.
SHARDS_PER_GROUP = 4096
#: Slots of one file, at most about so many.
SLOTS_PER_FILE = 250_000
#: Cells of a range of numbers that are joined to its intervals by equality.
CELLS = 4096
#: The table of sources is broadcast up to so many rows.
BROADCAST_SOURCES = 100_000
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def sizes(docs: DataFrame) -> DataFrame:
    """doc_id, source, size in words, and tie: a hash of the row."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"),
        F.regexp_count(text, F.lit(WORD)).cast("long").alias("size"), row_hash(docs).alias("tie"),
    )


def targets(sized: DataFrame, weights: tuple[float, ...] = WEIGHTS, repeats: int = MAX_REPEATS) -> DataFrame:
    """(sid, source, source_size, target) of every source.

    A single window runs over the table of sources, one row each.
    """
    totals = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    everything = W.orderBy(F.col("source").asc_nulls_last())
    share = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.col("sid"), F.lit(len(weights))) + 1).cast("int"))
    ranked = totals.withColumn("sid", F.row_number().over(everything).cast("long") - 1).withColumn("weight", share)
    ranked = ranked.withColumn("cap", F.col("source_size") * float(repeats)).withColumn("ratio", F.col("cap") / F.col("weight"))
    by = W.orderBy("ratio", "sid")
    before, after = by.rowsBetween(W.unboundedPreceding, -1), by.rowsBetween(0, W.unboundedFollowing)
    whole = W.partitionBy(F.lit(1))
    level = (F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    levelled = ranked.withColumn("level", level)
    # The first source, by ratio, that its level doesn't fill sets the level of all.
    final = F.min(F.when(F.col("ratio") >= F.col("level"), F.struct("ratio", "sid", "level"))).over(whole)["level"]
    filled = F.least(F.col("cap"), F.col("weight") * F.coalesce(final, F.lit(float("inf"))))
    return levelled.select("sid", "source", "source_size", filled.alias("target"))


def permuted(x: str, n: str, key: str, rounds: int = ROUNDS) -> Column:
    """The place of ``x`` under a pseudorandom permutation of 0 .. n-1 chosen by ``key`` (SQL expressions)."""
    partner = f"pmod(pmod(xxhash64({key}, r), {n}) - p, {n})"
    return F.expr(f"aggregate(sequence(1L, {rounds}L), cast({x} AS bigint), (p, r) -> CASE WHEN xxhash64({key}, r, greatest(p, {partner})) % 2 = 0 THEN p ELSE {partner} END)")


class Plan:
    """Tables of one mixture: placed documents, sources and slots."""

    def __init__(self, docs: DataFrame, block_words: int = BLOCK_WORDS, seed: int = SEED, shard_slots: int = SHARD_SLOTS, tolerance: float = TOLERANCE, repeats: int = MAX_REPEATS):
        self.block_words, self.seed, self.shard_slots = block_words, seed, shard_slots
        sized = stage(sizes(docs), "mix-sizes")
        self.spark = sized.sparkSession
        self.sources = stage(self._needs(targets(sized, repeats=repeats), tolerance, repeats), "mix-sources")
        self.n_sources, self.n_slots = self.sources.agg(F.count("*"), F.coalesce(F.max("high"), F.lit(0))).first()
        self.salts = max(LEAST_SALTS, sized.count() // ROWS_PER_SALT)
        self.placed = self._placed(sized)
        self.drawn = self._drawn()
        self.totals = self._totals()

    def _small(self, df: DataFrame) -> DataFrame:
        return F.broadcast(df) if self.n_sources <= BROADCAST_SOURCES else df

    def _needs(self, sources: DataFrame, tolerance: float, repeats: int) -> DataFrame:
        """Sources with the draws they need, bounds of what they may get, words of the last draw, and their interval of the draw."""
        b, size = self.block_words, F.col("source_size")
        words = F.floor(F.col("target") + 0.5)
        rows = sources.withColumn("full", F.floor(size / b)).withColumn("blocks", F.ceil(size / b)).withColumn("words", F.when(size > 0, words).otherwise(0))
        rest = F.when(size > 0, F.col("words") % size).otherwise(0)
        rows = rows.withColumn("rest", rest).withColumn("need", F.coalesce(F.floor(F.col("words") / F.nullif(size, F.lit(0))), F.lit(0)) * F.col("blocks") + F.ceil(F.col("rest") / b))
        slack = F.floor(F.col("need") * tolerance)
        last = F.when(F.col("rest") > 0, F.col("rest") - b * (F.ceil(F.col("rest") / b) - 1))
        ends = F.sum("need").over(W.orderBy("sid"))
        rows = rows.withColumn("least", F.col("need") - slack).withColumn("most", F.least(F.col("need") + slack, repeats * F.col("blocks")))
        rows = rows.withColumn("last", last).withColumn("high", ends).withColumn("low", F.col("high") - F.col("need"))
        return rows.select("sid", "source", "source_size", "target", "full", "blocks", "need", "least", "most", "last", "low", "high")

    def _placed(self, sized: DataFrame) -> DataFrame:
        """Each document with its source's number and its first word's offset in the source's stream."""
        source = self._small(self.sources.select("sid", F.col("source").alias("_source"), "source_size", "target"))
        rows = sized.join(source, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
        rows = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "tie"), F.lit(self.salts)))
        parts = rows.groupBy("sid", "salt").agg(F.sum("size").alias("part"))
        ahead = W.partitionBy("sid").orderBy("salt").rowsBetween(W.unboundedPreceding, -1)
        parts = parts.select("sid", "salt", F.coalesce(F.sum("part").over(ahead), F.lit(0)).alias("base"))
        inside = W.partitionBy("sid", "salt").orderBy("doc_id", "tie").rowsBetween(W.unboundedPreceding, -1)
        rows = rows.withColumn("ahead", F.coalesce(F.sum("size").over(inside), F.lit(0)))
        placed = rows.join(parts, ["sid", "salt"]).withColumn("first", F.col("base") + F.col("ahead"))
        return stage(placed.select("doc_id", "tie", "sid", "size", "source_size", "target", "first"), "mix-placed")

    def _within(self, rows: DataFrame, at: str, n: int, ranges: DataFrame) -> DataFrame:
        """``rows`` joined to the interval of ``ranges(low, high, ...)`` over 0 .. n-1 that holds column ``at``."""
        width = max(1, -(-n // CELLS))
        cells = F.explode(F.sequence(F.floor(F.col("low") / width), F.floor((F.col("high") - 1) / width))).alias("cell")
        celled = self._small(ranges.where("low < high").select("*", cells))
        return rows.withColumn("cell", F.floor(F.col(at) / width)).join(celled, "cell").where(f"{at} >= low AND {at} < high").drop("cell", "low", "high")

    def _drawn(self) -> DataFrame:
        """(shard, slot, sid, rank): the source each slot draws, and its number among the shard's slots of that source."""
        place = F.pmod(F.xxhash64(F.lit(self.seed).cast("long"), "shard", "slot"), F.lit(max(1, self.n_slots)).cast("long"))
        slots = self.spark.range(self.n_slots).select(F.floor(F.col("id") / self.shard_slots).alias("shard"), (F.col("id") % self.shard_slots).alias("slot"))
        drawn = self._within(slots.withColumn("place", place), "place", self.n_slots, self.sources.select("sid", "low", "high"))
        # Permutations make slots dear, so there are many files of them however few bytes they have.
        drawn = drawn.repartition(max(4 * self.spark.sparkContext.defaultParallelism, self.n_slots // SLOTS_PER_FILE), "shard")
        rank = F.row_number().over(W.partitionBy("shard", "sid").orderBy("slot")) - 1
        return stage(drawn.select("shard", "slot", "sid", rank.cast("long").alias("rank")), "mix-drawn")

    def shard_counts(self) -> DataFrame:
        """(shard, sid, n): the multinomial draw of each shard."""
        return self.drawn.groupBy("shard", "sid").agg(F.count("*").alias("n"))

    def _totals(self) -> DataFrame:
        """Sources with the draws they got, those they keep, the number of the first one given away, and what they lack."""
        got = self.drawn.groupBy("sid").agg(F.count("*").alias("got"))
        rows = self.sources.join(got, "sid", "left").withColumn("got", F.coalesce("got", F.lit(0)))
        rows = rows.withColumn("kept", F.least("got", "most")).withColumn("over", F.col("got") - F.col("kept"))
        rows = rows.withColumn("lacks", F.greatest(F.lit(0), F.col("least") - F.col("got"))).withColumn("room", F.greatest(F.lit(0), F.col("need") - F.greatest("got", "least")))
        every, whole = W.orderBy("sid"), W.partitionBy(F.lit(1))
        rows = rows.withColumn("given", F.sum("over").over(every) - F.col("over")).withColumn("all_over", F.sum("over").over(whole)).withColumn("all_lack", F.sum("lacks").over(whole))
        # What is short by more than the tolerance comes first; the rest of what is given away tops up those below their need.
        rows = rows.withColumn("lack_low", F.sum("lacks").over(every) - F.col("lacks")).withColumn("room_low", F.col("all_lack") + F.sum("room").over(every) - F.col("room"))
        fills = F.greatest(F.col("all_over"), F.col("all_lack"))
        topped = F.least("room", F.greatest(F.lit(0), fills - F.col("room_low")))
        return stage(rows.withColumn("fills", fills).withColumn("draws", F.col("kept") + F.col("lacks") + topped), "mix-totals")

    def numbered(self) -> DataFrame:
        """(shard, slot, sid, i): every slot's source after the correction, and its number among that source's draws."""
        group = F.floor(F.col("shard") / SHARDS_PER_GROUP)
        counts = self.shard_counts().withColumn("group", group)
        ahead = lambda keys, by: F.coalesce(F.sum("n").over(W.partitionBy(*keys).orderBy(by).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
        groups = counts.groupBy("sid", "group").agg(F.sum("n").alias("n")).withColumn("base", ahead(["sid"], "group")).select("sid", "group", "base")
        offsets = counts.withColumn("ahead", ahead(["sid", "group"], "shard")).join(groups, ["sid", "group"]).select("sid", "shard", (F.col("base") + F.col("ahead")).alias("offset"))
        own = self.drawn.join(offsets, ["sid", "shard"]).withColumn("i", F.col("offset") + F.col("rank"))
        own = own.join(self._small(self.totals.select("sid", "kept", "given")), "sid")
        keeps = own.where("i < kept").select("shard", "slot", "sid", "i")
        n = self.totals.agg(F.coalesce(F.max("fills"), F.lit(0)), F.coalesce(F.max("all_over"), F.lit(0))).first()
        if not n[0]:
            return keeps
        moved = own.where("i >= kept").select("shard", "slot", (F.col("given") + F.col("i") - F.col("kept")).alias("fill"))
        at = F.col("id") + self.n_slots
        added = self.spark.range(n[0] - n[1]).select(F.floor(at / self.shard_slots).alias("shard"), (at % self.shard_slots).alias("slot"), (F.col("id") + n[1]).alias("fill"))
        lacks = self.totals.select("sid", F.col("kept").alias("start"), F.col("lack_low").alias("low"), (F.col("lack_low") + F.col("lacks")).alias("high"))
        rooms = self.totals.select("sid", (F.col("kept") + F.col("lacks")).alias("start"), F.col("room_low").alias("low"), (F.col("room_low") + F.col("room")).alias("high"))
        demand = lacks.unionByName(rooms).withColumn("from", F.col("low"))
        filled = self._within(moved.unionByName(added), "fill", n[0], demand)
        return keeps.unionByName(filled.select("shard", "slot", "sid", (F.col("start") + F.col("fill") - F.col("from")).alias("i")))

    def slots(self) -> DataFrame:
        """(shard, slot, sid, pass, block, cut): what each slot holds; of a cut block only so many words."""
        about = self._small(self.totals.select("sid", "full", "blocks", "need", "draws", "last"))
        rows = self.numbered().join(about, "sid")
        cut = F.when((F.col("i") == F.col("need") - 1) & (F.col("draws") == F.col("need")), F.col("last"))
        rows = rows.select("shard", "slot", "sid", "full", cut.alias("cut"), F.floor(F.col("i") / F.col("blocks")).alias("pass"), (F.col("i") % F.col("blocks")).alias("at"))
        block = F.when(F.col("at") < F.col("full"), permuted("at", "greatest(full, 1L)", f"{self.seed}L, sid, pass")).otherwise(F.col("at"))
        return rows.select("shard", "slot", "sid", "pass", block.alias("block"), "cut")

    def pieces(self) -> DataFrame:
        """Each document's overlap with each block of its source: words start .. stop of the document, from word ``skip`` of the block."""
        size, b = F.col("size"), self.block_words
        rows = self.placed.where("size > 0").select(
            "*", F.explode(F.sequence(F.floor(F.col("first") / b), F.floor((F.col("first") + size - 1) / b))).alias("block")
        )
        start = F.greatest(F.lit(0), F.col("block") * b - F.col("first"))
        stop = F.least(size, (F.col("block") + 1) * b - F.col("first"))
        return rows.select(*self.placed.columns, "block", start.alias("start"), stop.alias("stop"), (F.col("first") + start - F.col("block") * b).alias("skip"))

    def taken(self) -> DataFrame:
        """Every document with its words that the mixture takes, the draws that take them, and the first and last output shard."""
        uses = self.slots().groupBy("sid", "block").agg(
            F.count_if(F.col("cut").isNull()).alias("times"), F.max("cut").alias("cut"), F.count("*").alias("hits"), F.min("shard").alias("low"), F.max("shard").alias("high")
        )
        own = ["doc_id", "tie", "sid", "first", "size", "source_size", "target"]
        length, zero = F.col("stop") - F.col("start"), F.lit(0).cast("long")
        words = F.coalesce(F.col("times"), zero) * length + F.greatest(zero, F.least(length, F.coalesce(F.col("cut"), zero) - F.col("skip")))
        some = self.pieces().join(uses, ["sid", "block"], "left").groupBy(*own).agg(
            F.sum(words).alias("taken"), F.coalesce(F.sum("hits"), zero).alias("draws"), F.min("low").alias("first_shard"), F.max("high").alias("last_shard")
        )
        none = self.placed.where("size = 0").select(*own, zero.alias("taken"), zero.alias("draws"), F.lit(None).cast("long").alias("first_shard"), F.lit(None).cast("long").alias("last_shard"))
        return some.unionByName(none)


def mix_documents(docs: DataFrame, block_words: int = BLOCK_WORDS, seed: int = SEED, shard_column: str | None = None) -> DataFrame:
    """The mixture as rows with all columns of ``docs``: one for each document and pass that takes any of it.

    A pass that takes every word of a document keeps its text as it is; one that
    takes some blocks keeps those words, joined by single spaces. n_chars is
    renewed. ``shard_column`` names a further column with the first output shard
    that holds words of the row.
    """
    plan = Plan(docs, block_words, seed)
    hits = plan.pieces().join(plan.slots().select("sid", "shard", "pass", "block", "cut"), ["sid", "block"])
    stop = F.least("stop", F.col("start") + F.coalesce(F.col("cut"), F.lit(block_words)) - F.col("skip"))
    hits = hits.withColumn("stop", stop).where("stop > start")
    passes = hits.groupBy("doc_id", "tie", "sid", "first", "pass", "size").agg(
        F.sum(F.col("stop") - F.col("start")).alias("words"), F.min("shard").alias("shard"), F.array_sort(F.collect_list(F.struct("start", "stop"))).alias("parts")
    )
    passes = passes.withColumn("parts", F.when(F.col("words") < F.col("size"), F.col("parts")))
    # Rows equal in every column have their passes in one list, so one of them stands for all.
    lists = passes.groupBy("doc_id", "tie").agg(F.array_sort(F.collect_list(F.struct("pass", "first", "shard", "parts"))).alias("uses"))
    lists = lists.select(F.col("doc_id").alias("use_id"), F.col("tie").alias("use_tie"), "uses")
    texts = docs.select(packed(docs), F.col("doc_id").cast("long").alias("key"), row_hash(docs).alias("hash")).dropDuplicates(["key", "hash"])
    each = texts.join(lists, F.col("key").eqNullSafe(F.col("use_id")) & (F.col("hash") == F.col("use_tie"))).select("row", F.explode("uses").alias("use"))
    text = F.col("row").getField("text").cast("string")
    each = each.select("row", text.alias("text"), F.col("use.parts").alias("parts"), F.col("use.shard").alias("shard"))
    words = f"filter(split(text, '{SPACE}'), w -> w <> '')".replace("\\", "\\\\")
    cut = F.expr(f"transform(array({words}), ws -> array_join(flatten(transform(parts, p -> slice(ws, cast(p.start + 1 AS int), cast(p.stop - p.start AS int)))), ' '))[0]")
    out = each.withColumn("text", F.when(F.col("parts").isNotNull(), cut).otherwise(F.col("text")))
    renewed = {"text": F.col("text"), "n_chars": F.length("text").cast("long")}
    return out.select(*unpacked(out, docs.columns, renewed), *([F.col("shard").alias(shard_column)] if shard_column else []))


def op7_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: doc_id, size, source_size, target, taken; with the draws and the output shards that hold them."""
    return Plan(table(spark, sf_dir, "documents")).taken().select("doc_id", "size", "source_size", "target", "taken", "draws", "first_shard", "last_shard")
