"""Token counts kept by signed deltas.

Totals by source, language and tokenizer version are additive, so a change is a
signed row: an insert adds a document's count, a delete takes it away, and a
revision does both with the old and the new count. A batch of changes is summed
before it is stored (partial sums first, so a hot source costs no more than
others) and is committed under its batch id by renaming a finished folder, a rename that fails
if the id is there. So replays after a failure, or of a stream's micro-batch,
change nothing. Compaction folds the batches of one listing into a snapshot that
remembers their ids; what is committed meanwhile stays beside it, and a batch
that a late writer commits once more is known by its id and not counted.

Defined cases: a null text has no tokens but counts as a document; null sources
and languages are groups of their own; repeated rows count each; totals without
documents and tokens are left out; extra columns are ignored; an empty batch
commits and adds nothing; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import re
import uuid
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.plans.session import path_exists, ship_package, stage, staging_path
from annspark.plans.skew import join_hot_apart
from annspark.sources.tables import table

KEYS = ("source", "lang", "tokenizer_version")
DELTA = "source string, lang string, tokenizer_version string, n_docs long, n_tokens long"
WORDS, TERMS, BYTE_BPE = "words-1", "words-2", "byte_bpe_50k-1"
_SPACED = re.compile(r"[^\x20\x09-\x0D]+")
_TERM = re.compile(r"\w+")
RANKS = "byte_bpe_50k.tiktoken"


@lru_cache(maxsize=2)
def _byte_bpe(path: str):
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    return tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def default_ranks_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(RANKS)


def count_tokens(docs: DataFrame, versions: tuple[str, ...] = (WORDS, TERMS, BYTE_BPE), ranks_path: str | None = None) -> DataFrame:
    """doc_id, source, lang, text_hash and a count column for each tokenizer version, of every whole text."""
    ship_package(docs.sparkSession)
    path = ranks_path or (default_ranks_path() if BYTE_BPE in versions else "")
    ways = {
        WORDS: lambda t: sum(1 for _ in _SPACED.finditer(t)),
        TERMS: lambda t: sum(1 for _ in _TERM.finditer(t)),
        BYTE_BPE: lambda t: len(_byte_bpe(path).encode_ordinary(t)),
    }

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [t.as_py() or "" for t in batch.column(4)]
            counts = [pa.array([ways[v](t) for t in texts], pa.int64()) for v in versions]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], *counts], ["doc_id", "source", "lang", "text_hash", *versions])

    text = F.col("text").cast("string")
    frame = docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), F.col("lang").cast("string"), F.sha2(text, 256).alias("text_hash"), text.alias("text"))
    return frame.mapInArrow(run, "doc_id long, source string, lang string, text_hash string, " + ", ".join(f"`{v}` long" for v in versions))


def changes(counted: DataFrame, version: str, sign: int) -> DataFrame:
    """Signed rows for one tokenizer version: ``sign`` is 1 for inserts and -1 for deletes."""
    return counted.select(
        "source", "lang", F.lit(version).alias("tokenizer_version"), F.lit(sign).cast("long").alias("n_docs"), (F.col(f"`{version}`") * sign).alias("n_tokens")
    )


def revisions(old: DataFrame, old_version: str, new: DataFrame, new_version: str) -> DataFrame:
    """Signed rows that replace the counts of ``old`` by those of ``new``."""
    return changes(old, old_version, -1).unionByName(changes(new, new_version, 1))


class TokenRollup:
    """Totals in one folder of the shared store."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _fs(self):
        jvm = self.spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(self.path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), jvm.org.apache.hadoop.fs.Path

    def _listing(self) -> tuple[str | None, list[str]]:
        """(snapshot, batches): folder names of one listing; a snapshot counts when its id list is complete."""
        fs, path = self._fs()
        if not fs.exists(path(self.path)):
            return None, []
        names = sorted(s.getPath().getName() for s in fs.listStatus(path(self.path)))
        done = [n for n in names if n.startswith("snapshot-") and path_exists(self.spark, f"{self.path}/{n}/batches/_SUCCESS")]
        return (done[-1] if done else None), [n for n in names if n.startswith("batch-")]

    def _folded(self, snapshot: str | None) -> set[str]:
        """Ids of the batches in the snapshot: one short string each."""
        return {r.batch for r in self.spark.read.schema("batch string").parquet(f"{self.path}/{snapshot}/batches").collect()} if snapshot else set()

    def _rename(self, old: str, new: str) -> bool:
        """Rename a folder; False if ``new`` exists. The file system decides, so of two writers one wins."""
        sc = self.spark.sparkContext
        fs = sc._jvm.org.apache.hadoop.fs
        context = fs.FileContext.getFileContext(fs.Path(new).toUri(), sc._jsc.hadoopConfiguration()) if "://" in new else fs.FileContext.getFileContext(sc._jsc.hadoopConfiguration())
        none = sc._gateway.new_array(getattr(fs, "Options$Rename"), 0)
        try:
            context.rename(fs.Path(old), fs.Path(new), none)
        except Py4JJavaError as e:
            if "FileAlreadyExistsException" in str(e.java_exception.getClass().getName()):
                return False
            raise
        return True

    def committed(self) -> set[str]:
        snapshot, live = self._listing()
        return {n.removeprefix("batch-") for n in live} | self._folded(snapshot)

    def commit(self, batch_id: str, signed: DataFrame) -> bool:
        """Add a batch of signed rows once; False if the id was there before."""
        if not re.fullmatch(r"[A-Za-z0-9_.-]+", batch_id):
            raise ValueError("a batch id has letters, digits, dots, dashes and underscores")
        if batch_id in self.committed():
            return False
        attempt = f"{self.path}/attempt-{uuid.uuid4().hex}"
        summed = signed.groupBy(*KEYS).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        summed.where("n_docs <> 0 OR n_tokens <> 0").write.parquet(attempt)
        if self._rename(attempt, f"{self.path}/batch-{batch_id}"):
            return True
        fs, path = self._fs()
        fs.delete(path(attempt), True)
        return False

    def _totals(self, snapshot: str | None, live: list[str], folded: set[str]) -> DataFrame:
        names = [*([f"{snapshot}/totals"] if snapshot else []), *(n for n in live if n.removeprefix("batch-") not in folded)]
        rows = self.spark.read.schema(DELTA).parquet(*[f"{self.path}/{n}" for n in names]) if names else self.spark.createDataFrame([], DELTA)
        out = rows.groupBy(*KEYS).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        return out.where("n_docs <> 0 OR n_tokens <> 0")

    def totals(self) -> DataFrame:
        """Additive totals over everything committed."""
        snapshot, live = self._listing()
        return self._totals(snapshot, live, self._folded(snapshot))

    def compact(self) -> None:
        """Fold the committed batches of one listing into a new snapshot; the old files go only when it is complete."""
        old, live = self._listing()
        folded = self._folded(old)
        name = f"{self.path}/snapshot-{(int(old.removeprefix('snapshot-')) if old else 0) + 1:09d}"
        self._totals(old, live, folded).write.mode("overwrite").parquet(f"{name}/totals")
        ids = sorted(folded | {n.removeprefix("batch-") for n in live})
        self.spark.createDataFrame([(i,) for i in ids], "batch string").coalesce(1).write.mode("overwrite").parquet(f"{name}/batches")
        fs, path = self._fs()
        for n in [*live, *([old] if old else [])]:
            fs.delete(path(f"{self.path}/{n}"), True)

    def stream_sink(self, prefix: str):
        """A foreachBatch function that commits each micro-batch of signed rows under its epoch."""
        return lambda rows, epoch: self.commit(f"{prefix}-{epoch}", rows)


def exact_copies(counted: DataFrame) -> DataFrame:
    """Rows of ``counted`` whose text also stands under a smaller doc_id."""
    first = counted.where("text_hash IS NOT NULL").groupBy("text_hash").agg(F.min("doc_id").alias("_first"), F.count("*").alias("_n")).where("_n > 1")
    both = join_hot_apart(counted, stage(first, "token-firsts"), "text_hash", "_n")
    return both.where(F.col("doc_id") > F.col("_first")).select(*counted.columns)


def rollup_documents(spark: SparkSession, sf_dir: str, versions: tuple[str, ...]) -> DataFrame:
    """Load all documents, take exact copies away, move `words` to its next version if counted, and replay the load."""
    counted = stage(count_tokens(table(spark, sf_dir, "documents"), versions), "token-counts")
    rollup = TokenRollup(spark, staging_path(spark, "token-rollup"))
    first = [v for v in versions if v != TERMS]

    def all_of(rows: DataFrame, sign: int, names: list[str]) -> DataFrame:
        out = changes(rows, names[0], sign)
        for v in names[1:]:
            out = out.unionByName(changes(rows, v, sign))
        return out

    rollup.commit("load", all_of(counted, 1, first))
    copies = stage(exact_copies(counted), "token-copies")
    rollup.commit("drop-copies", all_of(copies, -1, first))
    if TERMS in versions:
        rollup.commit("revise-words", revisions(counted, WORDS, counted, TERMS).unionByName(revisions(copies, TERMS, copies, WORDS)))
    rollup.commit("load", all_of(counted, 1, first))
    return rollup.totals()


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """source, lang, tokenizer_version, n_docs, n_tokens after inserts, deletes, a revision and a replay."""
    return rollup_documents(spark, sf_dir, (WORDS, TERMS, BYTE_BPE))


def token_rollup_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same rollup for white-space words alone, which SQL can count too."""
    return rollup_documents(spark, sf_dir, (WORDS,))


ORACLE_WORDS = r"""
WITH d AS (
    SELECT source, lang, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS n,
           doc_id, min(doc_id) OVER (PARTITION BY text) AS low, text
    FROM documents
)
SELECT source, lang, 'words-1' AS tokenizer_version, count(*) AS n_docs, CAST(sum(n) AS BIGINT) AS n_tokens
FROM d WHERE text IS NULL OR doc_id IS NULL OR doc_id = low GROUP BY source, lang
"""
