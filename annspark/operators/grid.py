"""All queries against all rows, as a grid of query blocks and row shards.

Both sides fall into parts by a hash of the id. Each cell of the grid is one
group of rows: a block's queries first, then a shard's rows, which stream past
them in Arrow batches. So a task holds one block and one batch, whatever the
table's size, nothing passes the driver, and a lost task is redone from shuffled
rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

QUERY_BLOCK = 8192
#: Rows of a shard, at most about so many; there are at least SPREAD cells for each core.
SHARD_ROWS = 262_144
SPREAD = 3

Part = tuple[pa.Array, pa.Array]


def grid(queries: DataFrame, rows: DataFrame, query_block: int | None = None, shard_rows: int | None = None) -> DataFrame:
    """(block, shard, side, id, vec), sorted: of each cell first the queries (side 0), then the rows.

    Both inputs have an id and a vector as their first two columns.
    """
    blocks = max(1, -(-queries.count() // (query_block or QUERY_BLOCK)))
    cores = rows.sparkSession.sparkContext.defaultParallelism
    shards = max(-(-rows.count() // (shard_rows or SHARD_ROWS)), -(-SPREAD * cores // blocks))

    def side(df: DataFrame, number: int) -> DataFrame:
        one = df.select(F.col(df.columns[0]).cast("long").alias("id"), F.col(df.columns[1]).cast("array<double>").alias("vec"))
        part = lambda n: F.pmod(F.xxhash64("id", F.lit(number)), F.lit(n)).cast("int")
        every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
        keys = (part(blocks).alias("block"), every(shards).alias("shard")) if number == 0 else (every(blocks).alias("block"), part(shards).alias("shard"))
        return one.select(*keys, F.lit(number).alias("side"), "id", "vec")

    return side(queries, 0).unionByName(side(rows, 1)).repartition(blocks * shards, "block", "shard").sortWithinPartitions("block", "shard", "side")


def walk(
    batches: Iterator[pa.RecordBatch], open_cell: Callable[[list[Part]], Any], visit: Callable[[Any, pa.Array, pa.Array], Iterator[pa.RecordBatch]],
    close: Callable[[Any], Iterator[pa.RecordBatch]] = lambda state: iter(()),
) -> Iterator[pa.RecordBatch]:
    """Go through the cells of a grid's partition.

    ``open_cell`` makes a state of a block's queries, ``visit`` shows it a batch
    of rows, and ``close`` ends the cell. Cells without rows are skipped.
    """
    now, held, state = None, [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        cell = np.stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(3)])
        cuts = [0, *(np.flatnonzero((cell[:, 1:] != cell[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
        for s, e in zip(cuts, cuts[1:]):
            block, shard, side = cell[:, s].tolist()
            if (block, shard) != now:
                if state is not None:
                    yield from close(state)
                now, held, state = (block, shard), [], None
            part = batch.slice(s, e - s)
            if side == 0:
                held.append((part.column(3), part.column(4)))
            elif held:
                if state is None:
                    state = open_cell(held)
                yield from visit(state, part.column(3), part.column(4))
    if state is not None:
        yield from close(state)
