"""Rows of a matrix packed into blocks, so that a pass costs no work for single rows outside numpy.

A block is one binary cell that holds the columns of some thousand rows, each in the
narrowest number type that gives back every value: indicators take one octet a row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallquant.functions.loss import batch_matrix

SCHEMA = "part int, seq int, n int, {} binary"
_TYPES = ("<i1", "<i2", "<f4", "<f8")


def encode(m: np.ndarray) -> bytes:
    codes, cells = np.zeros(m.shape[1], dtype=np.uint8), []
    for j, column in enumerate(m.T):
        for k, t in enumerate(_TYPES):
            with np.errstate(invalid="ignore", over="ignore"):
                short = column.astype(t)
            if k == len(_TYPES) - 1 or np.array_equal(short, column):
                break
        codes[j] = k
        cells.append(short.tobytes())
    return b"".join([np.array(m.shape, dtype="<i4").tobytes(), codes.tobytes(), *cells])


def decode(block: bytes | memoryview) -> np.ndarray:
    n, d = np.frombuffer(block, "<i4", 2)
    out, at = np.empty((n, d), order="F"), 8 + int(d)
    for j, k in enumerate(np.frombuffer(block, np.uint8, d, 8)):
        column = np.frombuffer(block, _TYPES[k], n, at)
        out[:, j] = column
        at += column.nbytes
    return out


def is_packed(frame: DataFrame, column: str) -> bool:
    return frame.schema[column].dataType.typeName() == "binary"


def matrices(column: pa.Array) -> Iterator[np.ndarray]:
    """The matrices of a batch: one for each block, or one of all rows of a list column."""
    if pa.types.is_list(column.type) or pa.types.is_large_list(column.type):
        if len(column):
            yield batch_matrix(column)
        return
    for cell in column:
        yield decode(cell.as_buffer())


def written(rows: DataFrame, name: str) -> DataFrame:
    """Blocks as Parquet in the shared folder, in small row groups: a reader holds one at a time.

    Blocks of fewer tasks than there are cores (a table of one file is one task's) are dealt evenly, so that passes use all cores.
    """
    frame = _saved(rows, name)
    parts, held = frame.agg(F.countDistinct("part"), F.count("*")).first()
    most = min(held, rows.sparkSession.sparkContext.defaultParallelism)
    if parts >= most:
        return frame
    even = _saved(frame.repartition(most), name)
    forget(frame)
    return even


def _saved(rows: DataFrame, name: str) -> DataFrame:
    from tallquant.sources.storage import scratch

    path = scratch(rows.sparkSession, "blocks")
    rows.write.option("parquet.block.size", 16 << 20).parquet(path)
    return rows.sparkSession.read.schema(SCHEMA.format(name)).parquet(path)


def pack(rows: DataFrame, name: str) -> DataFrame:
    """Blocks ``part, seq, n, <name>`` of the rows, whose columns are numbers and lists of numbers, side by side in that order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        for seq, batch in enumerate(batches):
            if len(batch):
                m = np.column_stack([batch_matrix(c) if pa.types.is_nested(c.type) else c.to_numpy(zero_copy_only=False) for c in batch.columns])
                yield one(part, seq, m, name)

    return written(rows.mapInArrow(run, SCHEMA.format(name)), name)


def one(part: int, seq: int, m: np.ndarray, name: str) -> pa.RecordBatch:
    cells = [pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([len(m)], pa.int32()), pa.array([encode(m)], pa.binary())]
    return pa.RecordBatch.from_arrays(cells, names=["part", "seq", "n", name])


def mapped(blocks: DataFrame, name: str, change) -> DataFrame:
    """Blocks of what ``change`` makes of each block's matrix; those without rows go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, seq, cell in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                m = change(decode(cell.as_buffer()))
                if len(m):
                    yield one(part, seq, m, name)

    return blocks.select("part", "seq", name).mapInArrow(run, SCHEMA.format(name))


def rewritten(blocks: DataFrame, name: str, change) -> DataFrame:
    return written(mapped(blocks, name, change), name)


def gathered(blocks: DataFrame, name: str) -> np.ndarray:
    """All rows on the driver, in their order; callers bound them."""
    table = blocks.select("part", "seq", name).toArrow().sort_by([("part", "ascending"), ("seq", "ascending")])
    found = [decode(cell.as_buffer()) for cell in table.column(2)]
    return np.vstack(found) if found else np.zeros((0, 0))


def height(blocks: DataFrame) -> int:
    return blocks.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long")).first()[0]


def width(blocks: DataFrame, name: str) -> int:
    row = blocks.select(name).first()
    return int(np.frombuffer(row[0], "<i4", 2)[1]) if row else 0


def forget(blocks: DataFrame) -> None:
    """Delete blocks that no later step reads."""
    from tallquant.sources.storage import discard

    files = blocks.inputFiles()
    if files:
        discard(blocks.sparkSession, files[0].rsplit("/", 1)[0])
