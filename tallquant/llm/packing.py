"""Bounded-space online packing of documents into sequences of one width.

Every partition keeps a fixed number of open windows.  What exceeds whole
windows of a document goes to the open window that it fits most closely; when
none fits, the fullest is emitted (its gap filled by a cut if the gap is wide)
and a new one opened.  Windows still open at the end of a partition are merged in
rounds, a bounded number of partitions at a time, each round again with a fixed
number of windows left open, until one group remains.

Null and empty texts become the end token alone; null or repeated identifiers
are packed like others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.llm.common import Workspace, as_bytes, default_tokenizer, text_slices, word_encoder

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, window long, offset long, closed boolean, part int"
_KINDS = [pa.int64()] * 7 + [pa.bool_(), pa.int32()]
_NAMES = [f.split()[0] for f in PIECES.split(", ")]


class OpenWindows:
    """A fixed number of open windows; ``place`` yields the pieces of windows that close."""

    def __init__(self, width: int, most: int, least_cut: int, first: int):
        self.width, self.most, self.least_cut, self.next = width, most, least_cut, first
        self.open: dict[int, tuple[int, list[tuple]]] = {}  # window: free, pieces

    def _new(self) -> int:
        self.next += 1
        return self.next - 1

    def _put(self, window: int, doc: tuple, ids: np.ndarray, start: int, length: int) -> None:
        free, pieces = self.open.setdefault(window, (self.width, []))
        pieces.append((doc[0], start, length, zlib.crc32(ids[start : start + length]), doc[1], window, self.width - free))
        self.open[window] = free - length, pieces

    def place(self, doc_id: int | None, ids: np.ndarray) -> Iterator[tuple]:
        n, doc = len(ids), (doc_id, len(ids))
        whole = n - n % self.width
        for start in range(0, whole, self.width):
            yield doc_id, start, self.width, zlib.crc32(ids[start : start + self.width]), n, self._new(), 0
        start, rest = whole, n - whole
        if not rest:
            return
        fits = [(free, w) for w, (free, _) in self.open.items() if free >= rest]
        if fits:
            free, window = min(fits)
            self._put(window, doc, ids, start, rest)
            if free == rest:
                yield from self.open.pop(window)[1]
            return
        if len(self.open) >= self.most:
            free, window = min((free, w) for w, (free, _) in self.open.items())
            if free >= self.least_cut and rest - free >= self.least_cut:
                self._put(window, doc, ids, start, free)
                start, rest = start + free, rest - free
            yield from self.open.pop(window)[1]
        self._put(self._new(), doc, ids, start, rest)


def merge_windows(keys: list[int], used: list[int], width: int, keep: int) -> tuple[list[int], list[int], set[int]]:
    """Best-fit of whole windows, longest first: the window each goes to, its shift there, and those that stay open."""
    into, shift, free = {}, {}, {}
    for k, n in sorted(zip(keys, used, strict=True), key=lambda x: (-x[1], x[0])):
        fits = [(f, w) for w, f in free.items() if f >= n]
        w = min(fits)[1] if fits else k
        into[k], shift[k] = w, width - free.get(w, width)
        free[w] = free.get(w, width) - n
    left = sorted(free, key=lambda w: (-free[w], w))[:keep]
    return [into[k] for k in keys], [shift[k] for k in keys], set(left)


def _merger(width: int, keep: int):
    def merge(rows: pd.DataFrame) -> pd.DataFrame:
        into, shift, left = merge_windows(rows.root.tolist(), rows.used.tolist(), width, keep)
        out = pd.DataFrame({"root": rows.root, "into": into, "by": shift, "grp": rows.grp})
        out["used"] = rows.used.groupby(pd.Series(into, index=rows.index)).transform("sum")
        out["open"] = [w in left for w in into]
        return out

    return merge


def pack(
    spark: SparkSession,
    docs: DataFrame,
    *,
    tokenizer: str | None = None,
    end_id: int = 1,
    width: int = 2048,
    open_windows: int = 32,
    least_cut: int = 32,
    fan_in: int = 64,
    cached: int = 700_000,
) -> DataFrame:
    """One row for each piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``.

    A worker keeps the ids of ``cached`` chunks (some 200 octets each).
    """
    tokenizer, work = tokenizer or default_tokenizer(), Workspace(spark, "packing")

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, part = word_encoder(tokenizer, cached), TaskContext.get().partitionId()
        windows = OpenWindows(width, open_windows, least_cut, part << 36)

        def batch(rows: list[tuple], closed: bool) -> pa.RecordBatch:
            columns = [*(zip(*rows, strict=True) if rows else [[]] * 7), [closed] * len(rows), [part] * len(rows)]
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, _KINDS, strict=True)], names=_NAMES)

        for rows in batches:
            keys, texts = rows.column(0).to_pylist(), as_bytes(rows.column(1))
            for a, b in text_slices(texts):
                out: list[tuple] = []
                for key, ids in zip(keys[a:b], encoder.encode(texts[a:b]), strict=True):
                    out += windows.place(key, np.append(ids, np.uint32(end_id)).astype("<u4"))
                yield batch(out, True)
        yield batch([p for _, pieces in windows.open.values() for p in pieces], False)

    pieces = work.save(docs.select("doc_id", "text").mapInArrow(fill, PIECES), "pieces")
    left = pieces.where("not closed").groupBy("window", "part").agg(F.sum("length").alias("used"))
    members = work.save(left.select("window", F.col("window").alias("root"), F.lit(0).cast("long").alias("shift"), "used", F.col("part").alias("grp")), "members-0")
    roots, k = members.select(F.col("window").alias("root"), "used", "grp"), 0
    parts = (members.agg(F.max("grp")).first()[0] or 0) + 1
    while True:
        keep = open_windows if parts > fan_in else 0
        grouped = roots.withColumn("grp", F.expr(f"cast(grp div {fan_in} as int)")).groupBy("grp")
        moved = work.save(grouped.applyInPandas(_merger(width, keep), "root long, into long, by long, grp int, used long, open boolean"), f"moved-{k}")
        k += 1
        step = moved.select("root", "into", "by")
        members = work.save(
            members.join(step, "root", "left").select("window", F.coalesce("into", "root").alias("root"), (F.col("shift") + F.coalesce("by", F.lit(0))).alias("shift")),
            f"members-{k}",
        )
        if parts <= fan_in:
            break
        roots, parts = moved.where("open and root = into").select("root", "used", "grp"), -(-parts // fan_in)
    ends = pieces.where("not closed").join(members, "window").withColumns({"window": F.col("root"), "offset": F.col("offset") + F.col("shift")})
    columns = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", F.col("window").alias("sequence_id"), "offset"]
    return pieces.where("closed").select(*columns).union(ends.select(*columns))


def padding(packed: DataFrame, width: int = 2048) -> DataFrame:
    """Sequences, tokens and the share of padding (a sequence of a power of two is not padded)."""
    sequences = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    power = F.expr("n & (n - 1)") == 0
    return sequences.agg(
        F.count("*").alias("n_sequences"), F.sum("n").alias("n_tokens"), F.sum(F.when(power, 0).otherwise(width - F.col("n"))).alias("n_padding")
    ).withColumn("padding_share", F.col("n_padding") / (F.col("n_padding") + F.col("n_tokens")))
