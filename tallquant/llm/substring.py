"""Substring dedup by difference-cover anchors.

A window of ``width`` consecutive words is removed if its word sequence also
starts in a document with a smaller identifier.  Hashing every window is wasteful,
so only windows of ``width - period + 1`` words at positions whose remainder lies
in a difference cover modulo ``period`` are hashed: for any two positions some
shift below the period brings both into the cover, so two equal long windows
always share an aligned anchor.  Where an anchor occurs in more than one document,
the long windows around it (and no others) are hashed as a whole and decided by
the smallest identifier of each.

Rows travel as packed arrays, one for each map batch and hash range.  A batch sends
one row for each distinct hash at most, and tells its own documents directly what
they share among themselves, so a passage that a third of all documents hold
costs one row a batch, and no pairs are formed.

A null text has no words; a null identifier counts as larger than all others;
rows with equal identifiers do not remove from each other; a document that
repeats itself loses nothing; whole documents may be emptied.  Windows of equal
96-bit hashes count as equal.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallquant.llm.common import BLANK_WORD, Workspace, as_bytes, blank_words, relaxed, release, row_of, text_slices, unfold, window_hashes, word_hashes, worker_cache

# Perfect difference sets, period to remainders.
COVERS = {
    1: [0],
    3: [0, 1],
    7: [1, 2, 4],
    13: [0, 1, 3, 9],
    21: [3, 6, 7, 12, 14],
    31: [1, 5, 11, 24, 25, 27],
}
LAST_ID = np.iinfo(np.int64).max
PACKED = "dest long, done boolean, blob binary"
_NAMES, _KINDS = ["dest", "done", "blob"], [pa.int64(), pa.bool_(), pa.binary()]
_WORD = re.compile(BLANK_WORD)
_U8, _U4, _I8, _I4 = np.dtype("<u8"), np.dtype("<u4"), np.dtype("<i8"), np.dtype("<i4")


def choose_period(width: int) -> int:
    """The longest period whose anchors still have about half the window."""
    return max(p for p in COVERS if p == 1 or width - p + 1 >= min(7, width - 1))


def _pack(*arrays: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(b"".join([len(arrays[0]).to_bytes(8, "little"), *[a.tobytes() for a in arrays]]))


def _unpack(blobs: list[bytes], kinds: list[np.dtype]) -> list[np.ndarray]:
    parts: list[list[np.ndarray]] = [[] for _ in kinds]
    for blob in blobs:
        raw = zstandard.ZstdDecompressor().decompress(blob)
        n, at = int.from_bytes(raw[:8], "little"), 8
        for out, kind in zip(parts, kinds, strict=True):
            out.append(np.frombuffer(raw, kind, n, at))
            at += n * kind.itemsize
    return [np.concatenate(p) if p else np.empty(0, k) for p, k in zip(parts, kinds, strict=True)]


def _deal(dest: np.ndarray, *arrays: np.ndarray) -> Iterator[tuple[int, bytes]]:
    """The rows of each destination as one blob."""
    if not len(dest):
        return
    order = np.argsort(dest, kind="stable")
    dest, arrays = dest[order], [a[order] for a in arrays]
    starts = np.flatnonzero(np.concatenate(([True], dest[1:] != dest[:-1])))
    for a, b in zip(starts, np.append(starts[1:], len(dest)), strict=True):
        yield int(dest[a]), _pack(*[x[a:b] for x in arrays])


def _table(rows: list[tuple[int, bool, bytes]]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[], [], []]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, _KINDS, strict=True)], names=_NAMES)


def _groups(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Group number of each row of sorted keys, and where groups start."""
    fresh = np.ones(len(keys[0]), dtype=bool)
    fresh[1:] = False
    for k in keys:
        fresh[1:] |= k[1:] != k[:-1]
    return np.cumsum(fresh) - 1, np.flatnonzero(fresh)


def _ids(column: pa.Array) -> np.ndarray:
    return np.array([LAST_ID if x is None else x for x in column.to_pylist()], dtype=np.int64)


def _bucket(keys: np.ndarray, n: int) -> np.ndarray:
    return (keys.view(np.uint64) % np.uint64(n)).astype(np.int64)


def find_anchors(width: int, period: int, n_buckets: int):
    """Map side of the first pass: ``own key, doc_id, text`` to anchors and what is already known as shared."""
    cover = np.zeros(period, dtype=bool)
    cover[COVERS[period]] = True
    size = width - period + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        worker_cache("substring")
        for batch in batches:
            keys, ids, texts = batch.column(0).to_numpy(), _ids(batch.column(1)), as_bytes(batch.column(2))
            order = np.argsort(ids, kind="stable")
            keys, ids, texts = keys[order], ids[order], [texts[i] for i in order]
            for a, b in text_slices(texts, 4_000_000):
                words = [blank_words(t) for t in texts[a:b]]
                counts = np.array([len(w) for w in words])
                if counts.sum() < size:
                    continue
                hashes = window_hashes(word_hashes([w for ws in words for w in ws]), size)
                doc = np.repeat(np.arange(a, b), counts)[: len(hashes)]
                first = np.repeat(np.cumsum(counts) - counts, counts)[: len(hashes)]
                pos = np.arange(len(hashes)) - first
                good = cover[pos % period] & (pos + size <= counts[doc - a]) & (counts[doc - a] >= width)
                hashes, doc, pos = hashes[good], doc[good], pos[good].astype(_I4)
                if not len(hashes):
                    continue
                order = np.argsort(hashes, kind="stable")
                group, starts = _groups(hashes[order])
                ends = np.append(starts[1:], len(hashes)) - 1
                several = (doc[order[starts]] != doc[order[ends]])[group]
                shared, sent = np.zeros(len(hashes), dtype=bool), np.ones(len(hashes), dtype=bool)
                shared[order] = several
                # one place of what is shared here; every place of what one document holds, however often
                several[starts] = False
                sent[order] = ~several
                rows = [(d, True, x) for d, x in _deal(_bucket(keys[doc[shared]], n_buckets), keys[doc[shared]], pos[shared])]
                # in the order of the texts, where keys repeat and positions rise, so that blobs compress
                rows += [(d, False, x) for d, x in _deal(_bucket(hashes[sent], n_buckets), hashes[sent], keys[doc[sent]], pos[sent])]
                yield _table(rows)

    return run


def match_anchors(n_buckets: int):
    """Reduce side of the first pass: anchors that more than one document holds."""

    @relaxed
    def run(table: pa.Table) -> pa.Table:
        done, blobs, dests = table.column("done").to_pylist(), table.column("blob").to_pylist(), table.column("dest").to_pylist()
        rows = [(d, True, x) for d, ok, x in zip(dests, done, blobs, strict=True) if ok]
        hashes, keys, pos = _unpack([x for ok, x in zip(done, blobs, strict=True) if not ok], [_U8, _I8, _I4])
        if len(hashes):
            order = np.argsort(hashes, kind="stable")
            hashes, keys, pos = hashes[order], keys[order], pos[order]
            group, starts = _groups(hashes)
            low, high = np.minimum.reduceat(keys, starts), np.maximum.reduceat(keys, starts)
            shared = (low != high)[group]
            rows += [(d, True, x) for d, x in _deal(_bucket(keys[shared], n_buckets), keys[shared], pos[shared])]
        return pa.Table.from_batches([_table(rows)])

    return run


def _by_key(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    keys, pos = _unpack(table.column("blob").to_pylist(), [_I8, _I4])
    order = np.argsort(keys, kind="stable")
    return keys[order], pos[order]


def _covered(starts: np.ndarray, back: int, ahead: int, n: int) -> np.ndarray:
    """Mask of 0..n-1 within ``[s - back, s + ahead)`` of any start."""
    edge = np.zeros(n + 1, dtype=np.int64)
    np.add.at(edge, np.clip(starts - back, 0, n), 1)
    np.add.at(edge, np.clip(starts + ahead, 0, n), -1)
    return np.cumsum(edge)[:-1] > 0


def extend(width: int, period: int, n_buckets: int):
    """Second pass, with the texts: hash the long windows around shared anchors."""
    reach = period - 1  # window length less anchor length

    @relaxed
    def run(docs: pa.Table, shared: pa.Table) -> pa.Table:
        keys, pos = _by_key(shared)
        own, ids, texts = docs.column("key").to_numpy(), _ids(docs.column("doc_id").combine_chunks()), as_bytes(docs.column("text").combine_chunks())
        found: list[tuple[np.ndarray, ...]] = []
        for key, doc_id, text, a, b in zip(own, ids, texts, np.searchsorted(keys, own), np.searchsorted(keys, own, side="right"), strict=True):
            if a == b:
                continue
            h = word_hashes(blank_words(text))
            if len(h) < width:
                continue
            at = np.flatnonzero(_covered(pos[a:b].astype(np.int64), reach, 1, len(h) - width + 1)).astype(_I4)
            one, two = window_hashes(h, width, 1)[at], window_hashes(h, width, 2)[at].astype(_U4)
            found.append((one, two, np.full(len(at), doc_id, _I8), np.full(len(at), key, _I8), at))
        if not found:
            return pa.Table.from_batches([_table([])])
        one, two, doc, key, at = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.lexsort((doc, two, one))
        group, starts = _groups(one[order], two[order])
        later = np.zeros(len(one), dtype=bool)
        later[order] = doc[order] > doc[order[starts]][group]
        rows = [(d, True, x) for d, x in _deal(_bucket(key[later], n_buckets), key[later], at[later])]
        rows += [(d, False, x) for d, x in _deal(_bucket(one[~later], n_buckets), *(x[~later] for x in (one, two, doc, key, at)))]
        return pa.Table.from_batches([_table(rows)])

    return run


def decide(n_buckets: int):
    """Windows that a smaller identifier holds too."""

    @relaxed
    def run(table: pa.Table) -> pa.Table:
        done, blobs, dests = table.column("done").to_pylist(), table.column("blob").to_pylist(), table.column("dest").to_pylist()
        rows = [(d, True, x) for d, ok, x in zip(dests, done, blobs, strict=True) if ok]
        one, two, doc, key, at = _unpack([x for ok, x in zip(done, blobs, strict=True) if not ok], [_U8, _U4, _I8, _I8, _I4])
        if len(one):
            order = np.lexsort((doc, two, one))
            one, two, doc, key, at = (x[order] for x in (one, two, doc, key, at))
            group, starts = _groups(one, two)
            later = doc > doc[starts][group]
            rows += [(d, True, x) for d, x in _deal(_bucket(key[later], n_buckets), key[later], at[later])]
        return pa.Table.from_batches([_table(rows)])

    return run


def _cut(text: bytes, gone: np.ndarray) -> str:
    """The text without removed words; a kept word keeps the white space behind it."""
    line = text.decode()
    ends = [m.start() for m in _WORD.finditer(line)] + [len(line)]
    return "".join(line[ends[i] : ends[i + 1]] for i in np.flatnonzero(~gone)).rstrip()


def remove(width: int):
    """Last pass, with the texts: drop covered words."""

    @relaxed
    def run(docs: pa.Table, flags: pa.Table) -> pa.Table:
        keys, pos = _by_key(flags)
        own, texts = docs.column("key").to_numpy(), as_bytes(docs.column("text").combine_chunks())
        n_words, n_removed, digests, kept = [], [], [], []
        for text, a, b in zip(texts, np.searchsorted(keys, own), np.searchsorted(keys, own, side="right"), strict=True):
            words = blank_words(text)
            n_words.append(len(words))
            if a < b:
                gone = _covered(pos[a:b].astype(np.int64), 0, width, len(words))
                n_removed.append(int(gone.sum()))
                words = [w for w, g in zip(words, gone, strict=True) if not g]
                kept.append(_cut(text, gone))
            else:
                n_removed.append(0)
                kept.append(text.decode() if text is not None else None)
            digests.append(hashlib.sha256(b" ".join(words)).hexdigest())
        arrays = [docs.column("key"), docs.column("own"), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(digests, pa.string()), pa.array(kept, pa.string())]
        return pa.Table.from_arrays(arrays, names=["key", "own", "n_words", "n_removed", "kept_sha256", "kept_text"])

    return run


def dedup_substrings(spark: SparkSession, docs: DataFrame, *, width: int = 13, keep: list[str] | None = None, bucket_bytes: int = 8 << 20, copies: int = 256) -> DataFrame:
    """``n_words, n_removed, kept_sha256, kept_text`` beside the columns that ``keep`` names (any but the text); one of these names gets ``_in`` behind it.

    A row (identifier and text) that occurs more than ``copies`` times goes through
    once, and its result is joined to all of them.
    """
    work, keep = Workspace(spark, "substring"), keep or ["doc_id"]
    if "text" in keep:
        raise ValueError("what is left of the text is kept_text")
    key = F.xxhash64("doc_id", "text")
    rows = docs.select(key.alias("key"), F.col("doc_id").cast("long").alias("doc_id"), "text", row_of(keep).alias("own"))
    crowded = work.save(rows.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > copies).select("key"), "crowded")
    if crowded.isEmpty():
        return unfold(_remove_all(work, rows, width, bucket_bytes).drop("key"), keep)
    often = rows.join(crowded, "key", "left_semi")
    one = often.groupBy("key").agg(F.first("doc_id").alias("doc_id"), F.first("text").alias("text")).withColumn("own", F.lit(None).cast(rows.schema["own"].dataType))
    done = work.save(_remove_all(work, rows.join(crowded, "key", "left_anti").unionByName(one), width, bucket_bytes), "done")
    again = often.select("key", "own").join(done.where("own is null").drop("own"), "key")
    return unfold(done.where("own is not null").unionByName(again).drop("key"), keep)


def _remove_all(work: Workspace, rows: DataFrame, width: int, bucket_bytes: int) -> DataFrame:
    """``key, own`` with the results, for ``rows(key, doc_id, text, own)``."""
    spark, period = rows.sparkSession, choose_period(width)
    total = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    n = max(64, -(-total // bucket_bytes))
    texts = rows.select("key", "doc_id", "text")
    shared = work.save(texts.mapInArrow(find_anchors(width, period, n), PACKED).groupBy("dest").applyInArrow(match_anchors(n), PACKED), "shared")
    release(spark)
    unsigned = F.expr(f"cast(pmod(cast(key as decimal(20,0)) + case when key < 0 then 18446744073709551616BD else 0BD end, {n}BD) as long)")
    dealt = texts.withColumn("dest", unsigned)
    flags = work.save(dealt.groupBy("dest").cogroup(shared.groupBy("dest")).applyInArrow(extend(width, period, n), PACKED).groupBy("dest").applyInArrow(decide(n), PACKED), "flags")
    work.free("shared")
    whole = rows.select("key", "own", "text").withColumn("dest", unsigned)
    schema = T.StructType([rows.schema["key"], T.StructField("own", rows.schema["own"].dataType), *T._parse_datatype_string("n_words long, n_removed long, kept_sha256 string, kept_text string").fields])
    return whole.groupBy("dest").cogroup(flags.groupBy("dest")).applyInArrow(remove(width), schema)
