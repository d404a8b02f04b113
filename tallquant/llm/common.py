"""Helpers that several training-data operators share."""

from __future__ import annotations

import ctypes
import gc
import os
import re
import tempfile
import time
import uuid
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.session import ship

# The two word classes of the contracts.
BLANK_WORD = r"[^\x20\x09-\x0D]+"
ALNUM_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same words before A-Z is lowered.
ALNUM_ANY_CASE = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"

_ALNUM_TABLE = bytes(
    b if b >= 128 or chr(b) in "0123456789abcdefghijklmnopqrstuvwxyz" else b + 32 if 65 <= b <= 90 else 32
    for b in range(256)
)


def blank_words(raw: bytes | None, lower: bool = False) -> list[bytes]:
    """Words between ASCII white space (the class ``BLANK_WORD``); null has none."""
    if not raw:
        return []
    return (raw.lower() if lower else raw).split()


def alnum_words(raw: bytes | None) -> list[bytes]:
    """Lower-cased words of the class ``ALNUM_WORD``; null has none."""
    return raw.translate(_ALNUM_TABLE).split() if raw else []


def as_bytes(column: pa.Array) -> list[bytes | None]:
    """UTF-8 bytes of a string column of an Arrow batch."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist()


def word_hashes(words: list[bytes]) -> np.ndarray:
    """64-bit hashes of words, equal in every process."""
    import xxhash

    digest = xxhash.xxh3_64_intdigest
    return np.fromiter(map(digest, words), dtype=np.uint64, count=len(words))


_MIX = np.uint64(0x9E3779B97F4A7C15)


def window_hashes(words: np.ndarray, width: int, seed: int = 0) -> np.ndarray:
    """A 64-bit hash for each run of ``width`` consecutive word hashes."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    with np.errstate(over="ignore"):
        out = np.full(n, np.uint64(0x243F6A8885A308D3 + seed), dtype=np.uint64)
        for k in range(width):
            out ^= words[k : k + n]
            out *= _MIX
            out ^= out >> np.uint64(29)
        out *= np.uint64(0xBF58476D1CE4E5B9)
        out ^= out >> np.uint64(32)
    return out


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``).

    Where it is unset, a local master gets a temporary folder of this machine; on
    a cluster its executors could not see that, so it is an error.
    """
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = "file://" + tempfile.mkdtemp(prefix="tallquant_shared_")
        spark.sparkContext.setCheckpointDir(where)
    return where.rstrip("/")


def filesystem(uri: str):
    """The file system of a folder or file, and the path in it."""
    import pyarrow.fs as pafs

    return pafs.FileSystem.from_uri(uri)


def publish(fs, temp: str, path: str) -> None:
    """Give a finished file its name; of repeated attempts, which write the same bytes, any one may stay.

    Some file systems rename onto an existing file, others refuse.
    """
    import pyarrow.fs as pafs

    try:
        fs.move(temp, path)
    except OSError:
        if fs.get_file_info(path).type != pafs.FileType.File:
            raise
        fs.delete_file(temp)


def carried(keep: list[str], results: list[str]) -> dict[str, str]:
    """Names under which columns are carried: one that a result column has as well gets ``_in`` behind it."""
    taken, out = {r.lower() for r in results}, {}
    for c in keep:
        name = c
        while name.lower() in taken:
            name += "_in"
        taken.add(name.lower())
        out[c] = name
    return out


def row_of(keep: list[str]):
    """The columns to carry but the text, as one struct whose fields are numbered, so that no name can clash."""
    return F.struct(F.lit(None).cast("int").alias("none"), *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(keep) if c != "text"])


def unfold(frame: DataFrame, keep: list[str]) -> DataFrame:
    """The carried columns of :func:`row_of` and the text, if it is one of them, then the results."""
    results = [c for c in frame.columns if c not in ("own", "own_text")]
    names = carried(keep, results)
    return frame.select(*[(F.col("own_text") if c == "text" else F.col("own")[f"c{i}"]).alias(names[c]) for i, c in enumerate(keep)], *results)


class Workspace:
    """Intermediate tables in the shared folder.

    A saved table cuts the lineage: a lost executor costs the re-reading of
    files, not the recomputation of what led to them.  The folder goes when the
    application ends.
    """

    def __init__(self, spark: SparkSession, name: str):
        ship(spark)
        self.spark, self.root = spark, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        folder = jvm.org.apache.hadoop.fs.Path(self.root)
        fs = folder.getFileSystem(conf)
        fs.mkdirs(folder)
        fs.deleteOnExit(folder)  # results are read from here until the application ends

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, *names: str) -> None:
        """Delete saved tables that no later step reads."""
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        for name in names:
            p = jvm.org.apache.hadoop.fs.Path(self.path(name))
            p.getFileSystem(conf).delete(p, True)

    def free(self, *names: str) -> None:
        """Delete saved tables, and the shuffle files of jobs that ended."""
        self.drop(*names)
        release(self.spark)


def release(spark: SparkSession) -> None:
    """Let Spark's cleaner drop shuffle files of finished jobs."""
    for _ in range(2):  # what the first round frees may hold the last reference to a shuffle
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


def components(spark: SparkSession, edges: DataFrame, work: Workspace, tag: str = "cc") -> DataFrame:
    """Connected components of an undirected graph, smallest node as the label.

    ``edges(a, b)`` with non-null longs; returns ``(node, component)`` for every
    node of an edge.  Alternates two star contractions, each a grouped minimum
    and a join on the node, until the edge set no longer changes; the edge set
    is written to the shared folder each round, so lineage stays short, and hub
    nodes are split by adaptive skew joins.  No part of the graph comes to the
    driver but one checksum a round.
    """
    edges = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    edges = work.save(edges, f"{tag}-0")
    before, k = None, 0

    def meet(some: DataFrame, least: DataFrame) -> DataFrame:
        """Join on the node and a second key, so that both sides have exchanges of their own and a hub's partition can be split."""
        near = F.shiftright("u", 5).alias("near")
        return some.select("u", "v", near).join(least.select("u", "m", near), ["u", "near"]).drop("near")

    while True:
        both = edges.union(edges.select("v", "u"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = meet(both.where("v > u"), least).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            meet(large, least)
            .select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
            .select("e.u", "e.v")
            .where("u <> v")
            .distinct()
        )
        k += 1
        edges = work.save(small, f"{tag}-{k}")
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
        work.drop(f"{tag}-{k - 1}")
    leaves = edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return leaves.union(leaves.select(F.col("component").alias("node"), "component").distinct())


_PLAIN = re.compile(rb"(?:[a-z]|\xc3[\x9f-\xb6\xb8-\xbf])+").fullmatch


def _byte_level_table() -> dict[int, int]:
    """Characters by which byte-level models write bytes: printable ones stand for themselves, the others follow from 256 on."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in printable]
    return dict(zip(printable, printable, strict=True)) | {b: 256 + i for i, b in enumerate(others)}


_BYTE_LEVEL = _byte_level_table()


class WordEncoder:
    """Token ids of whole texts by a `tokenizers` file, through a cache of chunks.

    The word-level pre-tokeniser of the file never joins text across white
    space, and its normaliser works inside a chunk, so the ids of a text are the
    ids of its white-space chunks in order; frequent chunks are encoded once.
    The cache holds ``limit`` chunks at most.  ``tests/llm`` compares with whole
    texts encoded by the library.
    """

    def __init__(self, path: str, limit: int = 700_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.lib, self.limit = Tokenizer.from_file(path), limit
        self.known: dict[bytes, int] = {}
        self.flat, self.size = np.empty(1 << 20, dtype=np.uint32), 0
        self.at, self.length = np.empty(1 << 18, dtype=np.int64), np.empty(1 << 18, dtype=np.int64)

    def _store(self, ids: np.ndarray, n: np.ndarray, first: int) -> None:
        """Append the ids of the chunks numbered first, first + 1, ..., of n ids each."""
        while self.size + len(ids) > len(self.flat):
            self.flat = np.resize(self.flat, 2 * len(self.flat))
        while first + len(n) > len(self.at):
            self.at, self.length = np.resize(self.at, 2 * len(self.at)), np.resize(self.length, 2 * len(self.length))
        self.flat[self.size : self.size + len(ids)] = ids
        self.at[first : first + len(n)] = self.size + np.cumsum(n) - n
        self.length[first : first + len(n)] = n
        self.size += len(ids)

    def _encode_names(self, names: list[bytes]) -> tuple[list[int], list[int]]:
        """All ids of some lower-case chunks one after the other, and how many each has."""
        found: dict[bytes, list[int]] = {}
        # lower-case Latin-1 letters are one pre-token that the normaliser leaves alone: straight to the library's model
        plain = [n for n in names if n.isalpha() or _PLAIN(n)]
        if plain:
            words = b"\n".join(plain).decode("latin-1").translate(_BYTE_LEVEL).split(chr(_BYTE_LEVEL[10]))
            found = dict(zip(plain, [[t.id for t in tokens] for tokens in map(self.lib.model.tokenize, words)], strict=True))
        other = [n for n in names if n not in found]
        for name in [n for n in other if b"\0" in n]:
            found[name] = self.lib.encode(name.decode(), add_special_tokens=False).ids
        other = [n for n in other if n not in found]
        for start in range(0, len(other), 1024):
            some = other[start : start + 1024]
            got = self.lib.encode_batch_fast(b"\0".join(some).decode().split("\0"), add_special_tokens=False)
            found.update(zip(some, [e.ids for e in got], strict=True))
        lists = [found[n] for n in names]
        return list(chain.from_iterable(lists)), list(map(len, lists))

    def _encode_chunks(self, chunks: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct chunks one after the other, and how many each has; a word in either case and before a full stop or comma is encoded once.

        The normaliser lowers letters, and a boundary always lies between a
        letter and a stop, so both steps give the ids of the chunk itself.  Chunks
        with ``<|`` may hold a special token, which is case-sensitive.
        """
        size = np.fromiter(map(len, chunks), dtype=np.int64, count=len(chunks))
        line = b"\n".join(chunks).lower()
        lows, raw, ends = line.split(b"\n"), np.frombuffer(line, dtype=np.uint8), np.cumsum(size + 1) - 1
        last, before = raw[ends - 1], raw[np.maximum(ends - 2, 0)]
        stop = ((last == 46) | (last == 44)) & (size > 1) & (before >= 97) & (before <= 122)
        if b"<|" in line or b"\0" in line:
            for i in [i for i, c in enumerate(chunks) if b"<|" in c or b"\0" in c]:
                lows[i], stop[i] = chunks[i], False
        bases = [x[:-1] if cut else x for x, cut in zip(lows, stop.tolist(), strict=True)]
        names = list(dict.fromkeys(chain(bases, (b".", b","))))
        at, n = np.empty(len(names), dtype=np.int64), np.empty(len(names), dtype=np.int64)
        number = np.fromiter(map(self.known.get, names, repeat(-1)), dtype=np.int64, count=len(names))
        old, new = np.flatnonzero(number >= 0), np.flatnonzero(number < 0)
        at[old], n[old] = self.at[number[old]], self.length[number[old]]
        ids, counts = self._encode_names([names[i] for i in new.tolist()])
        n[new] = counts
        at[new] = self.size + np.cumsum(n[new]) - n[new]
        source = np.concatenate((self.flat[: self.size], np.array(ids, dtype=np.uint32)))
        where = dict(zip(names, range(len(names)), strict=True))
        base = np.fromiter(map(where.__getitem__, bases), dtype=np.int64, count=len(bases))
        length, marks = n[base], {m: source[at[where[c]] : at[where[c]] + n[where[c]]] for m, c in ((46, b"."), (44, b","))}
        total = length.copy()
        for m, own in marks.items():
            total += np.where(stop & (last == m), len(own), 0)
        starts = np.cumsum(total) - total
        out = np.empty(int(total.sum()), dtype=np.uint32)
        step = np.arange(int(length.sum())) - np.repeat(np.cumsum(length) - length, length)
        out[np.repeat(starts, length) + step] = source[np.repeat(at[base], length) + step]
        for m, own in marks.items():
            there = np.flatnonzero(stop & (last == m))
            for j, one in enumerate(own.tolist()):
                out[starts[there] + length[there] + j] = one
        return out, total

    def encode(self, texts: list[bytes | None]) -> list[np.ndarray]:
        """Ids of each text as uint32; null as the empty text."""
        gc.disable()  # millions of small objects without cycles
        try:
            return self._encode(texts)
        finally:
            gc.enable()

    def _encode(self, texts: list[bytes | None]) -> list[np.ndarray]:
        chunks = [t.split() if t else [] for t in texts]
        counts = np.fromiter(map(len, chunks), dtype=np.int64, count=len(chunks))
        flat = list(chain.from_iterable(chunks))
        get = self.known.get
        index = np.fromiter(map(get, flat, repeat(-1)), dtype=np.int64, count=len(flat))
        size, missing = self.size, np.flatnonzero(index < 0)
        if len(missing):
            absent = [flat[i] for i in missing]
            names = list(dict.fromkeys(absent))
            first = len(self.known)
            numbers = dict(zip(names, range(first, first + len(names)), strict=True))
            ids, n = self._encode_chunks(names)
            room = min(len(names), max(0, self.limit - first))
            cut = int(n[:room].sum())
            self._store(ids[:cut], n[:room], first)
            self.known.update(zip(names[:room], range(first, first + room), strict=True))
            size = self.size
            self._store(ids[cut:], n[room:], first + room)
            index[missing] = np.fromiter(map(numbers.__getitem__, absent), dtype=np.int64, count=len(absent))
        length = self.length[index]
        ends = np.cumsum(length)
        total = int(ends[-1]) if len(ends) else 0
        ids = self.flat[np.repeat(self.at[index] - (ends - length), length) + np.arange(total)]
        self.size = size  # what was encoded only for this batch is forgotten
        stops = np.concatenate(([0], ends))[np.concatenate(([0], np.cumsum(counts)))]
        return [ids[a:b] for a, b in zip(stops[:-1], stops[1:], strict=True)]


#: What a Python worker keeps between tasks, by operator.
CACHES: dict[str, dict] = {}
_NOW = [""]


def worker_cache(operator: str) -> dict:
    """The operator's cache in this worker.

    Workers serve one stage after the other; one that turns to another operator
    gives back what it kept for the last.
    """
    if _NOW[0] != operator:
        for name in [n for n in CACHES if n != operator]:
            del CACHES[name]
        _NOW[0] = operator
        trim()
    return CACHES.setdefault(operator, {})


def relax() -> None:
    """Return freed memory of Arrow and the C library to the system, where that can."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def trim() -> None:
    """Collect garbage, then :func:`relax`."""
    gc.collect()
    relax()


def relaxed(function):
    """A function of Arrow tables after which the worker gives freed memory back: workers outlive their tasks."""

    def one(table: pa.Table) -> pa.Table:
        try:
            return function(table)
        finally:
            relax()

    def two(left: pa.Table, right: pa.Table) -> pa.Table:
        try:
            return function(left, right)
        finally:
            relax()

    return two if function.__code__.co_argcount == 2 else one


def word_encoder(path: str, limit: int = 700_000) -> WordEncoder:
    """One encoder for each file, cache size and Python worker."""
    kept = worker_cache("encoder")
    if (path, limit) not in kept:
        kept.clear()
        kept[path, limit] = WordEncoder(path, limit)
    return kept[path, limit]


def default_tokenizer() -> str:
    """The public vocabulary file that the contracts name; a parameter everywhere."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def text_slices(texts: list[bytes | None], most: int = 3_000_000):
    """Cut a batch into runs of rows with at most ``most`` bytes (one row at least)."""
    start = total = 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if i > start and total + n > most:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(texts):
        yield start, len(texts)
