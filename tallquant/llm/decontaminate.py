"""Benchmark decontamination with one Aho-Corasick automaton.

Every window of consecutive item words (a whole item if it is shorter) becomes a
pattern, spaces at both ends, so that a match always lies on word boundaries.
Each text is normalised once and scanned once; matches are counted in words and
mapped back to character offsets of the original text.

Null texts and items have no words and match nothing; an item without an
identifier takes part and is named by the empty string; items that share a
window are all found; an empty benchmark hits nothing.  Columns of the documents
other than ``doc_id`` and ``text`` are carried along on request; one that has the
name of a result column gets ``_in`` behind it.

An automaton takes some 50 bytes a node, and a word begins a window of its own, so
the nodes are at most ``width`` times the octets of the items.  Up to
``automaton_nodes`` of them one automaton scans everything in one pass.  A larger
benchmark is cut into parts of that size, long items into segments that overlap by
a window; each part is a job of its own that writes its hits, and the hits of all
parts are joined to the texts, so neither the broadcast nor a worker grows with it.
"""

from __future__ import annotations

import hashlib
import re
import string
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallquant.llm.common import ALNUM_ANY_CASE, ALNUM_WORD, Workspace, alnum_words, as_bytes, row_of, ship, unfold, worker_cache

FOUND = "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, item_ids array<string>, spans array<struct<start: int, end: int>>"
_SPAN = pa.struct([("start", pa.int32()), ("end", pa.int32())])
_WORD = re.compile(ALNUM_ANY_CASE)


def item_windows(text: bytes | None, width: int) -> list[tuple[str, int]]:
    """Patterns of one item, each with its number of words."""
    words = alnum_words(text)
    if not words:
        return []
    size = min(width, len(words))
    return [(f" {b' '.join(words[i : i + size]).decode()} ", size) for i in range(len(words) - size + 1)]


def build_automaton(items: list[tuple[str, bytes | None]], width: int):
    """The automaton over all items, or None if there is no pattern."""
    import ahocorasick

    owners: dict[str, tuple[int, set[str]]] = {}
    for name, text in items:
        for pattern, size in item_windows(text, width):
            owners.setdefault(pattern, (size, set()))[1].add(name)
    if not owners:
        return None
    machine = ahocorasick.Automaton()
    for pattern, (size, names) in owners.items():
        machine.add_word(pattern, (len(pattern), size, sorted(names)))
    machine.make_automaton()
    return machine


def scan(machine, text: bytes | None) -> tuple[int, np.ndarray, set[str]]:
    """Number of words, the indexes of hit words, and the items found."""
    words = alnum_words(text)
    n, names = len(words), set()
    edge = None
    line = f" {b' '.join(words).decode()} "
    for end, (length, size, owners) in machine.iter(line) if machine and n else ():
        if edge is None:
            starts = np.cumsum([0] + [len(w) + 1 for w in line[1:-1].split(" ")][:-1])
            edge = np.zeros(n + 1, dtype=np.int64)
        first = int(np.searchsorted(starts, end - length + 1))
        edge[first] += 1
        edge[first + size] -= 1
        names.update(owners)
    return n, np.flatnonzero(np.cumsum(edge)[:-1]) if edge is not None else np.empty(0, dtype=np.int64), names


def word_spans(text: bytes, hit: np.ndarray) -> list[dict[str, int]]:
    """Character ranges of the original text under runs of hit words."""
    places = [m.span() for m in _WORD.finditer(text.decode())]
    runs = np.split(hit, np.flatnonzero(np.diff(hit) > 1) + 1) if len(hit) else []
    return [{"start": places[r[0]][0], "end": places[r[-1]][1]} for r in runs]


def item_segments(benchmark: DataFrame, width: int, least_words: int, step: int) -> DataFrame:
    """``item_id, text``: the normalised items, long ones cut so that every window lies in one segment."""
    low = F.translate("text", string.ascii_uppercase, string.ascii_lowercase)
    words = F.regexp_extract_all(low, F.lit(ALNUM_WORD), F.lit(0))
    items = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item_id"), words.alias("words")).where(F.size("words") >= max(1, least_words))
    starts = F.sequence(F.lit(0), F.greatest(F.size("words") - width, F.lit(0)), F.lit(step))
    parts = items.select("item_id", "words", F.explode(starts).alias("at"))
    return parts.select("item_id", F.array_join(F.slice("words", F.col("at") + 1, F.lit(step + width - 1)), " ").alias("text"))


def decontaminate(
    spark: SparkSession,
    docs: DataFrame,
    benchmark: DataFrame,
    *,
    width: int = 10,
    least_words: int = 1,
    keep: list[str] | None = None,
    automaton_nodes: int = 4_000_000,
    segment_words: int = 4096,
) -> DataFrame:
    """Documents with what was found in them; ``keep`` names the columns to carry along."""
    ship(spark)
    keep = keep if keep is not None else ["doc_id"]
    items = item_segments(benchmark, width, least_words, segment_words)
    nodes = width * items.agg(F.coalesce(F.sum(F.octet_length("text") + 2), F.lit(0))).first()[0]
    parts = max(1, -(-nodes // automaton_nodes))

    def part(k: int):
        own = items if parts == 1 else items.where(F.expr(f"pmod(xxhash64(item_id, text), {parts}) = {k}"))
        return spark.sparkContext.broadcast([(r.item_id, r.text.encode()) for r in own.collect()])

    frame, with_text = docs.select(row_of(keep).alias("own"), "text"), "text" in keep
    schema = T.StructType([frame.schema["own"], *T._parse_datatype_string(FOUND + ", own_text string" * with_text).fields])
    if parts == 1:
        return unfold(frame.mapInArrow(_scanner(part(0), uuid.uuid4().hex, width, with_text), schema), keep)
    # the text alone decides what is found in it, so texts are told apart by 128 bits of hash
    work, key = Workspace(spark, "decontaminate"), [F.xxhash64("text").alias("k1"), F.xxhash64("text", F.lit(1)).alias("k2")]
    texts = docs.where("text is not null").select(*key, "text")
    found = [work.save(texts.mapInArrow(_finder(part(k), uuid.uuid4().hex, width), "k1 long, k2 long, hit array<int>, found array<string>"), f"hits-{k}") for k in range(parts)]
    for other in found[1:]:
        found[0] = found[0].union(other)
    hits = found[0].groupBy("k1", "k2").agg(F.flatten(F.collect_set("hit")).alias("hit"), F.flatten(F.collect_set("found")).alias("found"))
    both = docs.select(row_of(keep).alias("own"), "text", *key).join(hits, ["k1", "k2"], "left").select("own", "text", "hit", "found")
    return unfold(both.mapInArrow(_reporter(with_text), schema), keep)


def _machine(items, token: str, width: int):
    """The automaton of a part, one at a time in each worker."""
    kept = worker_cache("decontaminate")
    if token not in kept:
        kept.clear()
        kept[token] = build_automaton(items.value, width)
    return kept[token]


def _report(batch: pa.RecordBatch, with_text: bool, texts: list[bytes | None], counts: list[int], hits: list[np.ndarray], founds: list[list[str]]) -> pa.RecordBatch:
    spans = [word_spans(t, h) if len(h) else [] for t, h in zip(texts, hits, strict=True)]
    digest = [hashlib.sha256(",".join(f).encode()).hexdigest() for f in founds]
    n_hit = [len(h) for h in hits]
    out = [batch.column(0), pa.array(counts, pa.int64()), pa.array(n_hit, pa.int64()), pa.array(map(len, founds), pa.int64()), pa.array(digest, pa.string()), pa.array([n > 0 for n in n_hit], pa.bool_()), pa.array(founds, pa.list_(pa.string())), pa.array(spans, pa.list_(_SPAN)), *[batch.column(1)] * with_text]
    return pa.RecordBatch.from_arrays(out, names=["own", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "item_ids", "spans", *["own_text"] * with_text])


def _scanner(items, token: str, width: int, with_text: bool):
    """One automaton for the whole benchmark: ``own, text`` to results."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = _machine(items, token, width)
        for batch in batches:
            texts = as_bytes(batch.column(1))
            counts, hits, founds = zip(*[scan(machine, t) for t in texts], strict=True) if texts else ([], [], [])
            yield _report(batch, with_text, texts, list(counts), list(hits), [sorted(f) for f in founds])

    return run


def _finder(items, token: str, width: int):
    """One automaton of several: what it finds, for texts in which it finds something."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = _machine(items, token, width)
        for batch in batches:
            rows = [(a, b, hit.tolist(), sorted(names)) for a, b, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), as_bytes(batch.column(2)), strict=True) for _, hit, names in [scan(machine, t)] if len(hit)]
            kinds = [pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.string())]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["k1", "k2", "hit", "found"])

    return run


def _reporter(with_text: bool):
    """``own, text, hit, found`` to results."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = as_bytes(batch.column(1))
            hits = [np.unique(np.array(h or [], dtype=np.int64)) for h in batch.column(2).to_pylist()]
            founds = [sorted(set(f or [])) for f in batch.column(3).to_pylist()]
            yield _report(batch, with_text, texts, [len(alnum_words(t)) for t in texts], hits, founds)

    return run
