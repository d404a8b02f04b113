"""Hidden Markov language model of word sequences.

Symbols are the most frequent words, classes of all other words by their ending,
and the end token.  An extra state emits the end token only, and leads to the
first words, so many texts in a row are one Markov chain and lanes of texts run
through numpy side by side.  Baum-Welch sums expected counts over lanes, batches
and partitions of the whole corpus; the scaled forward recursion gives the exact
likelihood of a text.  A word of a class costs the class and its smoothed share of
the class, so the model, like the unigram base, gives some probability to any text.

Corpus counts cover every training token.  Only the ``listed`` most frequent words
go to the executors by broadcast (a parameter); the rest meet their counts in a
join by word.  Null and empty texts are the end token alone; repeated rows are
scored each; a null identifier is scored but belongs to neither fold, so is not
learned from; with nothing to learn from, every token is unknown.
"""

from __future__ import annotations

import heapq
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.llm.common import Workspace, as_bytes, blank_words, release, text_slices, worker_cache

SMOOTH = 0.1


@dataclass
class Lexicon:
    """The listed words with counts, the classes of the others, and the totals."""

    words: list[bytes]  # by falling count
    counts: np.ndarray
    n_symbols: int  # so many first words are symbols of their own
    class_total: np.ndarray  # of words that are no symbol
    class_types: np.ndarray
    tokens: int
    types: int
    docs: int

    @property
    def n_classes(self) -> int:
        return len(self.class_total)

    @property
    def end(self) -> int:
        return self.n_symbols + self.n_classes

    def unigram(self) -> np.ndarray:
        """Smoothed share of each symbol."""
        raw = np.concatenate((self.counts[: self.n_symbols], self.class_total, [self.docs])) + SMOOTH
        return raw / raw.sum()


def ending_class(word: bytes, n_classes: int) -> int:
    """Class of a word by its last two bytes."""
    return zlib.crc32(word[-2:]) % n_classes


class Coder:
    """Texts to symbols and to what the words of classes cost."""

    def __init__(self, lex: Lexicon):
        self.lex = lex
        self.at = {w: i for i, w in enumerate(lex.words)}
        k = np.arange(len(lex.words))
        self.class_of = np.array([ending_class(w, lex.n_classes) for w in lex.words], dtype=np.int64)
        self.symbol = np.where(k < lex.n_symbols, k, lex.n_symbols + self.class_of)
        self.log_c = np.log10(lex.counts + SMOOTH)
        self.log_z = np.log10(lex.class_total + SMOOTH * (lex.class_types + 1))
        self.extra = np.where(k < lex.n_symbols, 0.0, self.log_c - self.log_z[self.class_of])

    def symbols(self, texts: list[list[bytes]]) -> tuple[list[np.ndarray], list[np.ndarray]]:
        """For each text: symbols with the end token, and listed words (-1: not listed)."""
        get, n_symbols, n_classes = self.at.get, self.lex.n_symbols, self.lex.n_classes
        words = [w for t in texts for w in t]
        index = np.fromiter(map(get, words, repeat(-1)), dtype=np.int64, count=len(words))
        symbols = self.symbol[index] if len(self.symbol) else np.zeros(len(words), dtype=np.int64)
        other = np.flatnonzero(index < 0)
        symbols[other] = [n_symbols + zlib.crc32(words[i][-2:]) % n_classes for i in other.tolist()]
        ends = np.cumsum([len(t) for t in texts], dtype=np.int64)
        starts = np.concatenate(([0], ends[:-1]))
        whole = np.insert(symbols, ends, self.lex.end)
        cut = [whole[x + k : y + k + 1] for k, (x, y) in enumerate(zip(starts.tolist(), ends.tolist(), strict=True))]
        return cut, [index[x:y] for x, y in zip(starts.tolist(), ends.tolist(), strict=True)]


def lanes(texts: list[np.ndarray], n: int) -> tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]:
    """Deal texts to lanes of about equal length: symbols (time by lane), lane lengths (falling), each text's lane and end."""
    n = max(1, min(n, len(texts), -(-sum(map(len, texts)) // max(map(len, texts), default=1))))
    heap = [(0, i) for i in range(n)]
    held: list[list[int]] = [[] for _ in range(n)]
    for k in sorted(range(len(texts)), key=lambda k: -len(texts[k])):
        size, lane = heap[0]
        held[lane].append(k)
        heapq.heapreplace(heap, (size + len(texts[k]), lane))
    held.sort(key=lambda ks: -sum(len(texts[k]) for k in ks))
    length = np.array([sum(len(texts[k]) for k in ks) for ks in held])
    grid = np.zeros((length[0] if len(length) else 0, n), dtype=np.int64)
    where: list[tuple[int, int]] = [(0, 0)] * len(texts)
    for lane, ks in enumerate(held):
        at = 0
        for k in ks:
            grid[at : at + len(texts[k]), lane] = texts[k]
            at += len(texts[k])
            where[k] = lane, at
    return grid, length, where


@dataclass
class Chain:
    """Transitions and emissions; the last state is the end of a text."""

    move: np.ndarray
    emit: np.ndarray  # symbol by state

    def forward(self, grid: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Scale factors (time by lane) of the forward recursion; states are rows and lanes columns."""
        t_max, n = grid.shape
        scale, now = np.ones((t_max, n)), np.zeros((len(self.move), n))
        now[-1] = 1
        behind, emit = np.ascontiguousarray(self.move.T), np.ascontiguousarray(self.emit.T)
        active = np.searchsorted(-length, -np.arange(t_max), side="left")
        for t in range(t_max):
            a = active[t]
            now = behind @ now[:, :a]
            now *= emit.take(grid[t, :a], axis=1, mode="clip")
            scale[t, :a] = now.sum(axis=0)
            now /= scale[t, :a]
        return scale

    def score(self, texts: list[np.ndarray], n_lanes: int = 1536) -> np.ndarray:
        """log10 likelihood of each text."""
        if not texts:
            return np.empty(0)
        grid, length, where = lanes(texts, n_lanes)
        total = np.cumsum(np.log10(self.forward(grid, length)), axis=0)
        total = np.vstack([np.zeros((1, grid.shape[1])), total])
        return np.array([total[end, lane] - total[end - len(x), lane] for x, (lane, end) in zip(texts, where, strict=True)])

    def expect(self, texts: list[np.ndarray], n_lanes: int = 1536) -> tuple[np.ndarray, np.ndarray]:
        """Expected transitions and emissions of some texts.

        States are rows and lanes columns.  Emissions are taken relative to the
        best state of their symbol, which no expectation depends on; so two steps
        stay far inside the range of a float and every other step scales.
        """
        grid, length, _ = lanes(texts, n_lanes)
        kind, (t_max, n), k = np.float32, grid.shape, len(self.move)
        active = np.searchsorted(-length, -np.arange(t_max), side="left")
        scales = (np.arange(t_max) % 2 == 1) | (np.append(active[1:], 0) < active)
        ahead_of, behind = self.move.astype(kind), np.ascontiguousarray(self.move.T, dtype=kind)
        emit = np.ascontiguousarray((self.emit / self.emit.max(axis=1, keepdims=True)).T, dtype=kind)
        state, factor = np.zeros((t_max, k, n), dtype=kind), {}
        first = np.zeros((k, n), dtype=kind)
        first[-1] = 1
        now = first
        for t in range(t_max):
            a = active[t]
            now = behind @ now[:, :a]
            now *= emit.take(grid[t, :a], axis=1, mode="clip")
            if scales[t]:
                factor[t] = 1 / now.sum(axis=0)
                now *= factor[t]
            state[t, :, :a] = now
        moves = np.zeros((k, k))
        back = np.ones((k, n), dtype=kind)
        for t in range(t_max - 1, -1, -1):
            a = active[t]
            ahead = emit.take(grid[t, :a], axis=1, mode="clip")
            ahead *= back[:, :a]
            if scales[t]:
                ahead *= factor[t]
            state[t, :, :a] *= back[:, :a]
            before = state[t - 1, :, :a] if t else first[:, :a]
            moves += before @ ahead.T
            back[:, :a] = ahead_of @ ahead
        moves *= self.move
        flat = grid.ravel()  # cells beyond the end of a lane weigh nothing
        emits = np.zeros(self.emit.shape)
        for s in range(k - 1):
            emits[:, s] = np.bincount(flat, weights=state[:, s].ravel(), minlength=len(self.emit))
        emits[-1, -1] = len(texts)
        return moves, emits


def maximise(moves: np.ndarray, emits: np.ndarray, prior: np.ndarray, strength: float = 50.0) -> Chain:
    """Smoothed re-estimation; ``prior`` is the share of each symbol, the end last."""
    move = moves + 0.1
    move /= move.sum(axis=1, keepdims=True)
    emit = np.zeros_like(emits)
    words = prior[:-1] / prior[:-1].sum()
    body = emits[:-1, :-1] + strength * words[:, None]
    emit[:-1, :-1] = body / body.sum(axis=0)
    emit[-1, -1] = 1.0
    return Chain(move, emit)


def first_chain(prior: np.ndarray, states: int, seed: int = 7) -> Chain:
    """A start that tells states apart by a fixed random tilt of the word shares."""
    rng = np.random.default_rng(seed)
    moves = np.full((states + 1, states + 1), 1.0) + 20 * np.eye(states + 1)
    moves[-1] = 1.0
    tilt = rng.gamma(0.5, size=(len(prior), states + 1)) + 0.02
    return maximise(moves, prior[:, None] * tilt, prior, strength=1e-3)


def count_words(docs: DataFrame, learns, work: Workspace, flush: int = 400_000) -> DataFrame:
    """``word, c`` over all training texts, counted in batches before the shuffle; the empty word has the number of texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(counts: Counter) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(counts), pa.binary()).cast(pa.string()), pa.array(list(counts.values()), pa.int64())], names=["word", "n"])

        counts: Counter = Counter()
        for batch in batches:
            for text in as_bytes(batch.column(0)):
                counts.update(blank_words(text, lower=True))
                counts[b""] += 1
                if len(counts) >= flush:
                    yield out(counts)
                    counts = Counter()
        yield out(counts)

    counted = docs.where(learns).select("text").mapInArrow(run, "word string, n long")
    return work.save(counted.groupBy("word").agg(F.sum("n").alias("c")), "counts")


def build_lexicon(counts: DataFrame, *, listed: int, symbols: int, classes: int) -> Lexicon:
    """Collects at most ``listed`` words, the most frequent, and totals; the table itself stays distributed.

    A word is listed if its count is so high that no more than ``listed`` words
    reach it; the counts that occur (fewer than the root of twice the tokens) are
    tallied to find that limit, so nothing is ordered and no task keeps more.
    """
    raw = F.encode("word", "UTF-8")
    ending = F.when(F.length(raw) >= 2, F.substring(raw, -2, 2)).otherwise(raw)
    by_class = counts.where("word <> ''").groupBy(F.pmod(F.crc32(ending), F.lit(classes)).cast("int").alias("k")).agg(F.sum("c").alias("c"), F.count("*").alias("v")).collect()
    docs = counts.where("word = ''").first()
    tally = sorted(((r.c, r.n) for r in counts.where("word <> ''").groupBy("c").agg(F.count("*").alias("n")).collect()), reverse=True)
    least, held = None, 0
    for c, k in tally:
        if held + k > listed:
            break
        least, held = c, held + k
    top = counts.where("word <> ''").where(F.col("c") >= F.lit(least)).toArrow() if held else None
    pairs = sorted(zip(top.column("c").to_pylist(), top.column("word").to_pylist(), strict=True), key=lambda x: (-x[0], x[1])) if top else []
    words, n = [w.encode() for _, w in pairs], np.array([c for c, _ in pairs], dtype=np.int64)
    symbols = min(symbols, len(words))
    total, types = np.zeros(classes, dtype=np.int64), np.zeros(classes, dtype=np.int64)
    for r in by_class:
        total[r.k], types[r.k] = r.c, r.v
    for w, c in zip(words[:symbols], n[:symbols], strict=True):
        k = ending_class(w, classes)
        total[k] -= c
        types[k] -= 1
    n_docs = docs.c if docs else 0
    return Lexicon(words, n, symbols, total, types, int(sum(r.c for r in by_class)) + n_docs, int(sum(r.v for r in by_class)) + (n_docs > 0), n_docs)


def _texts(column: pa.Array) -> list[np.ndarray]:
    """Symbol arrays of a coded column."""
    return [np.frombuffer(x, "<u2").astype(np.int64) for x in column.to_pylist()]


def _slices(texts: list[np.ndarray], most: int = 2_600_000) -> Iterator[list[int]]:
    """Texts of like length together, about ``most`` tokens at a time: their numbers.

    Lanes of like texts end at about the same time, so the grid of a run has
    hardly more cells than tokens, however long the longest text is.
    """
    part, size = [], 0
    for k in sorted(range(len(texts)), key=lambda k: -len(texts[k])):
        part.append(k)
        size += len(texts[k])
        if size >= most:
            yield part
            part, size = [], 0
    if part:
        yield part


def train(spark: SparkSession, coded: DataFrame, lex: Lexicon, *, states: int = 8, passes: int = 12) -> Chain:
    """Baum-Welch over ``coded(symbols)``: every round is a pass over all texts."""
    prior = lex.unigram()
    chain = first_chain(prior, states)
    width = states + 1
    schema = "slot int, " + ", ".join(f"e{s} double" for s in range(width))
    for _ in range(passes):
        cast = spark.sparkContext.broadcast(chain)

        def expect(batches: Iterator[pa.RecordBatch], cast=cast) -> Iterator[pa.RecordBatch]:
            worker_cache("hmm chain")
            chain = cast.value
            moves, emits = np.zeros_like(chain.move), np.zeros_like(chain.emit)
            for batch in batches:
                texts = _texts(batch.column(0))
                for part in _slices(texts):
                    m, e = chain.expect([texts[k] for k in part])
                    moves += m
                    emits += e
            some = np.flatnonzero(emits.sum(axis=1))
            table = np.vstack([emits[some], moves])
            slots = np.concatenate((some, -1 - np.arange(width)))
            yield pa.RecordBatch.from_arrays([pa.array(slots, pa.int32()), *(pa.array(table[:, s]) for s in range(width))], names=["slot", *(f"e{s}" for s in range(width))])

        sums = coded.select("symbols").mapInArrow(expect, schema).groupBy("slot").agg(*[F.sum(f"e{s}").alias(f"e{s}") for s in range(width)]).collect()
        moves, emits = np.zeros_like(chain.move), np.zeros_like(chain.emit)
        for r in sums:
            (emits if r.slot >= 0 else moves)[r.slot if r.slot >= 0 else -1 - r.slot] = r[1:]
        chain = maximise(moves, emits, prior)
    return chain


def worker_coder(lexicon) -> Coder:
    """One coder for each broadcast lexicon and Python worker."""
    kept = worker_cache("hmm")
    if lexicon.id not in kept:
        kept.clear()
        kept[lexicon.id] = Coder(lexicon.value)
    return kept[lexicon.id]


class SharedLexicon:
    """A broadcast lexicon with an identity that workers can keep a coder by."""

    def __init__(self, spark: SparkSession, lex: Lexicon):
        import uuid

        self.id, self.cast = uuid.uuid4().hex, spark.sparkContext.broadcast(lex)

    @property
    def value(self) -> Lexicon:
        return self.cast.value


def score_texts(
    spark: SparkSession,
    docs: DataFrame,
    learns,
    *,
    states: int = 8,
    passes: int = 12,
    listed: int = 262_144,
    symbols: int = 8192,
    classes: int = 64,
) -> DataFrame:
    """``doc_id, learned, n_tokens, n_known, train_tokens, base_score, score`` for every row of docs.

    ``learns`` is the condition of the training texts.
    """
    work = Workspace(spark, "hmm")
    learns = F.coalesce(learns, F.lit(False))
    counts = count_words(docs, learns, work)
    release(spark)
    if symbols + classes >= 65_536:
        raise ValueError("symbols are coded in two bytes")
    lex = build_lexicon(counts, listed=listed, symbols=symbols, classes=classes)
    shared = SharedLexicon(spark, lex)
    lex_docs = lex.docs
    names = ["uid", "doc_id", "learned", "n_tokens", "n_known", "base", "extra", "symbols", "word", "tf"]
    kinds = [pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary(), pa.string(), pa.int64()]

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, uid = worker_coder(shared), TaskContext.get().partitionId() << 36
        for batch in batches:
            ids, learned, raw = batch.column(0).to_pylist(), batch.column(1).to_pylist(), as_bytes(batch.column(2))
            for a, b in text_slices(raw, 4_000_000):
                known, base, extra = [], [], []
                rare_uid, rare_word, rare_tf = [], [], []
                words = [blank_words(t, lower=True) for t in raw[a:b]]
                texts, indexes = coder.symbols(words)
                for k, (ws, symbols, index) in enumerate(zip(words, texts, indexes, strict=True)):
                    there = index[index >= 0]
                    known.append(len(there) + (lex_docs > 0))
                    base.append(float(coder.log_c[there].sum()) + np.log10(lex_docs + SMOOTH))
                    cost = float(coder.extra[there].sum())
                    if len(there) < len(index):
                        other = np.flatnonzero(index < 0)
                        cost -= float(coder.log_z[symbols[other] - coder.lex.n_symbols].sum())
                        tf = Counter([ws[i] for i in other.tolist()])
                        rare_uid += [uid + k] * len(tf)
                        rare_word += tf.keys()
                        rare_tf += tf.values()
                    extra.append(cost)
                n, m = b - a, len(rare_uid)
                part = [np.arange(uid, uid + n), ids[a:b], learned[a:b], [len(x) for x in texts], known, base, extra, [x.astype("<u2").tobytes() for x in texts], [None] * n, [None] * n]
                yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(part, kinds, strict=True)], names=names)
                nothing = [pa.nulls(m, x) for x in kinds[1:8]]
                yield pa.RecordBatch.from_arrays([pa.array(rare_uid, pa.int64()), *nothing, pa.array(rare_word, pa.binary()).cast(pa.string()), pa.array(rare_tf, pa.int64())], names=names)
                uid += n

    # texts are coded once; training and scoring read the symbols
    schema = "uid long, doc_id long, learned boolean, n_tokens long, n_known long, base double, extra double, symbols binary, word string, tf long"
    parts = work.save(docs.select(F.col("doc_id").cast("long").alias("doc_id"), learns.alias("learned"), "text").mapInArrow(code, schema), "parts")
    coded = parts.where("symbols is not null")
    chain = spark.sparkContext.broadcast(train(spark, coded.where("learned"), lex, states=states, passes=passes))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, total = _texts(batch.column(6)), np.zeros(len(batch))
            for part in _slices(texts):
                total[part] = chain.value.score([texts[k] for k in part])
            yield pa.RecordBatch.from_arrays([*batch.columns[:6], pa.array(total + batch.column(7).to_numpy())], names=["uid", "doc_id", "learned", "n_tokens", "n_known", "base", "score"])

    scored = coded.select("uid", "doc_id", "learned", "n_tokens", "n_known", "base", "symbols", "extra").mapInArrow(score, "uid long, doc_id long, learned boolean, n_tokens long, n_known long, base double, score double")
    # at most ``listed`` words were told by broadcast; the others meet their counts here
    rare = parts.where("word is not null").select("uid", "word", "tf").join(counts.where("word <> ''").hint("shuffle_hash"), "word", "left")
    c = F.coalesce("c", F.lit(0))
    rare = rare.groupBy("uid").agg(F.sum(F.col("tf") * F.log10(c + SMOOTH)).alias("rare"), F.sum(F.when(c > 0, F.col("tf")).otherwise(0)).alias("rare_known"))
    whole = scored.join(rare, "uid", "left")
    zero = F.coalesce("rare", F.lit(0.0))
    z = float(np.log10(lex.tokens + SMOOTH * (lex.types + 1)))
    return whole.select(
        "doc_id",
        "learned",
        "n_tokens",
        (F.col("n_known") + F.coalesce("rare_known", F.lit(0))).alias("n_known"),
        F.lit(lex.tokens).cast("long").alias("train_tokens"),
        (F.col("base") + zero - F.col("n_tokens") * z).alias("base_score"),
        (F.col("score") + zero).alias("score"),
    )
