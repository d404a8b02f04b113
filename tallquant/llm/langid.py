"""Language identification by nearest clustered centroid.

A text is the TF-IDF vector of its letter trigrams, hashed to a fixed number of
dimensions and scaled to length one; what is not a letter counts as space.
Document frequencies are counted over all documents to learn from.  Each language
has several centroids, found by spherical k-means over about ``sample`` of its documents
(chosen by a hash; never more than twice as many).  The language of the nearest centroid by
cosine wins; a text that is further from it than any document that it was learned
from, with a margin that is wider for short texts, is rejected.

Null texts and texts without a letter are ``und``, with score 0 and rejected; so
is every text if there is nothing to learn from.  Ties go to the smaller language
name.  Rows with a null identifier are predicted and never learned from.  Extra
columns are carried only if ``keep`` names them.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallquant.llm.common import as_bytes, row_of, ship, text_slices, unfold, worker_cache

_LETTERS = bytes(b if b >= 128 or 97 <= b <= 122 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))
#: Upper ends of the length bands (in trigrams) that have a rejection floor each.
BANDS = (32, 128, 512)
UNKNOWN = "und"


def has_letter(raw: bytes | None) -> bool:
    if not raw:
        return False
    spaced = raw.translate(_LETTERS).strip()
    return bool(spaced) and (any(97 <= b <= 122 for b in spaced[:64]) or any(ch.isalpha() for ch in raw.decode()))


def trigram_counts(texts: list[bytes | None], dims: int) -> np.ndarray:
    """Counts of hashed trigrams, one row a text (float32)."""
    line = b"  " + b"  ".join((t or b"").translate(_LETTERS) for t in texts) + b"  "
    raw = np.frombuffer(line, dtype=np.uint8).astype(np.uint32)
    code = (raw[:-2] << np.uint32(16)) | (raw[1:-1] << np.uint32(8)) | raw[2:]
    blank = code == np.uint32(0x202020)
    code = (code * np.uint32(2654435761)) >> np.uint32(32 - int(dims).bit_length() + 1)
    code[blank] = dims
    ends = np.cumsum([len(t or b"") + 2 for t in texts])
    starts = np.concatenate(([0], ends[:-1]))
    out = np.empty((len(texts), dims), dtype=np.float32)
    for i, (a, b) in enumerate(zip(starts, ends, strict=True)):
        out[i] = np.bincount(code[a:b], minlength=dims + 1)[:dims]
    return out


def unit_vectors(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    v = np.log1p(counts) * idf
    return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)


def band_of(counts: np.ndarray) -> np.ndarray:
    return np.searchsorted(BANDS, counts.sum(axis=1), side="right")


def cluster(vectors: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """Spherical k-means from far-apart seeds."""
    centers = [vectors.mean(axis=0)]
    while len(centers) < min(k, len(vectors)):
        near = (vectors @ np.array(centers).T).max(axis=1)
        centers.append(vectors[int(near.argmin())])
    c = np.array(centers)
    for _ in range(rounds):
        owner = (vectors @ c.T).argmax(axis=1)
        for j in range(len(c)):
            if (owner == j).any():
                c[j] = vectors[owner == j].mean(axis=0)
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


@dataclass
class Model:
    """Centroids with their languages, IDF, and the rejection floor of each centroid and length band."""

    langs: list[str]
    centers: np.ndarray
    floors: np.ndarray
    idf: np.ndarray

    def predict(self, texts: list[bytes | None]) -> tuple[list[str], list[float], list[bool]]:
        langs, scores, rejected = [], [], []
        counts = trigram_counts(texts, len(self.idf))
        if not self.langs:
            return [UNKNOWN] * len(texts), [0.0] * len(texts), [True] * len(texts)
        cosine = unit_vectors(counts, self.idf) @ self.centers.T
        best, bands = cosine.argmax(axis=1), band_of(counts)
        for i, text in enumerate(texts):
            if not has_letter(text):
                langs.append(UNKNOWN)
                scores.append(0.0)
                rejected.append(True)
            else:
                s = float(min(1.0, max(0.0, cosine[i, best[i]])))
                langs.append(self.langs[best[i]])
                scores.append(s)
                rejected.append(s < self.floors[best[i], bands[i]])
        return langs, scores, rejected


def learn(spark: SparkSession, docs: DataFrame, learns, *, dims: int = 4096, centroids: int = 4, sample: int = 400, margin: float = 0.5) -> Model:
    """Fit on the rows of ``docs(doc_id, text, lang)`` where the condition ``learns`` holds.

    ``sample`` bounds the documents of each language that centroids are fitted
    on; document frequencies cover every row.  The languages are few: their sizes
    and centroids come to the driver.
    """
    ship(spark)
    rows = docs.where(learns & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())

    def frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        worker_cache("langid")
        df, n = np.zeros(dims, dtype=np.int64), 0
        for batch in batches:
            texts = as_bytes(batch.column(0))
            for a, b in text_slices(texts, 2_000_000):
                for start in range(a, b, 512):
                    df += (trigram_counts(texts[start : min(b, start + 512)], dims) > 0).sum(axis=0)
            n += len(texts)
        yield pa.RecordBatch.from_arrays([pa.array([*range(dims), -1], pa.int32()), pa.array([*df.tolist(), n], pa.int64())], names=["slot", "n"])

    counted = {r.slot: r.n for r in rows.select("text").mapInArrow(frequencies, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).collect()}
    total = counted.pop(-1, 0)
    idf = np.array([np.log((1 + total) / (1 + counted.get(j, 0))) + 0.05 for j in range(dims)], dtype=np.float32)

    # about ``sample`` different rows of each language, by a hash: the scan drops the others, and repeated rows are one
    fine, key = 1 << 30, F.xxhash64("doc_id", "text")
    sizes = {r.lang: r.size for r in rows.groupBy("lang").agg(F.approx_count_distinct(key, 0.02).alias("size")).collect()}
    limits = F.create_map(*[F.lit(x) for lang, n in sorted(sizes.items()) for x in (lang, int(min(fine, fine * sample // n)))]) if sizes else F.create_map(F.lit(""), F.lit(0))
    chosen = rows.where(F.pmod(key, F.lit(fine)) < limits[F.col("lang")]).select("doc_id", "text", "lang").distinct()

    def fit(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["doc_id", "text"], kind="stable").head(2 * sample)
        counts = np.concatenate([trigram_counts([t.encode() for t in part.text[i : i + 128]], dims) for i in range(0, len(part), 128)])
        vectors = unit_vectors(counts, idf)
        centers = cluster(vectors, centroids)
        best = (vectors @ centers.T).max(axis=1)
        # the furthest document that was learned from, with a margin; few trigrams say less, so short texts get more
        floors = [margin * float(best.min()) * (0.5 if b < 2 else 1.0) for b in range(len(BANDS) + 1)]
        return pd.DataFrame({"lang": part.lang.iloc[0], "center": [c.tolist() for c in centers], "floors": [floors] * len(centers)})

    fitted = chosen.groupBy("lang").applyInPandas(fit, "lang string, center array<float>, floors array<double>").collect()
    fitted.sort(key=lambda r: (r.lang, r.center))
    return Model([r.lang for r in fitted], np.array([r.center for r in fitted], dtype=np.float32).reshape(len(fitted), dims), np.array([r.floors for r in fitted]).reshape(len(fitted), len(BANDS) + 1), idf)


def identify(spark: SparkSession, docs: DataFrame, model: Model, *, keep: list[str]) -> DataFrame:
    """The columns in ``keep`` with ``lang_pred, score, rejected``; a kept column of one of these names gets ``_in`` behind it."""
    ship(spark)
    cast, with_text = spark.sparkContext.broadcast(model), "text" in keep

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        worker_cache("langid")
        for batch in batches:
            texts = as_bytes(batch.column(1))
            langs, scores, rejected = [], [], []
            for a, b in text_slices(texts, 2_000_000):
                for start in range(a, b, 512):
                    for out, x in zip((langs, scores, rejected), cast.value.predict(texts[start : min(b, start + 512)]), strict=True):
                        out += x
            out = [batch.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(rejected, pa.bool_()), *[batch.column(1)] * with_text]
            yield pa.RecordBatch.from_arrays(out, names=["own", "lang_pred", "score", "rejected", *["own_text"] * with_text])

    frame = docs.select(row_of(keep).alias("own"), "text")
    schema = T.StructType([frame.schema["own"], *T._parse_datatype_string("lang_pred string, score double, rejected boolean" + ", own_text string" * with_text).fields])
    return unfold(frame.mapInArrow(run, schema), keep)
