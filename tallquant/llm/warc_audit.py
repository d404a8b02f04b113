"""WARC replicas and their Merkle fixity audit.

A record is one WARC/1.0 response.  Records are kept in files of a fixed range of
identifiers, in ascending order, so each has an offset range in its file.  The
fixity tree hashes records (level 0) and, level by level, the ordered ranges of
``fan`` neighbours up to one file, then runs of files, then the whole replica;
every node has its digest, its records and the octets that it covers.  Two
replicas are compared from the root: only children of mismatching nodes are read
at the next level, until the damaged, missing or surplus records are named.

Null url or html count as empty; line breaks in a url are percent-encoded; equal
rows are one record with a number of copies; rows of one identifier with different
content are separate records, ordered by digest; null identifiers share a file.
Identifiers (or null) with more different rows than a file holds have their
records dealt by digest to files of their own, as many as it takes, so no file,
window or node grows with one identifier.  A damaged record without an identifier
is reported as one missing and one extra.  An empty replica has an empty tree;
columns other than page_id, url and html are ignored.
"""

from __future__ import annotations

import gzip
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window
from pyspark.sql import functions as F

from tallquant.llm.common import Workspace, as_bytes, filesystem, publish

FILE_IDS, FAN, SHELF, WING = 1024, 16, 256, 4096
NO_ID_FILE = -(1 << 40)


def _header(url, record_id, length):
    return F.concat(
        F.lit("WARC/1.0\r\nWARC-Type: response\r\nWARC-Target-URI: "), url,
        F.lit("\r\nWARC-Record-ID: <urn:page:"), F.coalesce(record_id.cast("string"), F.lit("")),
        F.lit(">\r\nContent-Type: text/html\r\nContent-Length: "), length.cast("string"), F.lit("\r\n\r\n"),
    )


def warc_records(pages: DataFrame) -> DataFrame:
    """``record_id, url, body, record``: the page as the text of a WARC record."""
    url, body = F.coalesce("url", F.lit("")), F.coalesce("html", F.lit(""))
    url = F.replace(F.replace(url, F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    record = F.concat(_header(url, F.col("page_id"), F.octet_length(body)), body, F.lit("\r\n\r\n"))
    return pages.select(F.col("page_id").cast("long").alias("record_id"), url.alias("url"), body.alias("body"), record.alias("record"))


class Shelving:
    """Which file a record belongs to: the range of its identifier, or overflow files for crowded identifiers.

    Made from one replica and used for all, so that equal records meet.
    """

    def __init__(self, records: DataFrame, work: Workspace, most: int = FILE_IDS):
        counts = records.groupBy("record_id").agg(F.count("*").alias("n")).where(F.col("n") > most)
        self.crowded = work.save(counts, "crowded")
        n = self.crowded.agg(F.sum("n")).first()[0] or 0
        self.files = -(-n // most)

    def place(self, records: DataFrame, digest) -> DataFrame:
        """The records with ``file`` and ``slot``."""
        in_range = F.coalesce(F.floor(F.col("record_id") / FILE_IDS), F.lit(NO_ID_FILE).cast("long"))
        slot = F.coalesce(F.pmod("record_id", F.lit(FILE_IDS)), F.lit(0))
        if not self.files:
            return records.withColumns({"file": in_range, "slot": slot})
        own = self.crowded.select(F.col("record_id").alias("crowded_id"), F.lit(True).alias("crowded"))
        dealt = F.xxhash64("record_id", digest)
        both = records.join(own, F.col("record_id").eqNullSafe(F.col("crowded_id")), "left")
        file = F.when(F.col("crowded"), NO_ID_FILE - 1 - F.pmod(dealt, F.lit(self.files))).otherwise(in_range)
        slot = F.when(F.col("crowded"), F.pmod(F.shiftright(dealt, 32), F.lit(FILE_IDS))).otherwise(slot)
        return both.withColumns({"file": file.cast("long"), "slot": slot.cast("long")}).drop("crowded_id", "crowded")


def write_replica(pages: DataFrame, work: Workspace, name: str, damage: Callable[[DataFrame], DataFrame] | None = None, shelving: Shelving | None = None) -> DataFrame:
    """Write ``.warc.gz`` files, one member a record, and return their names.

    ``damage`` changes the records (as :func:`warc_records` gives them) on the way
    to the disk, to rehearse an audit.
    """
    records = warc_records(pages)
    shelving = shelving or Shelving(records, work)
    records = damage(records) if damage else records
    root = work.path(name)
    fs, path = filesystem(root)
    fs.create_dir(path, recursive=True)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, temp, out, names = None, "", None, []

        def close() -> None:
            if out:
                out.close()
                publish(fs, temp, f"{path}/{now}.warc.gz")
                names.append(f"{root}/{now}.warc.gz")

        fs, path = filesystem(root)
        for batch in batches:
            for file, raw in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)), strict=True):
                if file != now:
                    close()
                    now, temp = file, f"{path}/{file}.{uuid.uuid4().hex}.tmp"
                    out = fs.open_output_stream(temp)
                out.write(gzip.compress(raw, 1, mtime=0))
        close()
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string())], names=["file"])

    keyed = shelving.place(records, F.sha2("record", 256)).select("file", "record", "record_id")
    ordered = keyed.repartition("file").sortWithinPartitions("file", "record_id", "record").select("file", "record")
    return work.save(ordered.mapInArrow(write, "file string"), f"{name}-files")


def read_replica(files: DataFrame) -> DataFrame:
    """``record_id, url, body, record`` from WARC files, one at a time in each task."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri in batch.column(0).to_pylist():
                fs, path = filesystem(uri)
                with fs.open_input_file(path) as f:
                    stream = gzip.GzipFile(fileobj=f)
                    rows: list[tuple] = []
                    for row in parse_records(stream):
                        rows.append(row)
                        if len(rows) >= 512:
                            yield _rows(rows)
                            rows = []
                    yield _rows(rows)

    return files.repartition(max(1, min(files.count(), 10_000)), "file").mapInArrow(read, "record_id long, url string, body string, record string")


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int64(), pa.string(), pa.string(), pa.string()), strict=True)], names=["record_id", "url", "body", "record"])


def parse_records(stream) -> Iterator[tuple[int | None, str, str, str]]:
    """Records of an uncompressed WARC stream."""
    while True:
        head = []
        line = stream.readline()
        if not line:
            return
        while line.strip():
            head.append(line)
            line = stream.readline()
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.decode("utf-8", "replace").partition(":") for x in head[1:])}
        body = stream.read(int(fields["content-length"]))
        tail = stream.read(4)
        name = fields["warc-record-id"].removeprefix("<urn:page:").removesuffix(">")
        raw = b"".join(head) + b"\r\n" + body + tail
        yield int(name) if name else None, fields["warc-target-uri"], body.decode("utf-8", "replace"), raw.decode("utf-8", "replace")


class FixityTree:
    """Levels of one replica, each a saved table ``parent, node, digest, n_records, octets``."""

    def __init__(self, records: DataFrame, work: Workspace, name: str, shelving: Shelving):
        leaf = records.select("record_id", F.sha2("record", 256).alias("digest"), F.octet_length("record").cast("long").alias("octets"))
        leaf = leaf.groupBy("record_id", "digest", "octets").agg(F.count("*").alias("copies"))
        order = Window.partitionBy("file").orderBy(F.col("record_id").asc_nulls_first(), "digest")
        size = F.col("octets") * F.col("copies")
        self.leaves = work.save(
            shelving.place(leaf, F.col("digest")).withColumn("start", F.sum(size).over(order) - size)
            .select("file", (F.col("slot") / FAN).cast("long").alias("slot"), "record_id", "digest", "octets", "copies", "start"),
            f"{name}-leaves",
        )
        part = F.struct(F.col("record_id").alias("key"), "digest", F.col("copies").alias("n"), (F.col("octets") * F.col("copies")).alias("octets"))
        self.levels: list[DataFrame] = []
        level = self._fold(self.leaves.select("file", "slot", part.alias("part")), ["file", "slot"])
        self.levels.append(work.save(level, f"{name}-0"))
        slots = FILE_IDS // FAN
        while slots > 1:
            slots = -(-slots // FAN)
            level = self._fold(self._up(level, "file", F.col("slot").alias("key"), (F.col("slot") / FAN).cast("long").alias("slot")), ["file", "slot"])
            self.levels.append(work.save(level, f"{name}-{len(self.levels)}"))
        for width in (SHELF, WING, None):
            above = F.floor(F.col("file") / width) if width else F.lit(0).cast("long")
            level = self._fold(self._up(self.levels[-1], above.alias("file"), F.col("file").alias("key"), F.lit(0).cast("long").alias("slot")), ["file", "slot"])
            self.levels.append(work.save(level, f"{name}-{len(self.levels)}"))

    @staticmethod
    def _up(level: DataFrame, file, key, slot) -> DataFrame:
        return level.select(file, slot, F.struct(key, "digest", "n", "octets").alias("part"))

    @staticmethod
    def _fold(parts: DataFrame, by: list[str]) -> DataFrame:
        """One node for each group of neighbours: the digest of its ordered children."""
        children = F.sort_array(F.collect_list("part"))
        text = F.array_join(F.transform(children, lambda c: F.concat_ws(":", F.coalesce(c["key"].cast("string"), F.lit("")), c["digest"], c["n"].cast("string"), c["octets"].cast("string"))), ";")
        return parts.groupBy(*by).agg(F.sha2(text, 256).alias("digest"), F.sum("part.n").alias("n"), F.sum("part.octets").alias("octets"))

    def root(self) -> str | None:
        row = self.levels[-1].first()
        return row.digest if row else None


def _differing(a: DataFrame, b: DataFrame, bad: DataFrame | None, above) -> DataFrame:
    """Nodes of one level that differ, among the children of the bad nodes above."""
    if bad is not None:
        near = bad.select(F.col("file").alias("up_file"), F.col("slot").alias("up_slot"))
        a, b = (x.join(near, [above[0] == F.col("up_file"), above[1] == F.col("up_slot")], "left_semi") for x in (a, b))
    a, b = a.alias("a"), b.alias("b")
    both = a.join(b, ["file", "slot"], "full")
    return both.where(~F.col("a.digest").eqNullSafe(F.col("b.digest"))).select("file", "slot")


def audit(spark: SparkSession, primary: DataFrame, replica: DataFrame, work: Workspace, shelving: Shelving | None = None) -> tuple[DataFrame, FixityTree, list[int]]:
    """Compare two replicas; returns the bad records, the primary's tree and the nodes that differ by level, root first.

    Bad records: ``record_id, digest, found, status`` with status ``corrupt``
    (content differs), ``missing`` or ``extra``.
    """
    shelving = shelving or Shelving(primary, work)
    one, two = (FixityTree(x, work, n, shelving) for x, n in ((primary, "primary"), (replica, "replica")))
    bad, counts, top = None, [], len(one.levels) - 1
    zero = F.lit(0).cast("long")
    for k in range(top, -1, -1):
        if k == top - 1:
            above = (zero, zero)
        elif k == top - 2:
            above = (F.floor(F.col("file") / WING), zero)
        elif k == top - 3:
            above = (F.floor(F.col("file") / SHELF), zero)
        else:
            above = (F.col("file"), (F.col("slot") / FAN).cast("long"))
        bad = work.save(_differing(one.levels[k], two.levels[k], bad, above), f"bad-{k}")
        counts.append(bad.count())
        if not counts[-1]:
            break
    if not counts[-1]:
        return spark.createDataFrame([], "record_id long, digest string, found string, status string"), one, counts
    a, b = (x.leaves.join(bad, ["file", "slot"], "left_semi").select("record_id", "digest", "copies") for x in (one, two))
    turn = F.row_number().over(Window.partitionBy("record_id").orderBy("digest", "copies"))
    a, b = (_without(x, y, ["record_id", "digest", "copies"]).withColumn("turn", turn).alias(n) for x, y, n in ((a, b, "a"), (b, a, "b")))
    status = F.when(F.col("b.digest").isNull(), "missing").when(F.col("a.digest").isNull(), "extra").otherwise("corrupt")
    pairs = a.join(b, ["record_id", "turn"], "full")  # null identifiers meet nothing
    out = pairs.select("record_id", F.col("a.digest").alias("digest"), F.col("b.digest").alias("found"), status.alias("status"))
    return work.save(out, "found"), one, counts


def _without(a: DataFrame, b: DataFrame, columns: list[str]) -> DataFrame:
    """Rows of ``a`` that ``b`` does not have."""
    a, b = a.alias("a"), b.alias("b")
    return a.join(b, F.expr(" AND ".join(f"a.{c} <=> b.{c}" for c in columns)), "left_anti")


def audit_report(spark: SparkSession, pages: DataFrame, damage: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Write a replica of pages, read it back and audit it: a row for every record with its place, digest and status."""
    work = Workspace(spark, "warc")
    records = warc_records(pages)
    shelving = Shelving(records, work)
    replica = read_replica(write_replica(pages, work, "copy", damage, shelving))
    bad, tree, _ = audit(spark, records, replica, work, shelving)
    rows = tree.leaves.alias("l").join(bad.alias("b"), F.expr("l.record_id <=> b.record_id AND l.digest = b.digest"), "full")
    return rows.select(
        F.coalesce("l.record_id", "b.record_id").alias("page_id"), F.col("file").alias("warc_file"), F.col("start").alias("record_offset"), F.col("octets").alias("record_octets"),
        F.col("l.digest").alias("sha256"), F.coalesce("status", F.lit("ok")).alias("status"),
    )
