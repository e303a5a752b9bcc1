"""Removal of repeated word windows with a log-structured index of fingerprints.

Of every window of ``WINDOW`` words one 8-word piece is its anchor: the piece of smallest
hash, leftmost on ties.  Equal windows have equal anchors at the same place, so only windows
whose anchor hash occurs at two places can repeat.  Neighbouring windows share their anchor;
an entry (fingerprint, document, first window, last window) stands for all of them.

The index holds fingerprints in immutable runs: distinct, bucketed by fingerprint and sorted.
Each batch becomes a run and is merge-joined with the older runs, bucket by bucket, without
moving those; what both hold is shared.  When ``FANOUT`` runs of one level have gathered they are merged
into one.  A hot passage is one row of a run, however many documents have it.  The index lives on a path: a
manifest names its complete runs and the entries of their batches, so that a later call, in another
session, opens it and joins the next batch with all that came before.  A run counts once the manifest that names
it is written; what a lost driver left behind is not read.

Windows with a shared fingerprint are then verified: within a fingerprint, two independent 64-bit hashes
of all 35 words are compared, 128 bits in all (at 2e13 windows a false equal has probability below 1e-11).
Windows that repeat inside a task's slice are decided there and only one of each
goes on, so the most frequent window costs one row a slice.

Defined cases: null text has no words; documents of fewer than ``WINDOW`` words lose nothing;
a row that repeats an id and its text is another occurrence, so both lose what they share; rows
with a null id lose nothing; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bitmap import bit_table, lacks, may_contain
from .scratch import Scratch, delete
from .words import Words, gram_hashes, mix, ranges, slices, split, word_hashes

WINDOW = 35
ANCHOR = 8
BATCHES = 3
FANOUT = 4
BUCKET_ROWS = 2_000_000
REGION_WINDOWS = 1_500_000
ENTRIES = "fp bigint, doc bigint, lo int, hi int"
_MANIFEST = "kind string, name string, level int, place int, buckets int"
_U = np.uint64
_SECOND = (_U(0x2545F4914F6CDD1D), _U(0xA0761D6478BD642F))  # bases of the second hash


def _entries(h: np.ndarray, docs: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """fingerprint, document, first and last window (words from the document's start) of every anchor."""
    g = gram_hashes(h, ANCHOR)
    width = window - ANCHOR + 1
    value, place, span = g, np.arange(len(g)), 1

    def least(step: int) -> None:
        nonlocal value, place
        a, b = value[:-step], value[step:]
        left = a <= b
        value, place = np.where(left, a, b), np.where(left, place[:-step], place[step:])

    while span < width and len(value):
        step = min(span, width - span)
        if step >= len(value):
            value = value[:0]
            break
        least(step)
        span += step
    n = np.maximum(np.diff(docs) - window + 1, 0)
    doc = np.repeat(np.arange(len(n)), n)
    start = ranges(docs[:-1][n > 0], n[n > 0])
    if not len(start):
        z = np.zeros(0, np.int64)
        return np.zeros(0, _U), z, z, z
    at, fp = place[start], value[start]
    new = np.r_[True, (at[1:] != at[:-1]) | (doc[1:] != doc[:-1])]
    first = np.flatnonzero(new)
    last = np.r_[first[1:], len(start)] - 1
    base = docs[doc[first]]
    return mix(fp[first]), doc[first], start[first] - base, start[last] - base


def _anchors(window: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, col in slices(batch):
                w = split(col)
                fp, doc, lo, hi = _entries(word_hashes(w), w.docs, window)
                yield pa.RecordBatch.from_arrays([pa.array(fp.view(np.int64)), rows.column(0).take(pa.array(doc)), pa.array(lo.astype(np.int32)), pa.array(hi.astype(np.int32))], ["fp", "doc", "lo", "hi"])

    return run


class FingerprintIndex:
    """Sorted immutable runs of distinct fingerprints on a path; ``n`` is how often each occurred so far in its run."""

    def __init__(self, spark: SparkSession, path: str, buckets: int):
        self.spark, self.path, self.buckets = spark, path.rstrip("/"), buckets
        self.runs: list[tuple[str, int]] = []  # name, level
        self.batches: list[str] = []  # entries of every batch
        self.version = 0

    @classmethod
    def open(cls, spark: SparkSession, path: str, buckets: int = 8) -> FingerprintIndex:
        """The index on a path as its last manifest has it; a new one (with so many buckets) where there is none."""
        index = cls(spark, path, buckets)
        folder = spark._jvm.org.apache.hadoop.fs.Path(f"{index.path}/manifest")
        fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
        if fs.exists(folder):
            made = [int(x.getPath().getName()) for x in fs.listStatus(folder) if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
            if made:
                index.version = max(made)
                rows = spark.read.schema(_MANIFEST).json(f"{index.path}/manifest/{index.version}").collect()
                index.buckets = rows[0]["buckets"]
                index.runs = [(x["name"], x["level"]) for x in sorted(rows, key=lambda x: x["place"]) if x["kind"] == "run"]
                index.batches = [x["name"] for x in sorted(rows, key=lambda x: x["place"]) if x["kind"] == "batch"]
                for name, _ in index.runs:
                    index._register(name)
        return index

    def _register(self, name: str) -> None:
        """A name in this session's catalogue for a run's files, so that their buckets are known."""
        self.spark.sql(f"CREATE TABLE IF NOT EXISTS {name} (fp BIGINT, n BIGINT) USING parquet CLUSTERED BY (fp) SORTED BY (fp) INTO {self.buckets} BUCKETS LOCATION '{self.path}/{name}'")

    def _commit(self) -> None:
        self.version += 1
        rows = [("run", name, level, i, self.buckets) for i, (name, level) in enumerate(self.runs)] + [("batch", name, 0, i, self.buckets) for i, name in enumerate(self.batches)]
        self.spark.createDataFrame(rows, _MANIFEST).coalesce(1).write.mode("overwrite").json(f"{self.path}/manifest/{self.version}")

    def _store(self, rows: DataFrame) -> str:
        name = f"semjoin_run_{uuid.uuid4().hex[:12]}"
        rows.repartition(self.buckets, "fp").write.bucketBy(self.buckets, "fp").sortBy("fp").option("path", f"{self.path}/{name}").saveAsTable(name)
        return name

    def entries(self) -> list[DataFrame]:
        """(fp, doc, lo, hi) of every batch so far."""
        return [self.spark.read.schema(ENTRIES).parquet(f"{self.path}/{name}") for name in self.batches]

    def ingest(self, entries: DataFrame) -> list[DataFrame]:
        """Adds a batch; returns tables of fingerprints that are shared within it or with older runs."""
        spark, batch = self.spark, f"batch_{uuid.uuid4().hex[:12]}"
        entries.write.parquet(f"{self.path}/{batch}")
        entries = spark.read.schema(ENTRIES).parquet(f"{self.path}/{batch}")
        name = self._store(entries.groupBy("fp").agg(F.count("*").alias("n")))
        new = spark.table(name)
        shared = [new.where("n > 1").select("fp")]
        shared += [new.select("fp").join(spark.table(old).select("fp"), "fp", "left_semi") for old, _ in self.runs]
        for i, x in enumerate(shared):
            x.write.parquet(f"{self.path}/shared/{batch}-{i}")
        self.runs.append((name, 0))
        self.batches.append(batch)
        gone = self.compact()
        self._commit()
        for old in gone:
            self._forget(old)
        return [spark.read.schema("fp bigint").parquet(f"{self.path}/shared/{batch}-{i}") for i in range(len(shared))]

    def compact(self) -> list[str]:
        """Merges the youngest runs when ``FANOUT`` of one level have gathered; returns those that are merged."""
        gone = []
        while len(last := [x for x in self.runs if x[1] == self.runs[-1][1]]) >= FANOUT:
            merged = self.spark.table(last[0][0])
            for name, _ in last[1:]:
                merged = merged.union(self.spark.table(name))
            made = self._store(merged.groupBy("fp").agg(F.sum("n").alias("n")))
            self.runs = [x for x in self.runs if x not in last] + [(made, last[0][1] + 1)]
            gone += [name for name, _ in last]
        return gone

    def _forget(self, name: str) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {name}")
        delete(self.spark, f"{self.path}/{name}")

    def close(self) -> None:
        """Takes the names out of the session's catalogue; the files stay."""
        for name, _ in self.runs:
            self.spark.sql(f"DROP TABLE IF EXISTS {name}")


def _spans(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, first and second field of a column of lists of (long, long, ...) structs."""
    flat = column.flatten()
    return np.repeat(np.arange(len(column)), np.diff(np.asarray(column.offsets))), *(np.asarray(flat.field(i)).astype(np.int64) for i in range(flat.type.num_fields))


def _covers(mark: np.ndarray, window: int, starts: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word ranges that the marked windows (sorted by document and start) cover, by document."""
    s, d = starts[mark], doc[mark]
    if not len(s):
        z = np.zeros(0, np.int64)
        return z, z, z
    new = np.flatnonzero(np.r_[True, (d[1:] != d[:-1]) | (s[1:] > s[:-1] + window)])
    last = np.r_[new[1:], len(s)] - 1
    return d[new], s[new], s[last] + window


def _windows(window: int, bits: int):
    """Hashes of the candidate windows, packed by fingerprint range; ranges already decided go along under parts below 0."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn = 0
        for batch in batches:
            for rows, col in slices(batch):
                w = split(col)
                g = gram_hashes(word_hashes(w), window)
                g2 = gram_hashes(word_hashes(w, _SECOND[0]), window, _SECOND[1])
                ids = np.asarray(rows.column(0))
                doc, fp, lo, hi = _spans(rows.column(rows.schema.get_field_index("spans")))
                ok = w.docs[doc] + hi + window <= w.docs[doc + 1]  # spans of another row with this id
                doc, fp, lo, hi = doc[ok], fp[ok].view(_U), lo[ok], hi[ok]
                order = np.lexsort((lo, doc))
                doc, fp, lo, hi = doc[order], fp[order], lo[order], hi[order]
                size = hi - lo + 1
                start, of, key = ranges(lo, size), np.repeat(doc, size), np.repeat(fp, size)
                if not len(start):
                    continue
                place = start + w.docs[of]
                h, h2 = mix(g[place] ^ key), g2[place]
                first, count = _distinct(h, h2)
                lone = np.zeros(len(h), bool)
                lone[first] = True  # one of each goes on
                many = np.zeros(len(h), bool)
                many[first] = count > 1
                lone_once = lone.copy()
                lone_once[first[count > 1]] = False
                d, a, b = _covers(~lone_once, window, start, of)
                turn += 1
                if len(d):
                    yield _packed([-1 - turn % (1 << bits)], [np.concatenate([ids[d], a, b]).tobytes()])
                send = np.flatnonzero(lone)
                part = (key[send] >> _U(64 - bits)).astype(np.int64) if bits else np.zeros(len(send), np.int64)
                by = np.argsort(part, kind="stable")
                send, part = send[by], part[by]
                cuts = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]).tolist() + [len(part)]
                where = start * 2 + many  # the flag rides in the lowest bit
                data = [h[send[x:y]].tobytes() + h2[send[x:y]].tobytes() + np.diff(ids[of[send[x:y]]], prepend=0).tobytes() + where[send[x:y]].astype(np.int32).tobytes() for x, y in zip(cuts, cuts[1:])]
                yield _packed(part[cuts[:-1]], data)

    return run


def _distinct(h: np.ndarray, h2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index of one of each distinct pair, and how often it occurs."""
    order = np.lexsort((h2, h))
    a, b = h[order], h2[order]
    first = np.flatnonzero(np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
    return order[first], np.diff(np.r_[first, len(h)])


def _packed(part, data) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.asarray(part, np.int32)), pa.array(data, pa.binary())], ["part", "data"])


def _repeated(window: int):
    """Word ranges covered by windows that occur twice: (doc, a, b)."""

    def out(d, a, b):
        for lo in range(0, len(d), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[lo : lo + 100_000]) for x in (d, a, b)], ["doc", "a", "b"])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, seconds, docs, wheres = [], [], [], []
        for batch in batches:
            for part, x in zip(batch.column(0).to_pylist(), batch.column(1)):
                raw = x.as_buffer()
                if part < 0:
                    d = np.frombuffer(raw, np.int64).reshape(3, -1)
                    yield from out(d[0], d[1], d[2])
                    continue
                n = raw.size // 28
                hashes.append(np.frombuffer(raw, _U, n))
                seconds.append(np.frombuffer(raw, _U, n, 8 * n))
                docs.append(np.cumsum(np.frombuffer(raw, np.int64, n, 16 * n)))
                wheres.append(np.frombuffer(raw, np.int32, n, 24 * n))
        if not hashes:
            return
        h, h2, doc, where = np.concatenate(hashes), np.concatenate(seconds), np.concatenate(docs), np.concatenate(wheres)
        del hashes, seconds, docs, wheres
        order = np.lexsort((h2, h))
        h, h2 = h[order], h2[order]
        first = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (h2[1:] != h2[:-1])])
        size = np.diff(np.r_[first, len(h)])
        del h, h2
        # Those met twice in their slice are marked there already; others are marked here.
        again = order[np.repeat(size > 1, size)]
        again = again[(where[again] & 1) == 0]
        doc, start = doc[again], where[again].astype(np.int64) >> 1
        by = np.lexsort((start, doc))
        yield from out(*_covers(slice(None), window, start[by], doc[by]))

    return run


def _finish(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for rows, col in slices(batch):
            w: Words = split(col)
            removed = np.zeros(w.n, bool)
            if (at := rows.schema.get_field_index("spans")) >= 0:
                doc, a, b = _spans(rows.column(at))
                step = np.zeros(w.n + 1, np.int64)
                end = w.docs[doc + 1]
                np.add.at(step, np.minimum(w.docs[doc] + a, end), 1)
                np.add.at(step, np.minimum(w.docs[doc] + b, end), -1)
                removed = np.cumsum(step[:-1]) > 0
            size = np.diff(w.at)[~removed] + 1
            ends = np.concatenate([[0], np.cumsum(size)])
            text = np.full(ends[-1], 32, np.uint8)
            inner = np.ones(len(text), bool)
            inner[ends[1:] - 1] = False
            text[inner] = w.data[np.repeat(~removed, np.diff(w.at))]
            kept = np.concatenate([[0], np.cumsum(~removed)])[w.docs]
            cut = ends[kept]
            digests = [hashlib.sha256(text[a : max(a, b - 1)]).hexdigest() for a, b in zip(cut[:-1].tolist(), cut[1:].tolist())]
            n = np.diff(w.docs)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(n), pa.array(n - np.diff(kept)), pa.array(digests, pa.string())], [rows.schema.names[0], "n_words", "n_removed", "kept_sha256"])


def _union(tables: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.union, tables)


def _entries_of(docs: DataFrame, window: int) -> DataFrame:
    return docs.select("doc", "text").mapInArrow(_anchors(window), ENTRIES)


def _verified(docs: DataFrame, entries: list[DataFrame], shared: list[DataFrame], scratch: Scratch, window: int) -> DataFrame:
    """(doc, a, b) of windows whose anchor is shared and whose words are the same."""
    # Both sides of the join are written or scanned as they are, so that adaptive execution can split a hot fingerprint.
    fps = scratch.table(_union(shared).distinct(), "fps")
    some = [may_contain(e.where("doc is not null"), "fp", table) for table in [bit_table(fps, "fp")] for e in entries]
    mine = scratch.table(_union(some).join(fps, "fp", "left_semi"), "candidates")
    windows = mine.agg(F.sum(F.expr("hi - lo + 1"))).first()[0] or 0
    bits = max(4, int(windows / REGION_WINDOWS).bit_length())
    spans = mine.groupBy("doc").agg(F.collect_list(F.struct("fp", F.col("lo").cast("long").alias("lo"), F.col("hi").cast("long").alias("hi"))).alias("spans"))
    texts = may_contain(docs, "doc", bit_table(mine, "doc")).join(spans, "doc").select("doc", "text", "spans")
    packed = texts.mapInArrow(_windows(window, bits), "part int, data binary")
    return scratch.table(packed.repartition(1 << bits, "part").mapInArrow(_repeated(window), "doc bigint, a bigint, b bigint"), "ranges")


def repeated_ranges(docs: DataFrame, scratch: Scratch, window: int = WINDOW, batches: int = BATCHES) -> DataFrame:
    """(doc, a, b): ranges of words covered by windows that occur elsewhere; ``docs`` has doc and text.

    The documents come in ``batches`` by id, each indexed against those before it.
    """
    ids = docs.select("doc").where("doc is not null")
    cuts = (ids.agg(F.percentile_approx("doc", [i / batches for i in range(1, batches)], 1000)).first()[0] or []) if batches > 1 else []
    edges = [None, *sorted(set(cuts)), None]
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    # About one entry for 90 bytes.
    index, shared = FingerprintIndex(docs.sparkSession, f"{scratch.base}/index", max(8, (size // 90 // BUCKET_ROWS).bit_length() * 8)), []
    for lo, hi in zip(edges, edges[1:]):
        batch = docs
        if lo is not None:
            batch = batch.where(F.col("doc") > lo)
        if hi is not None:
            batch = batch.where((F.col("doc") <= hi) | (F.col("doc").isNull() if lo is None else F.lit(False)))
        shared += index.ingest(_entries_of(batch, window))
    found = _verified(docs, index.entries(), shared, scratch, window)
    index.close()
    return found


def ingest_batch(docs: DataFrame, history: DataFrame | None, path: str, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, buckets: int = 64) -> DataFrame:
    """Joins the next batch of documents with the index on ``path`` and adds it there.

    Returns (doc, a, b): word ranges covered by windows that occur twice and at least once in this batch, of the
    batch's documents and of those in ``history`` (all earlier batches; null for the first).  Their union over all
    batches is what ``repeated_ranges`` gives for all documents together.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "substrings")
    named = lambda df: df.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).alias("text"))
    index = FingerprintIndex.open(spark, path, buckets)
    shared = index.ingest(_entries_of(named(docs), window))
    every = named(docs) if history is None else named(history).union(named(docs))
    found = _verified(every, index.entries(), shared, scratch, window)
    index.close()
    return found


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, batches: int = BATCHES) -> DataFrame:
    """One row per document: id, n_words, n_removed, kept_sha256."""
    scratch = Scratch(docs.sparkSession, "substrings")
    rows = docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).alias("text"))
    found = repeated_ranges(rows, scratch, window, batches)
    spans = found.groupBy("doc").agg(F.collect_list(F.struct("a", "b")).alias("spans"))
    table = bit_table(found, "doc")
    out = f"`{id_col}` bigint, n_words bigint, n_removed bigint, kept_sha256 string"
    named = lambda df, *more: df.select(F.col("doc").alias(id_col), "text", *more)
    whole = named(lacks(rows, "doc", table)).mapInArrow(_finish, out)
    cut = may_contain(rows, "doc", table).join(spans, "doc", "left").withColumn("spans", F.coalesce("spans", F.array().cast("array<struct<a:bigint,b:bigint>>")))
    return whole.union(named(cut, "spans").mapInArrow(_finish, out))
