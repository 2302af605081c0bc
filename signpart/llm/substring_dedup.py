"""Deduplication of long passages with a log-structured fingerprint index.

A window is ``width`` consecutive words.  Storing every window of the corpus costs
far more than the corpus, so windows are grouped first: each window has an anchor,
the first of its least ``gram``-word hashes, and neighbouring windows with one
anchor form a segment.  Equal windows have equal anchors at equal distances, so
whatever is shared is found among the segments of one anchor value.

Documents arrive in batches of rising doc_id.  The index holds sorted immutable
runs of (anchor, digest of the segment's words, doc_id), each key once, with the
first document that had it.  The segments of a batch are merge-joined with all runs
before: a segment that is there, or in a smaller document of the batch, is removed
whole, and what is new becomes a run.  Runs are compacted as soon as a level has
``fanout`` of them.  Anchors are rolling hashes; the digest that verifies a match is
taken from the bytes of the words themselves and has 128 bits.  Only where one
anchor value has several different segments are the windows compared, by the same
digest, and there only those of the first document of each segment: all windows of
any other document with that segment are removed anyway.

Defined cases: a null or empty text has no words; a text of fewer than ``width``
words has no window; rows with equal doc_id don't remove each other's words; rows
with null doc_id neither lose words nor cause losses; repeated passages in one
document stay unless a smaller document has them; an empty table gives an empty
result; columns of the input called ``n_words`` or ``n_removed`` are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from signpart.llm import hashing, store
from signpart.llm.arrowmap import arrow_map, with_columns

WIDTH, GRAM = 50, 10

_SEGMENT = "batch int, doc_id long, row long, at int, n int, anchor long, g1 long, g2 long"
_WINDOW = "doc_id long, row long, at int, h1 long, h2 long"
_RUN = "anchor long, g1 long, g2 long, doc_id long"


def _plain(data: np.ndarray, offsets: np.ndarray) -> tuple[bytes, np.ndarray]:
    """The rows with their words joined by one space each, so that equal runs of words have equal bytes."""
    rows = [b" ".join(data[a:b].tobytes().split()) for a, b in zip(offsets, offsets[1:])]
    return b"".join(rows), np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)


def _digests(data: bytes, begin: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128-bit digests of byte ranges, as two arrays of longs."""
    digest = xxhash.xxh3_128_digest
    both = np.frombuffer(b"".join([digest(data[a:b]) for a, b in zip(begin.tolist(), stop.tolist())]), dtype="<i8").reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _first_least(value: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """(least value, its first position) of each run of ``span`` values."""
    place, size = np.arange(len(value), dtype=np.int64), 1
    while size < span:
        step = min(size, span - size)
        a, b = value[:-step], value[step:]
        later = b < a
        value, place = np.where(later, b, a), np.where(later, place[step:], place[:-step])
        size += step
    return value, place


def segments_of(data: np.ndarray, offsets: np.ndarray, width: int, gram: int) -> tuple[np.ndarray, ...] | None:
    """(row, first window as a word number in the row, windows, anchor, digest as two longs) of all segments."""
    text, offsets = _plain(data, offsets)
    start, end, first = hashing.word_spans(np.frombuffer(text, np.uint8), offsets)
    n = len(start)
    if n < width or not (np.diff(first) >= width).any():
        return None
    words = hashing.span_hashes(np.frombuffer(text, np.uint8), start, end)
    at = np.arange(n - gram + 1)
    value, place = _first_least(hashing.run_hashes(words, at, at + gram), width - gram + 1)
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(first))[: len(value)]
    valid = np.arange(len(value)) + width <= first[row + 1]
    new = valid.copy()
    new[1:] &= ~valid[:-1] | (place[1:] != place[:-1]) | (row[1:] != row[:-1])
    head = np.flatnonzero(new)
    if not len(head):
        return None
    windows = np.add.reduceat(valid, head, dtype=np.int64)
    g1, g2 = _digests(text, start[head], end[head + windows + width - 2])
    return row[head], head - first[row[head]], windows, value[head], g1, g2


def _rows(docs: DataFrame) -> DataFrame:
    """(doc_id, row, text) of documents with a doc_id; ``row`` is a key of the content, so that rows with one doc_id stay apart."""
    return docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), _row_key().alias("row"), "text")


def _row_key() -> Column:
    return F.xxhash64("doc_id", "text")


def segments(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, batch: Column | None = None) -> DataFrame:
    """The segments of all documents with a doc_id; ``batch`` is a function of doc_id."""

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in batches:
            ids, keys, numbers = (np.asarray(part.column(i).to_numpy(zero_copy_only=False)) for i in (0, 1, 3))
            for a, b, data, offsets in hashing.chunks(part.column(2)):
                found = segments_of(data, offsets, width, gram)
                if found is not None:
                    row, at, n, anchor, g1, g2 = found
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(numbers[a:b][row], pa.int32()), pa.array(ids[a:b][row], pa.int64()), pa.array(keys[a:b][row], pa.int64()), pa.array(at, pa.int32()), pa.array(n, pa.int32()), pa.array(hashing.signed(anchor)), pa.array(g1), pa.array(g2)],
                        names=["batch", "doc_id", "row", "at", "n", "anchor", "g1", "g2"],
                    )

    rows = _rows(docs).withColumn("batch", (F.lit(0) if batch is None else batch).cast("int"))
    return rows.transform(arrow_map, find, _SEGMENT)


class FingerprintIndex:
    """Levels of sorted runs of (anchor, digest, first doc_id); a key is in one run only."""

    def __init__(self, spark: SparkSession, fanout: int = 4, folder: str | None = None):
        self.spark, self.fanout = spark, fanout
        self.folder = folder or store.shared_folder(spark)
        self.levels: list[list[str]] = [[]]
        self.merges = 0
        self._made = 0

    def _write(self, run: DataFrame, level: int) -> None:
        path = f"{self.folder}/level-{level}/run-{self._made}"
        self._made += 1
        store.written(run.repartition("anchor", "g1", "g2").sortWithinPartitions("anchor", "g1", "g2"), path)
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(path)

    def runs(self, paths: list[str] | None = None) -> DataFrame:
        """The rows of all runs, or of some."""
        paths = [p for level in self.levels for p in level] if paths is None else paths
        return self.spark.read.schema(_RUN).parquet(*paths) if paths else self.spark.createDataFrame([], _RUN)

    def look_up(self, batch: DataFrame) -> DataFrame:
        """The segments of a batch with ``whole``: whether an earlier batch, or a smaller document of this one, has the same segment."""
        mine = batch.groupBy("anchor", "g1", "g2").agg(F.min("doc_id").alias("least"))
        before = self.runs().select("anchor", "g1", "g2", F.col("doc_id").alias("before"))
        # Written, so that the join below is one of two shuffles, of which Spark splits a key with very many rows.
        known = store.written(mine.join(before.hint("merge"), ["anchor", "g1", "g2"], "left"), f"{self.folder}/known")
        found = batch.join(known.hint("merge"), ["anchor", "g1", "g2"])
        return found.select(*batch.columns, (F.col("before").isNotNull() | (F.col("doc_id") > F.col("least"))).alias("whole"))

    def add(self, judged: DataFrame) -> None:
        """One more run from the rows of ``look_up`` that were new; compacts the levels that are full."""
        self._write(judged.where("not whole").select("anchor", "g1", "g2", "doc_id").distinct(), 0)
        level = 0
        while len(self.levels[level]) >= self.fanout:
            full, self.levels[level] = self.levels[level], []
            self._write(self.runs(full), level + 1)
            self.merges += 1
            for path in full:
                store.remove(self.spark, path)
            level += 1


def _windows(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """Digests of the windows of the wanted segments (doc_id, row, at, n)."""
    lists = wanted.groupBy("doc_id", "row").agg(F.collect_list("at").alias("ats"), F.collect_list("n").alias("ns"))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            ats, ns = batch.column(3), batch.column(4)
            for a, b, data, offsets in hashing.chunks(batch.column(2)):
                text, offsets = _plain(data, offsets)
                start, end, first = hashing.word_spans(np.frombuffer(text, np.uint8), offsets)
                heads, counts = ats.slice(a, b - a), ns.slice(a, b - a)
                per_row = pc.list_value_length(heads).to_numpy(zero_copy_only=False)
                row = np.repeat(np.arange(b - a), per_row)
                head = heads.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                n = counts.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                at, row = np.repeat(head, n) + step, np.repeat(row, n)
                h1, h2 = _digests(text, start[first[row] + at], end[first[row] + at + width - 1])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids[a:b][row], pa.int64()), pa.array(keys[a:b][row], pa.int64()), pa.array(at, pa.int32()), pa.array(h1), pa.array(h2)],
                    names=["doc_id", "row", "at", "h1", "h2"],
                )

    joined = _rows(docs).dropDuplicates(["doc_id", "row"]).join(lists, ["doc_id", "row"])
    return joined.select("doc_id", "row", "text", "ats", "ns").transform(arrow_map, find, _WINDOW)


def _in_order(docs: DataFrame, batches: int) -> Column:
    """The batch of a doc_id: ranges of about equal size, in rising order."""
    if batches < 2:
        return F.lit(0)
    cuts = docs.where("doc_id is not null").select(F.col("doc_id").cast("double").alias("d")).stat.approxQuantile("d", [k / batches for k in range(1, batches)], 0.01)
    number = F.lit(0)
    for cut in sorted({int(c) for c in cuts}):
        number = number + (F.col("doc_id") > F.lit(cut)).cast("int")
    return number


def repeated_ranges(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, batches: int = 5, fanout: int = 4) -> DataFrame:
    """(of_doc, of_row, begins, stops): for each row that loses words, the word ranges covered by windows that a smaller document also has.

    Written, as are the steps before; each step's tables are removed when the next one is written.
    """
    spark = docs.sparkSession
    index, folder = FingerprintIndex(spark, fanout), store.shared_folder(spark)
    # One pass over the texts; the batches are folders of its output.
    made = segments(docs, width, gram, _in_order(docs, batches))
    with store.freed_shuffles(spark):
        made.write.partitionBy("batch").parquet(f"{folder}/segments")
    plain = _SEGMENT.removeprefix("batch int, ")
    judged = None
    for k in range(batches):
        path = f"{folder}/segments/batch={k}"
        if not store.exists(spark, path):
            continue
        part = store.written(index.look_up(spark.read.schema(plain).parquet(path)), f"{folder}/judged/{k}")
        store.remove(spark, path)
        index.add(part)
        judged = part if judged is None else judged.unionByName(part)
    if judged is None:
        return spark.createDataFrame([], "of_doc long, of_row long, begins array<int>, stops array<int>")
    whole = judged.where("whole").select("doc_id", "row", F.col("at").alias("begin"), (F.col("at") + F.col("n") + F.lit(width - 1)).alias("stop"))

    # Anchors with more than one segment: their segments may share windows in part.
    several = index.runs().groupBy("anchor").agg(F.count(F.lit(1)).alias("keys")).where("keys > 1").select("anchor")
    wanted = store.written(judged.where("not whole").join(several, "anchor", "left_semi").select("doc_id", "row", "at", "n"), f"{folder}/wanted")
    store.remove(spark, index.folder)
    windows = store.written(_windows(docs, wanted, width), f"{folder}/windows")
    first = windows.groupBy("h1", "h2").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most")).where("least < most").drop("most")
    partial = windows.join(first, ["h1", "h2"]).where("doc_id > least").select("doc_id", "row", F.col("at").alias("begin"), (F.col("at") + F.lit(width)).alias("stop"))
    lists = whole.unionByName(partial).groupBy(F.col("doc_id").alias("of_doc"), F.col("row").alias("of_row")).agg(F.collect_set(F.struct("begin", "stop")).alias("r"))
    found = store.written(lists.select("of_doc", "of_row", F.col("r.begin").alias("begins"), F.col("r.stop").alias("stops")), f"{folder}/ranges")
    for step in ("judged", "wanted", "windows"):
        store.remove(spark, f"{folder}/{step}")
    return found


_ADDED = {"text": T.StringType(), "n_words": T.LongType(), "n_removed": T.LongType()}


def substring_dedup(docs: DataFrame, width: int = WIDTH, gram: int = GRAM, batches: int = 5, fanout: int = 4) -> DataFrame:
    """docs with ``text`` as its kept words joined by one space, ``n_words`` (before) and ``n_removed``."""
    row_, doc_, of_, begins_, stops_ = store.free_names(docs, "row", "of_doc", "of_row", "begins", "stops")
    lists = repeated_ranges(docs.select("doc_id", "text"), width, gram, batches, fanout).toDF(doc_, of_, begins_, stops_)
    joined = docs.withColumn(row_, _row_key()).join(lists, (F.col("doc_id") == F.col(doc_)) & (F.col(row_) == F.col(of_)), "left")

    def make(batch: pa.RecordBatch) -> dict:
        col = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
        texts = pc.fill_null(col["text"], "").cast(pa.large_binary()).to_pylist()
        kept, n_words, n_removed = [], [], []
        for text, begin, stop in zip(texts, col[begins_].to_pylist(), col[stops_].to_pylist()):
            words = text.split()
            total = len(words)
            if begin:
                depth = np.zeros(total + 1, dtype=np.int64)
                np.add.at(depth, begin, 1)
                np.add.at(depth, stop, -1)
                words = [words[i] for i in np.flatnonzero(np.cumsum(depth[:-1]) == 0)]
            kept.append(b" ".join(words))
            n_words.append(total)
            n_removed.append(total - len(words))
        return {"text": pa.array(kept, pa.binary()).cast(pa.string()), "n_words": pa.array(n_words, pa.int64()), "n_removed": pa.array(n_removed, pa.int64())}

    return with_columns(joined, _ADDED, make, keep=docs.columns)


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substring_dedup(store.table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "n_words", "n_removed", F.sha2(F.col("text"), 256).alias("kept_sha256"))


OP10_SQL = r"""
with docs as (
  select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as words from documents
), windows as (
  select doc_id, pos, md5(array_to_string(list_slice(words, pos, pos + 49), ' ')) as h
  from (select doc_id, words, unnest(range(1, len(words) - 48)) as pos from docs where len(words) >= 50)
), least as (
  select h, min(doc_id) as least from windows group by h having min(doc_id) < max(doc_id)
), covered as (
  select distinct doc_id, pos + step as pos
  from (select w.doc_id, w.pos from windows w join least l on w.h = l.h where w.doc_id > l.least), (select unnest(range(0, 50)) as step)
), listed as (
  select doc_id, unnest(words) as word, generate_subscripts(words, 1) as pos from docs
), kept as (
  select l.doc_id, l.word, l.pos, c.pos is not null as gone from listed l left join covered c on l.doc_id = c.doc_id and l.pos = c.pos
), sums as (
  select doc_id, count(*)::bigint as n_words, sum(case when gone then 1 else 0 end)::bigint as n_removed,
         string_agg(word, ' ' order by pos) filter (where not gone) as kept
  from kept group by doc_id
)
select d.doc_id, coalesce(n_words, 0)::bigint as n_words, coalesce(n_removed, 0)::bigint as n_removed, sha256(coalesce(kept, '')) as kept_sha256
from docs d left join sums s on d.doc_id = s.doc_id
"""
