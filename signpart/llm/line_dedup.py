"""Line deduplication over levelled sorted runs of line hashes.

An index takes documents in batches.  The line keys of a batch, with the number of
its documents that hold each, are merge-joined with the runs of all batches before:
keys without a match are new, the others learn how often they stood before, and a
key whose total passes the limit here is noted as common, once.  Then the batch
becomes an immutable run itself, sorted by hash.  Runs of one level are merged into
one run of the next as soon as there are ``fanout`` of them, so an index over many
batches holds few runs.

The key of a line is the line without the characters ``[\\x20\\x09-\\x0D]`` at
both ends and with A-Z lower-cased, hashed to 128 bits.

Defined cases: a null or empty text is one empty line; an empty key is never
dropped while ``min_chars`` is at least 1; each row of the input counts as one
document, whether or not doc_ids repeat; a null doc_id is carried through; an
empty table gives an empty result; columns of the input called ``n_lines`` or
``n_dropped`` are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from signpart.llm import store
from signpart.llm.arrowmap import arrow_map, with_columns

#: Rows of counts that a task combines before it hands them on.
_COMBINE = 1 << 17
#: Common keys that are sent to every executor at once; beyond it they are joined.
BROADCAST_KEYS = 200_000


def _keys(text: bytes, min_chars: int) -> list[bytes | None]:
    """The hash of every line's key in order; None for a key that is too short."""
    found = []
    for line in text.split(b"\n"):
        key = line.strip().lower()
        short = len(key) < min_chars or (min_chars > 1 and len(key.decode()) < min_chars)
        found.append(None if short else xxhash.xxh3_128_digest(key))
    return found


def _texts(batch: pa.RecordBatch, name: str = "text") -> list[bytes]:
    col = batch.column(batch.schema.get_field_index(name))
    return pc.fill_null(col, "").cast(pa.large_binary()).to_pylist()


def line_counts(docs: DataFrame, min_chars: int = 1, batch: Column | None = None) -> DataFrame:
    """(batch, key, n_docs): the number of documents of each batch that hold each line key, combined in each task first."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[tuple[int, bytes], int] = {}

        def out() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([pa.array([k[0] for k in seen], pa.int32()), pa.array([k[1] for k in seen], pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["batch", "key", "n_docs"])
            seen.clear()
            return made

        for part in batches:
            for number, text in zip(part.column(0).to_pylist(), _texts(part)):
                for key in {*_keys(text, min_chars)} - {None}:
                    seen[number, key] = seen.get((number, key), 0) + 1
                if len(seen) >= _COMBINE:
                    yield out()
        if seen:
            yield out()

    per_task = docs.select((F.lit(0) if batch is None else batch).cast("int").alias("batch"), "text").transform(arrow_map, count, "batch int, key binary, n_docs long")
    return per_task.groupBy("batch", "key").agg(F.sum("n_docs").alias("n_docs"))


class LineRuns:
    """An index of line keys as levels of immutable sorted runs in the shared folder."""

    def __init__(self, spark: SparkSession, min_docs: int = 10, folder: str | None = None, fanout: int = 4, min_chars: int = 1):
        self.spark, self.fanout, self.min_chars, self.min_docs = spark, fanout, min_chars, min_docs
        self.folder = folder or store.shared_folder(spark)
        self.levels: list[list[str]] = [[]]
        self.merges = 0
        self._noted: list[str] = []
        self._made = 0

    def _write(self, counts: DataFrame, level: int) -> DataFrame:
        path = f"{self.folder}/level-{level}/run-{self._made}"
        self._made += 1
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(path)
        return store.written(counts.sortWithinPartitions("key"), path)

    def _merge(self, paths: list[str]) -> DataFrame:
        runs = self.spark.read.schema("key binary, n_docs long").parquet(*paths)
        return runs.groupBy("key").agg(F.sum("n_docs").alias("n_docs"))

    def counts(self) -> DataFrame:
        """(key, n_docs) over all runs."""
        paths = [p for level in self.levels for p in level]
        return self._merge(paths) if paths else self.spark.createDataFrame([], "key binary, n_docs long")

    def judged(self, counts: DataFrame) -> DataFrame:
        """(key, n_docs, before) of a batch's counts: ``before`` is the total of the runs, null for a key that no run holds."""
        return counts.select("key", "n_docs").join(self.counts().withColumnRenamed("n_docs", "before").hint("merge"), "key", "left")

    def add(self, docs: DataFrame) -> DataFrame:
        return self.add_counts(line_counts(docs, self.min_chars))

    def add_counts(self, counts: DataFrame) -> DataFrame:
        """Judges a batch by the runs so far, notes the keys that become common, and adds its run; returns the keys that were new.

        Full levels are compacted afterwards.
        """
        run = self._write(self.judged(counts), 0)
        before = F.coalesce("before", F.lit(0))
        noted = f"{self.folder}/common/{self._made}"
        store.written(run.where((before < self.min_docs) & (before + F.col("n_docs") >= self.min_docs)).select("key"), noted)
        self._noted.append(noted)
        new, level = run.where("before is null").select("key"), 0
        while len(self.levels[level]) >= self.fanout:
            full, self.levels[level] = self.levels[level], []
            self._write(self._merge(full), level + 1)
            self.merges += 1
            # The latest run stays for the caller, who may still read its new keys.
            for path in full[:-1] if level == 0 else full:
                store.remove(self.spark, path)
            level += 1
        return new

    def common(self) -> DataFrame:
        """Keys found in at least ``min_docs`` documents of all batches so far."""
        return self.spark.read.schema("key binary").parquet(*self._noted) if self._noted else self.spark.createDataFrame([], "key binary")


_ADDED = {"text": T.StringType(), "n_lines": T.LongType(), "n_dropped": T.LongType()}


def _without(texts: list[bytes], drop, min_chars: int) -> dict:
    """Texts without the lines whose key ``drop(row)`` holds."""
    kept, n_lines, n_dropped = [], [], []
    for row, text in enumerate(texts):
        common = drop(row)
        keys = _keys(text, min_chars) if common else []
        lines = text.split(b"\n")
        rest = [line for line, key in zip(lines, keys) if key not in common] if common else lines
        kept.append(b"\n".join(rest))
        n_lines.append(len(lines))
        n_dropped.append(len(lines) - len(rest))
    return {"text": pa.array(kept, pa.binary()).cast(pa.string()), "n_lines": pa.array(n_lines, pa.int64()), "n_dropped": pa.array(n_dropped, pa.int64())}


def drop_lines(docs: DataFrame, common: DataFrame, min_chars: int = 1, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """docs with ``text`` without the lines whose key is in ``common``, and ``n_lines`` and ``n_dropped``.

    The keys go to every executor only if there are at most ``broadcast_keys``
    of them; more are joined to the distinct (document, key) rows, where Spark
    splits a key with very many rows, and gathered per document.
    """
    spark = docs.sparkSession
    if store.small_enough(common, broadcast_keys):
        held = spark.sparkContext.broadcast(frozenset(bytes(r[0]) for r in common.collect()))
        return with_columns(docs, _ADDED, lambda batch: _without(_texts(batch), lambda _: held.value, min_chars))

    id_, drop_ = store.free_names(docs, "id", "drop")
    keyed = docs.withColumn(id_, F.md5(F.coalesce("text", F.lit(""))))

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_pylist()
            rows = [(i, k) for i, text in zip(ids, _texts(batch)) for k in {*_keys(text, min_chars)} - {None}]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.binary())], names=["id", "key"])

    found = keyed.select(id_, "text").transform(arrow_map, pairs, "id string, key binary").distinct().join(common, "key")
    per_text = found.groupBy(F.col("id").alias(id_)).agg(F.collect_set("key").alias(drop_))
    joined = keyed.join(per_text, id_, "left")

    def make(batch: pa.RecordBatch) -> dict:
        drops = batch.column(batch.schema.get_field_index(drop_)).to_pylist()
        return _without(_texts(batch), lambda row: {*(drops[row] or ())}, min_chars)

    return with_columns(joined, _ADDED, make, keep=docs.columns)


def line_dedup(docs: DataFrame, min_docs: int = 10, min_chars: int = 1, batches: int = 5, fanout: int = 4, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """docs without the lines whose key stands in at least ``min_docs`` documents.

    The index takes the documents in ``batches`` batches, as successive deliveries
    would come; more of them than ``fanout`` compact it on the way.  The lines of
    all batches are hashed in one pass over the documents.  A key's total does not
    depend on the order or the number of batches.
    """
    spark = docs.sparkSession
    index = LineRuns(spark, min_docs, min_chars=min_chars, fanout=fanout)
    counts = store.written(line_counts(docs, min_chars, F.pmod(F.xxhash64("doc_id", "text"), F.lit(batches))), f"{index.folder}/counts")
    for k in range(batches):
        index.add_counts(counts.where(F.col("batch") == k))
    return drop_lines(docs, index.common(), min_chars, broadcast_keys)


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_dedup(store.table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text"), 256).alias("kept_sha256"))


OP4_SQL = r"""
with lines as (
  select doc_id, text_rows.pos as pos, text_rows.line as line,
         lower_ascii.key as key
  from documents,
       lateral (select unnest(string_split(coalesce(text, ''), chr(10))) as line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as pos) text_rows,
       lateral (select translate(trim(text_rows.line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key) lower_ascii
), common as (
  select key from lines where key <> '' group by key having count(distinct doc_id) >= 10
), marked as (
  select l.*, c.key is not null as dropped from lines l left join common c on l.key = c.key
)
select doc_id, count(*) as n_lines, sum(case when dropped then 1 else 0 end)::bigint as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where not dropped), '')) as kept_sha256
from marked group by doc_id
"""
