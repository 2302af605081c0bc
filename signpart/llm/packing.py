"""Best-fit packing of tokenised documents by exact-complement hashing.

Only the number of pieces of each length (1 … capacity) decides how sequences are
filled, so the plan is made from that histogram, whose size does not depend on the
data.  An index by sum holds the single lengths and the pairs of lengths, and finds
triples as a length and a pair; a gap is closed by a combination that fills it
exactly, as often as the counts allow, and a combination goes from the index when a
length of it is used up.  What has no exact complement is placed by best fit.  The
plan is a list of patterns (a tuple of lengths and how many sequences use it).

Pieces get a rank among those of their length, and an interval join with the
pattern table turns the rank into a sequence and an offset.  Ranks come from
salted groups of bounded size, so a length that holds most pieces is spread over
many tasks.

Defined cases: a null or empty text is the end mark alone; longer documents are
cut so that all pieces but the first have full length; repeated doc_ids are
separate documents if their texts differ in rank only, each row is packed; a null
doc_id is carried through; an empty table gives an empty result; columns of the
input other than doc_id and text are ignored.
"""

from __future__ import annotations

import json
import logging
import zlib
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from signpart.llm import store
from signpart.llm.arrowmap import arrow_map

END_ID = 2
CAPACITY = 1024
#: Groups that pieces of one length are ranked in at least, and pieces of a group beyond which there are more groups.
SALTS, GROUP_ROWS = 64, 500_000

_log = logging.getLogger(__name__)


class Encoder:
    """Ids of the byte-level vocabulary file at ``path``.

    The file is read by the library ``tokenizers``.  Where a vocabulary has the
    plain byte-level split rule, its merges are run by a faster library from the
    same file; a text on which that fails goes to the first one.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.slow = Tokenizer.from_file(path)
        self.fast = self._fast(path)

    @staticmethod
    def _fast(path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, before = spec["model"], spec.get("pre_tokenizer") or {}
        plain = model.get("type", "BPE") == "BPE" and before.get("type") == "ByteLevel" and not before.get("add_prefix_space") and before.get("use_regex", True) and not spec.get("normalizer")
        if not plain:
            return None
        # Printable bytes stand for themselves in the file, the others for code points from 256 on.
        shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
        byte_of = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
        special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        ranks = {bytes(byte_of[c] for c in t): i for t, i in model["vocab"].items() if t not in special}
        merged = [bytes(byte_of[c] for part in (m if isinstance(m, list) else m.split(" ")) for c in part) for m in model["merges"]]
        at = [ranks[m] for m in merged]
        if any(a >= b for a, b in zip(at, at[1:])):  # ids don't follow the order of the merges
            return None
        # Fixed value: the split rule of byte-level vocabularies.
        pattern = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
        return tiktoken.Encoding("vocabulary", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)

    def ids(self, text: str) -> np.ndarray:
        if self.fast is not None:
            try:
                return self.fast.encode_to_numpy(text, allowed_special="all")
            except Exception as error:  # the split rule gave up on this text; the other library has no such limit
                _log.warning("a text of %d characters goes to the slower encoder: %s", len(text), error)
        return np.asarray(self.slow.encode(text, add_special_tokens=False).ids, dtype=np.uint32)


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every document's pieces."""
    id_type = docs.schema["doc_id"].dataType

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(tokenizer_path)
        for batch in batches:
            doc, piece, start, length, crc = [], [], [], [], []
            for row, text in enumerate(batch.column(1).to_pylist()):
                ids = np.append(encoder.ids(text or ""), end_id).astype("<u4")
                bounds = [0, *range((len(ids) - 1) % capacity + 1, len(ids) + 1, capacity)]
                for i, (a, b) in enumerate(zip(bounds, bounds[1:])):
                    doc.append(row)
                    piece.append(i)
                    start.append(a)
                    length.append(b - a)
                    crc.append(zlib.crc32(ids[a:b].tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(doc, pa.int64())), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    out = f"doc_id {id_type.simpleString()}, piece int, start long, length long, ids_crc32 long"
    return docs.select("doc_id", "text").transform(arrow_map, cut, out)


class SumIndex:
    """Combinations of one, two or three available lengths by their sum; ``left`` holds how many there are of each length."""

    def __init__(self, counts: dict[int, int], capacity: int):
        self.left = [0] * (capacity + 1)
        for length, n in counts.items():
            self.left[length] = n
        self.lengths = np.asarray(sorted((x for x, n in counts.items() if n), reverse=True), dtype=np.int64)
        large, small = self.lengths[:, None], self.lengths[None, :]
        i, j = np.nonzero((large >= small) & (large + small <= capacity))
        total = self.lengths[i] + self.lengths[j]
        order = np.argsort(total, kind="stable")  # within a sum the largest length comes first
        ends = np.searchsorted(total[order], np.arange(capacity + 2))
        large, small = self.lengths[i[order]].tolist(), self.lengths[j[order]].tolist()
        #: The pairs of each sum, the best last, so that a used-up pair is popped.
        self.pairs = [list(zip(large[a:b], small[a:b]))[::-1] for a, b in zip(ends, ends[1:])]
        self.singles = self.lengths.tolist()[::-1]

    def _has(self, *lengths: int) -> bool:
        return all(self.left[x] >= lengths.count(x) for x in lengths)

    def pair(self, total: int) -> tuple[int, int] | None:
        """The available pair with this sum that has the largest length."""
        of_sum = self.pairs[total]
        while of_sum and not self._has(*of_sum[-1]):  # counts only fall: it never comes back
            of_sum.pop()
        return of_sum[-1] if of_sum else None

    def exact(self, gap: int) -> tuple[int, ...] | None:
        """Available lengths with exactly this sum, of as few and as large as there are."""
        if self.left[gap]:
            return (gap,)
        two = self.pair(gap)
        if two:
            return two
        while self.singles and not self.left[self.singles[-1]]:
            self.singles.pop()
        for a in reversed(self.singles):
            if a > gap - 2 or not self.left[a]:
                continue
            if 3 * a < gap:  # the largest of three is a third at least
                break
            for b, c in reversed(self.pairs[gap - a]):
                if b <= a and self._has(a, b, c):
                    return a, b, c
        return None

    def largest(self, gap: int) -> int | None:
        """The largest available length that fits."""
        return next((x for x in range(gap, 0, -1) if self.left[x]), None)

    def take(self, lengths: Iterable[int], times: int = 1) -> None:
        for x in lengths:
            self.left[x] -= times


def fill_plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, number of sequences) that use every piece once.

    The longest length left opens sequences; its gap is closed exactly by a
    combination of the index, else best fit puts in the longest that fits, and so
    on.  Each pattern is repeated as often as the counts allow, so the number of
    patterns is bounded by the capacity, not by the number of pieces.
    """
    index = SumIndex(counts, capacity)
    plan: Counter[tuple[int, ...]] = Counter()
    for length in index.lengths.tolist():
        while index.left[length]:
            used, gap = [length], capacity - length
            index.take(used)
            while gap:
                closing = index.exact(gap)
                if closing is None:
                    best = index.largest(gap)
                    if best is None:
                        break
                    closing = (best,)
                index.take(closing)
                used += closing
                gap -= sum(closing)
            need = Counter(used)
            more = min(index.left[x] // k for x, k in need.items())
            index.take(used, more)
            plan[tuple(used)] += 1 + more
    return list(plan.items())


def pack(cut: DataFrame, capacity: int = CAPACITY, salts: int = SALTS, group_rows: int = GROUP_ROWS) -> DataFrame:
    """cut with ``sequence_id`` and ``offset``; cut is read more than once, so it should be a written table."""
    spark = cut.sparkSession
    counts = {r["length"]: r["count"] for r in cut.groupBy("length").count().collect()}  # at most capacity rows
    if not counts:
        return cut.withColumns({"sequence_id": F.lit(0).cast("long"), "offset": F.lit(0).cast("long")})
    salt_, in_, first_, rank_, from_, to_, seq_, length_, offset_ = store.free_names(cut, "salt", "place", "first", "rank", "begin", "stop", "sequence", "of_length", "at")
    more = {x: -(-n // group_rows) for x, n in counts.items() if n > salts * group_rows}
    groups_of = F.coalesce(F.element_at(F.create_map(*(F.lit(v) for pair in more.items() for v in pair)), F.col("length")), F.lit(salts)) if more else F.lit(salts)
    salted = cut.withColumn(salt_, F.pmod(F.xxhash64("doc_id", "piece", "start"), groups_of).cast("long"))
    groups = salted.groupBy("length", salt_).agg(F.count(F.lit(1)).alias("n")).collect()  # at most salts for each length, and pieces / group_rows
    used: Counter[int] = Counter()
    first = []
    for length, salt, n in sorted(map(tuple, groups)):
        first.append((length, salt, used[length]))
        used[length] += n

    slots, base, used = [], 0, Counter()
    for lengths, n in fill_plan(counts, capacity):
        offset = 0
        for x in lengths:
            slots.append((x, used[x], used[x] + n, base, offset))
            used[x] += n
            offset += x
        base += n
    starts = F.broadcast(spark.createDataFrame(first, f"{length_} long, {salt_} long, {first_} long"))
    table = F.broadcast(spark.createDataFrame(slots, f"{length_} long, {from_} long, {to_} long, {seq_} long, {offset_} long"))
    order = Window.partitionBy("length", salt_).orderBy("doc_id", "piece", "start")
    ranked = salted.withColumn(in_, F.row_number().over(order) - 1)
    ranked = ranked.join(starts, (ranked["length"] == starts[length_]) & (ranked[salt_] == starts[salt_])).drop(starts[length_], starts[salt_]).withColumn(rank_, F.col(first_) + F.col(in_))
    placed = ranked.join(table, (F.col("length") == F.col(length_)) & (F.col(rank_) >= F.col(from_)) & (F.col(rank_) < F.col(to_)))
    return placed.select(*cut.columns, (F.col(seq_) + F.col(rank_) - F.col(from_)).alias("sequence_id"), F.col(offset_).alias("offset"))


def pack_documents(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Pieces of all documents with their sequences and offsets."""
    if tokenizer_path is None:
        import public_tokenizers

        tokenizer_path = public_tokenizers.path("byte_bpe_50k.json")
    return pack(store.written(pieces(docs, tokenizer_path, capacity, end_id)), capacity)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(store.table(spark, sf_dir, "documents"))
