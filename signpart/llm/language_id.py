"""Language identification with bit-sliced Bloom filters of n-grams.

Every language has a set of byte n-grams that are typical of it.  The filters of
all languages share one table: the word at a hash position holds one bit for each
language, so the AND of the words at an n-gram's positions is the set of all
languages whose filter holds it.  A document's hits per language, less the hits
that a filter of that fill would report by chance, decide.

The filters are fitted on about ``sample`` labelled documents per language at most,
those with the least hashes of their key in each of 64 parts; this bound is a
parameter.  Prediction reads
whole texts and nothing else of a row.

Defined cases: a null text and a text without a letter are ``und`` with score 0;
so is every text if nothing could be learned; rows without label are not learned
from; of languages with equal counts the first by name is taken; a text whose
n-grams are all unknown gets the first language with score 0; an empty table gives
an empty result; columns called ``lang_pred`` or ``score`` are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from signpart.llm import hashing, store
from signpart.llm.arrowmap import arrow_map, with_columns

UNDECIDED = "und"
SIZES = (3, 4)
#: Bound of the documents per language that the filters are fitted on.
SAMPLE = 1500
_PARTS = 64
#: N-grams per language and size in a filter, and positions in the table.
GRAMS, SLOTS_BITS, PROBES = 2500, 16, 2

_FOLD = hashing.LOWER.copy()
_FOLD[:65] = 32
_FOLD[91:97] = 32
_FOLD[123:128] = 32


def gram_codes(data: np.ndarray, size: int) -> np.ndarray:
    """The n-gram at each byte as an integer; letters are folded and other ASCII characters are blanks."""
    wide = np.zeros(len(data) + size, dtype=np.uint32)
    wide[: len(data)] = _FOLD[data]
    code = wide[: len(data)].copy()
    for i in range(1, size):
        code |= wide[i : len(data) + i] << np.uint32(8 * i)
    return code


def _inside(offsets: np.ndarray, n: int, size: int) -> np.ndarray:
    """Whether the n-gram at a byte ends in the same text."""
    ok = np.ones(n, dtype=bool)
    for i in range(1, size):
        at = offsets[1:] - i
        ok[at[at >= 0]] = False
    return ok


def _slots(code: np.ndarray, size: int) -> list[np.ndarray]:
    """Table positions of n-grams, one array for each probe."""
    odd = (0x9E3779B1, 0x85EBCA6B, 0xC2B2AE35, 0x27D4EB2F)
    salted = code ^ np.uint32(size * 0x01000193)
    return [(salted * np.uint32(odd[k])) >> np.uint32(32 - SLOTS_BITS) for k in range(PROBES)]


@dataclass(frozen=True)
class Filters:
    """Languages by name, their bits in ``table`` [planes, positions], and each filter's chance of a false hit."""

    languages: tuple[str, ...]
    table: np.ndarray
    by_chance: np.ndarray

    @staticmethod
    def build(grams: dict[str, dict[int, list[int]]]) -> Filters:
        """From {language: {size: codes}}."""
        names = tuple(sorted(grams))
        table = np.zeros((max(1, -(-len(names) // 64)), 1 << SLOTS_BITS), dtype=np.uint64)
        for i, name in enumerate(names):
            for size, codes in grams[name].items():
                for at in _slots(np.asarray(codes, dtype=np.uint32), size):
                    table[i // 64, at] |= np.uint64(1 << (i % 64))
        fill = [np.mean((table[i // 64] >> np.uint64(i % 64)) & np.uint64(1)) for i in range(len(names))]
        return Filters(names, table, np.asarray(fill) ** PROBES)

    def hits(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(n-grams per text, hits per text and language corrected for false positives)."""
        rows = len(offsets) - 1
        seen, counts = np.zeros(rows), np.zeros((rows, len(self.languages)))
        filled = np.flatnonzero(np.diff(offsets))
        if not len(filled):
            return seen, counts
        at = offsets[:-1][filled]
        for size in SIZES:
            code = gram_codes(data, size)
            ok = _inside(offsets, len(data), size)
            seen[filled] += np.add.reduceat(ok, at, dtype=np.int64)
            slots = _slots(code, size)
            for plane in range(len(self.table)):
                found = self.table[plane][slots[0]]
                for s in slots[1:]:
                    found &= self.table[plane][s]
                found[~ok] = 0
                for i in range(plane * 64, min(len(self.languages), plane * 64 + 64)):
                    bit = (found & np.uint64(1 << (i % 64))) != 0
                    counts[filled, i] += np.add.reduceat(bit, at, dtype=np.int64)
        corrected = (counts - seen[:, None] * self.by_chance) / (1 - self.by_chance)
        return seen, np.maximum(corrected, 0)


def fit(labelled: DataFrame, sample: int = SAMPLE, grams: int = GRAMS) -> Filters | None:
    """Filters from (key, text, lang) rows; None if no row has a label."""
    named = labelled.where("lang is not null and text is not null")
    # The least hashes of each of 64 parts: no task ranks all labels of a language.
    each = -(-sample // _PARTS)
    order = Window.partitionBy("lang", "__part").orderBy("__h", "key")
    hashed = named.select("key", "lang", F.xxhash64("key").alias("__h")).withColumn("__part", F.pmod("__h", F.lit(_PARTS)))
    chosen = hashed.withColumn("__n", F.row_number().over(order)).where(F.col("__n") <= each).select("key")
    # At most ``sample`` keys per language, rounded up to the parts.
    texts = named.join(F.broadcast(chosen.distinct()), "key", "left_semi").select("lang", "text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs = np.asarray(batch.column(0).to_pylist(), dtype=object)
            for a, b, data, offsets in hashing.chunks(batch.column(1)):
                row = np.repeat(np.arange(b - a), np.diff(offsets))
                for lang in sorted(set(langs[a:b])):
                    mine = (langs[a:b] == lang)[row]
                    for size in SIZES:
                        codes, n = np.unique(gram_codes(data, size)[mine & _inside(offsets, len(data), size)], return_counts=True)
                        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(codes)), pa.array([size] * len(codes), pa.int32()), pa.array(codes, pa.int64()), pa.array(n, pa.int64())], names=["lang", "size", "code", "n"])

    counted = texts.transform(arrow_map, count, "lang string, size int, code long, n long").groupBy("lang", "size", "code").agg(F.sum("n").alias("n"))
    share = F.col("n") / F.sum("n").over(Window.partitionBy("lang", "size"))
    shared = counted.withColumn("share", share)
    typical = shared.withColumn("most", F.max("share").over(Window.partitionBy("size", "code"))).where("share >= 0.5 * most")
    best = Window.partitionBy("lang", "size").orderBy(F.desc("n"), "code")
    top = typical.withColumn("__n", F.row_number().over(best)).where(F.col("__n") <= grams).select("lang", "size", "code").collect()
    found: dict[str, dict[int, list[int]]] = {}
    for r in top:
        found.setdefault(r["lang"], {}).setdefault(r["size"], []).append(r["code"])
    return Filters.build(found) if found else None


def _letters(data: bytes) -> bool:
    return any(c.isalpha() for c in data.decode())


def predict(docs: DataFrame, filters: Filters | None) -> DataFrame:
    """docs with ``lang_pred`` and ``score``: the share of the corrected hits that the language has."""
    held = docs.sparkSession.sparkContext.broadcast(filters)
    ascii_letter = np.zeros(256, dtype=bool)
    ascii_letter[65:91] = ascii_letter[97:123] = True

    def make(batch: pa.RecordBatch) -> dict:
        model = held.value
        named: list[str] = []
        scores: list[float] = []
        for _, _, data, offsets in hashing.chunks(batch.column(batch.schema.get_field_index("text"))):
            letters = np.concatenate([[0], np.cumsum(ascii_letter[data])])
            has = (letters[offsets[1:]] - letters[offsets[:-1]]) > 0
            for r in np.flatnonzero(~has & (np.diff(offsets) > 0)):
                has[r] = _letters(data[offsets[r] : offsets[r + 1]].tobytes())
            if model is None:
                named += [UNDECIDED] * len(has)
                scores += [0.0] * len(has)
                continue
            _, counts = model.hits(data, offsets)
            total = counts.sum(axis=1)
            best = counts.argmax(axis=1)
            share = np.where(total > 0, counts[np.arange(len(best)), best] / np.where(total > 0, total, 1), 0.0)
            named += [model.languages[k] if ok else UNDECIDED for k, ok in zip(best, has)]
            scores += np.where(has, share, 0.0).tolist()
        return {"lang_pred": pa.array(named, pa.string()), "score": pa.array(scores, pa.float64())}

    return with_columns(docs, {"lang_pred": T.StringType(), "score": T.DoubleType()}, make)


def held_out(doc_id: str = "doc_id") -> F.Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 3 == 1, F.lit(False))


def identify(docs: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """Fit on the labelled documents that aren't held out, predict all."""
    learned = docs.where(~held_out() & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("key"), "text", "lang")
    return predict(docs, fit(learned, sample))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return identify(docs).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
