"""Stupid-backoff scores against the corpus' own n-gram counts.

Counts of all n-grams are tables partitioned by hash.  Joining every n-gram of the
corpus to them row by row would move several times the corpus, so both sides of
the join are packed: documents are dealt into blocks, each block sends its distinct
n-grams to their hash partitions as sorted delta-coded arrays with counts, each
partition adds up its table and answers every block with the totals in the order
asked, and the block looks its n-grams up there and sums per document.  The join
is the same, on (partition, hash), with one row for each block and partition.  The
lengths of n-grams are counted one after the other, each answer is written, and
what a length has shuffled goes before the next one.

A word is scored by the n-gram of ``order`` words that it ends: if that was seen at
least ``least`` times, the score is its count / the count of its words before the
last; else ``backoff`` times the score by the n-gram that is one word shorter, down
to the word's share.  The first words of a document have shorter n-grams, at no
cost.  ``n_backoff`` counts the steps of backing off, ``log_score`` is the sum of
natural logarithms, ``score`` its mean per word.

Defined cases: a null or empty text has no words and null scores; repeated rows
are counted as often as they stand; a null doc_id is carried through; an empty
table gives an empty result; only doc_id and text are read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signpart.llm import hashing, packed_keys, store
from signpart.llm.arrowmap import arrow_map

#: Bytes of text in a block, and distinct n-grams of a hash partition, about.
BLOCK_BYTES, PARTITION_GRAMS = 12 << 20, 3_000_000
LEAST, BACKOFF = 2, 0.4
#: Words of the longest n-gram.
ORDER = 3

_ASKED = "block int, kind int, part int, grams binary, counts binary"
_ANSWER = "block int, kind int, part int, totals binary"


def _numbers(values: np.ndarray) -> bytes:
    return zlib.compress(values.astype("<u8" if len(values) and values.max() >= 1 << 32 else "<u4").tobytes(), 1) + (b"8" if len(values) and values.max() >= 1 << 32 else b"4")


def _from_numbers(data: bytes) -> np.ndarray:
    return np.frombuffer(zlib.decompress(data[:-1]), "<u8" if data[-1:] == b"8" else "<u4").astype(np.int64)


def _hashes(col: pa.Array, orders: range) -> tuple[list[np.ndarray], np.ndarray]:
    """(hashes of the n-grams of each length, first word of each row); n-gram i starts at word i, also if it runs over the end of its row."""
    grams: list[list[np.ndarray]] = [[np.zeros(0, np.uint64)] for _ in orders]
    first = [np.zeros(1, np.int64)]
    for _, _, data, offsets in hashing.chunks(col):
        start, end, f = hashing.word_spans(data, offsets)
        w = hashing.span_hashes(data, start, end)
        for n, found in zip(orders, grams):
            at = np.arange(max(0, len(w) - n + 1))
            g = w if n == 1 else hashing.run_hashes(w, at, at + n) if len(at) else np.zeros(0, np.uint64)
            found.append(np.append(g, np.zeros(len(w) - len(g), np.uint64)))
        first.append(first[-1][-1] + f[1:])
    return [np.concatenate(g) for g in grams], np.concatenate(first)


def _inner(first: np.ndarray, n: int) -> np.ndarray:
    """Whether the n-gram that starts at each word ends in the same row."""
    return np.arange(first[-1]) + n <= np.repeat(first[1:], np.diff(first))


def lm_scores(docs: DataFrame, least: int = LEAST, backoff: float = BACKOFF, order: int = ORDER) -> DataFrame:
    """(doc_id, n_words, n_backoff, log_score, score) of every document, by n-grams of up to ``order`` words."""
    if order < 1:
        raise ValueError(f"order {order} is less than one word")
    plain = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = size = 0
        for batch in batches:
            for _, _, data, offsets in hashing.chunks(batch.column(0)):
                n += len(hashing.word_spans(data, offsets)[0])
                size += len(data)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([size])], names=["n", "size"])

    total = plain.select("text").transform(arrow_map, measure, "n long, size long").agg(F.sum("n"), F.sum("size")).first()
    words, size = total[0] or 0, total[1] or 0
    blocks = max(1, -(-size // BLOCK_BYTES))
    parts = max(1, -(-words // PARTITION_GRAMS))
    width = np.uint64(-(-(1 << 64) // parts)) if parts > 1 else None
    dealt = plain.withColumn("block", F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).cast("int"))

    def asking(kind: int):
        def ask(table: pa.Table) -> pa.Table:
            col, block = table.column("text").combine_chunks(), table.column("block")[0].as_py()
            (keys,), first = _hashes(col, range(kind, kind + 1))
            found, n = np.unique(keys[_inner(first, kind)], return_counts=True)
            where = (found // width).astype(np.int64) if parts > 1 else np.zeros(len(found), np.int64)
            cuts = np.searchsorted(where, np.arange(parts + 1))
            rows = [(block, kind, p, packed_keys.packed(found[a:b]), _numbers(n[a:b])) for p, (a, b) in enumerate(zip(cuts, cuts[1:])) if b > a]
            return pa.table([pa.array(c, t) for c, t in zip(zip(*rows) if rows else ((),) * 5, (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()))], names=["block", "kind", "part", "grams", "counts"])

        return ask

    def answer(table: pa.Table) -> pa.Table:
        grams = [packed_keys.unpacked(x) for x in table.column("grams").to_pylist()]
        keys = np.concatenate(grams)
        counts = np.concatenate([_from_numbers(x) for x in table.column("counts").to_pylist()])
        rank = np.argsort(keys, kind="stable")
        keys, counts = keys[rank], counts[rank]
        head = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
        keys, sums = keys[head], np.add.reduceat(counts, head)
        totals = [_numbers(sums[np.searchsorted(keys, g)]) for g in grams]
        return pa.table([table.column("block"), table.column("kind"), table.column("part"), pa.array(totals, pa.binary())], names=["block", "kind", "part", "totals"])

    def score(texts: pa.Table, answers: pa.Table) -> pa.Table:
        held: dict[int, list] = {kind: [] for kind in range(1, order + 1)}
        for r in sorted(answers.select(["kind", "part", "totals"]).to_pylist(), key=lambda r: r["part"]):
            held[r["kind"]].append(_from_numbers(r["totals"]))
        grams, first = _hashes(texts.column("text").combine_chunks(), range(1, order + 1))
        value, back, shorter = np.zeros(0), np.zeros(first[-1], dtype=np.int64), np.zeros(0)
        for kind, keys in enumerate(grams, 1):
            ok = _inner(first, kind)
            count = np.zeros(len(keys))
            if ok.any():
                count[ok] = np.concatenate(held[kind])[np.unique(keys[ok], return_inverse=True)[1]]
            if kind == 1:
                value = count / max(words, 1)
            else:
                # An n-gram scores its last word, against the count of the shorter one that starts with it.
                at = np.flatnonzero(ok)
                last, seen = at + kind - 1, count[at] >= least
                value[last] = np.where(seen, count[at] / shorter[at], backoff * value[last])
                back[last] = np.where(seen, 0, back[last] + 1)
            shorter = count
        logs = np.concatenate([[0.0], np.cumsum(np.log(value))])
        backs = np.concatenate([[0], np.cumsum(back)])
        n = np.diff(first)
        sums = np.asarray([np.log(value[a:b]).sum() for a, b in zip(first, first[1:])]) if len(value) else logs[first[1:]] - logs[first[:-1]]
        none = n == 0
        return pa.table(
            [texts.column("doc_id"), pa.array(n), pa.array(backs[first[1:]] - backs[first[:-1]]), pa.array(sums, mask=none), pa.array(sums / np.maximum(n, 1), mask=none)],
            names=["doc_id", "n_words", "n_backoff", "log_score", "score"],
        )

    folder = store.shared_folder(docs.sparkSession)
    answers = None
    for kind in range(1, order + 1):
        asked = dealt.groupBy("block").applyInArrow(asking(kind), _ASKED)
        found = store.written(asked.groupBy("kind", "part").applyInArrow(answer, _ANSWER), f"{folder}/{kind}")
        answers = found if answers is None else answers.unionByName(found)
    out = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_words long, n_backoff long, log_score double, score double"
    return dealt.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(score, out)


def op5_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = lm_scores(store.table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_backoff", F.round("score", 6).alias("score"))


OP5_SQL = r"""
with docs as (
  select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as words from documents
), listed as (
  select doc_id, unnest(words) as w, generate_subscripts(words, 1) as pos from docs
), grams as (
  select doc_id, w, lag(w) over (partition by doc_id order by pos) as v, lag(w, 2) over (partition by doc_id order by pos) as u from listed
), one as (select w, count(*) as n from listed group by w),
two as (select v, w, count(*) as n from grams where v is not null group by 1, 2),
three as (select u, v, w, count(*) as n from grams where u is not null group by 1, 2, 3),
total as (select count(*)::double as n from listed),
shares as (
  select g.doc_id, g.u, g.v, c.n / total.n as p1, b.n as seen2, b.n / cv.n::double as p2, t.n as seen3, t.n / bu.n::double as p3
  from grams g join one c on c.w = g.w left join one cv on cv.w = g.v
  left join two b on b.v = g.v and b.w = g.w left join two bu on bu.v = g.u and bu.w = g.v
  left join three t on t.u = g.u and t.v = g.v and t.w = g.w, total
), scored as (
  select doc_id,
         case when u is not null and seen3 >= 2 then p3
              when v is not null and seen2 >= 2 then p2 * case when u is null then 1.0::double else 0.4::double end
              else p1 * case when v is null then 1.0::double when u is null then 0.4::double else 0.4::double * 0.4::double end end as s,
         case when u is not null and seen3 >= 2 then 0
              when v is not null and seen2 >= 2 then case when u is null then 0 else 1 end
              else case when v is null then 0 when u is null then 1 else 2 end end as back
  from shares
), sums as (select doc_id, count(*) as n, sum(back)::bigint as back, sum(ln(s)) as l from scored group by doc_id)
select d.doc_id, coalesce(n, 0)::bigint as n_words, coalesce(back, 0)::bigint as n_backoff, round(l / n, 6) as score
from docs d left join sums s on s.doc_id = d.doc_id
"""
