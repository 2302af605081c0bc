"""Exact n-gram Jaccard join: size-banded tiles with hashed bitmap signatures.

Documents with equal shingle sets are one class first.  Two classes of similarity
t or more differ in few shingles: at most (1-t)/(1+t) of the sum of their sizes.
Sizes are dealt into bands a factor t wide, so such a pair lies in one band or in
neighbouring ones.  For every pair of bands the hash range of shingles is cut into
one more part than a pair can have differences: in at least one part both sets are
identical.  A tile is (bands, part, hash of the set's part); all pairs meet in a
tile.  Spare parts make up for parts that hold no shingle, so that a set need not
enter the tiles of empty parts, where everything would meet.

Most tiles hold one class only.  To find the others, each task sends its tiles
packed: sorted 48-bit hashes as deltas with two-byte places, about six bytes a tile
instead of a row.  What meets there by chance only costs a comparison.

In a tile the document that shares most tiles is compared with all others, which
joins a group of near copies with as many comparisons as it has members.  What that
leaves is only pairs of a tile whose documents are not in one component yet.  A pair's sizes and
the bit counts of its hashed bitmaps bound the overlap from above; the exact
intersection of the sorted shingle arrays decides what passes the bound.

Defined cases: a null text and a text without words have the empty set and link
with nothing; fewer words than a shingle are one shingle; equal texts link; rows
with equal doc_id are one document with the first text in order if their texts
differ, and each of them has its row in the result; a null doc_id forms no link
and its component is null; an empty table gives an empty result; only ``doc_id``
and ``text`` of the input are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from signpart.llm import hashing, packed_keys, store
from signpart.llm.arrowmap import arrow_map
from signpart.llm.components import components

BITMAP_WORDS = 8
#: Bits of a tile's hash that are sent, and tiles (with their places) that a task packs or unpacks at once.
TILE_BITS, BLOCK_TILES, PART_TILES = 48, 1 << 20, 4 << 20
#: Places in a block at most, as they have two bytes.
BLOCK_PLACES = 1 << 16
#: Bytes of ids that are sent to every executor at most; more are joined.
BROADCAST_BYTES = store.BROADCAST_BYTES

_BITS = [f"b{i}" for i in range(BITMAP_WORDS)]


class Rule:
    """Shingles of ``words`` words; links from ``percent`` of 100 on."""

    def __init__(self, words: int = 3, percent: int = 90):
        self.words, self.percent = words, percent
        # Bounds of the size bands: a partner's size is in the same band or the next.
        bounds = [1]
        while bounds[-1] < 1 << 40:
            bounds.append((bounds[-1] * 100) // percent + 1)
        self.bounds = np.asarray(bounds, dtype=np.int64)

    def band(self, size: int) -> int:
        return int(np.searchsorted(self.bounds, size, "right")) - 1

    def parts(self, band: int) -> tuple[int, int]:
        """(number of parts, empty parts that a set may leave out) for pairs with sizes up to the end of the band.

        With one part more than a linked pair can have differences, and ``spare``
        parts on top, a set with at most ``spare`` empty parts shares a part that
        isn't empty with each partner.
        """
        largest = int(self.bounds[band + 1]) - 1
        need = (100 - self.percent) * 2 * largest // (100 + self.percent) + 1
        empty = need * np.exp(-self.bounds[max(0, band - 1)] / need)
        spare = int(np.ceil(empty + 3 * np.sqrt(empty))) if need > 1 else 0
        return need + spare, spare

    def sets(self, data: np.ndarray, offsets: np.ndarray) -> Iterator[np.ndarray]:
        """The sorted distinct shingle hashes of each row."""
        data = hashing.LOWER[data]
        start, end, first = hashing.word_spans(data, offsets)
        words = hashing.span_hashes(data, start, end)
        n = np.diff(first)
        at = np.arange(max(0, len(words) - self.words + 1))
        grams = hashing.run_hashes(words, at, at + self.words) if len(at) else np.zeros(0, np.uint64)
        short = np.flatnonzero((n > 0) & (n < self.words))
        whole = dict(zip(short.tolist(), hashing.run_hashes(words, first[:-1][short], first[1:][short]))) if len(short) else {}
        for r in range(len(n)):
            if r in whole:
                yield np.asarray([whole[r]], dtype=np.uint64)
            else:
                found = np.sort(grams[first[r] : max(first[r], first[r + 1] - self.words + 1)])
                yield found[np.concatenate([[True], found[1:] != found[:-1]])] if len(found) else found

    def tiles(self, found: np.ndarray) -> list[tuple[np.ndarray, int]]:
        """For the pairs with the band below and with the band above: a hash for each tile of a set, and how many of them a partner must share.

        A part that differs holds a difference at least, so a linked pair has as
        many equal parts as there are more parts than the differences that the
        sizes allow; of these only the empty ones are not tiles.
        """
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(hashing.mix(found + np.uint64(0x5851F42D4C957F2D)))])
        size, band, out = len(found), self.band(len(found)), []
        for pair in (band, band + 1):
            parts, spare = self.parts(pair)
            cut = np.searchsorted(found, (np.arange(1, parts, dtype=np.float64) * (2.0**64 / parts)).astype(np.uint64))
            cut = np.concatenate([[0], cut, [size]])
            place = np.arange(parts, dtype=np.uint64) + np.uint64((pair << 40) & ((1 << 64) - 1))
            tile = hashing.mix(hashing.mix(total[cut[1:]] - total[cut[:-1]]) ^ hashing.mix(place))
            filled = cut[1:] > cut[:-1]
            empty = parts - int(filled.sum())
            if empty <= spare:
                tile = tile[filled]
            else:
                empty = 0
            largest = min(100 * size // self.percent, int(self.bounds[pair + 1]) - 1)
            differences = (100 - self.percent) * (size + largest) // (100 + self.percent)
            out.append((tile, max(1, parts - differences - empty)))
        return out


def _bitmap(found: np.ndarray) -> np.ndarray:
    bits = np.zeros(BITMAP_WORDS * 64, dtype=bool)
    bits[(found & np.uint64(BITMAP_WORDS * 64 - 1)).astype(np.int64)] = True
    return np.packbits(bits, bitorder="little").view(np.int64)


def signatures(docs: DataFrame, rule: Rule) -> DataFrame:
    """(doc_id, n, k1, k2, n_tiles, b0 …): set size, 128-bit hash of the set, most tiles it can have, and bitmap."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, data, offsets in hashing.chunks(batch.column(1)):
                n, k1, k2, most, bits = [], [], [], [], []
                for found in rule.sets(data, offsets):
                    n.append(len(found))
                    k1.append(np.sum(hashing.mix(found)))
                    k2.append(np.bitwise_xor.reduce(hashing.mix(found ^ np.uint64(0xA5A5A5A55A5A5A5A))) if len(found) else np.uint64(0))
                    bits.append(_bitmap(found))
                    most.append(sum(rule.parts(rule.band(len(found)) + up)[0] for up in (0, 1)) if len(found) else 0)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(a, b - a).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(hashing.signed(np.asarray(k1, np.uint64))), pa.array(hashing.signed(np.asarray(k2, np.uint64))),
                        pa.array(most, pa.int64()), *(pa.array(column) for column in np.ascontiguousarray(np.stack(bits).T)),
                    ],
                    names=["doc_id", "n", "k1", "k2", "n_tiles", *_BITS],
                )

    return docs.select("doc_id", "text").transform(arrow_map, make, f"doc_id long, n long, k1 long, k2 long, n_tiles long, {', '.join(f'{b} long' for b in _BITS)}")


def shared_tiles(docs: DataFrame, rule: Rule, n_tiles: int) -> DataFrame:
    """(tile, v): tiles that several documents have, with the documents that share as many as a link takes.

    ``docs`` has each doc_id once, equal sets once, and no empty ones.  A task
    deals its documents into blocks, sorts a block's tiles and sends each hash
    range as one row of packed hashes and places of documents in the block.  The
    ids of a block travel as a row of their own and pass through.  ``n_tiles`` is
    the number of tiles, for choosing the number of hash ranges.
    """
    parts = max(store.shuffle_partitions(docs.sparkSession), -(-n_tiles // PART_TILES))
    bounds = np.asarray([(p << TILE_BITS) // parts for p in range(1, parts)], dtype=np.uint64)
    sent_type = "part int, block long, keys binary, places binary, ids array<long>, least array<int>"
    held_type = "tile long, block long, place int, ids array<long>, least array<int>"
    types = {"part": pa.int32(), "tile": pa.int64(), "block": pa.int64(), "place": pa.int32(), "keys": pa.binary(), "places": pa.binary(), "ids": pa.list_(pa.int64()), "least": pa.list_(pa.int32())}

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Places 2 i and 2 i + 1 are document i's tiles with the band below and above.
        task, ids, least, found, size, block = TaskContext.get().partitionId(), [], [], [], 0, 0
        names = ["part", "block", "keys", "places", "ids", "least"]

        def out() -> pa.RecordBatch:
            nonlocal size, block
            number = (task << 24) + block
            keys = np.concatenate(found) >> np.uint64(64 - TILE_BITS)
            order = np.argsort(keys, kind="stable")
            keys, place = keys[order], np.repeat(np.arange(len(found), dtype="<u2"), [len(t) for t in found])[order]
            cuts = np.concatenate([[0], np.searchsorted(keys, bounds), [len(keys)]])
            rows = [(p, number, packed_keys.packed(keys[a:b]), place[a:b].tobytes(), None, None) for p, (a, b) in enumerate(zip(cuts, cuts[1:])) if b > a]
            rows.append((-1 - number % parts, number, None, None, list(ids), list(least)))
            for kept in (ids, least, found):
                kept.clear()
            size, block = 0, block + 1
            return pa.RecordBatch.from_arrays([pa.array(c, types[n]) for c, n in zip(zip(*rows), names)], names=names)

        for batch in batches:
            known = batch.column(0).to_pylist()
            for a, _, data, offsets in hashing.chunks(batch.column(1)):
                for i, one in enumerate(rule.sets(data, offsets), a):
                    if not len(one) or known[i] is None:
                        continue
                    both = rule.tiles(one)
                    more = sum(len(t) for t, _ in both)
                    if size and (size + more > BLOCK_TILES or len(ids) == BLOCK_PLACES):
                        yield out()
                    for tiles, enough in both:
                        ids.append(known[i])
                        least.append(enough)
                        found.append(tiles)
                    size += more
        if ids:
            yield out()

    def match(table: pa.Table) -> pa.Table:
        names = ["tile", "block", "place", "ids", "least"]
        if table.column("part")[0].as_py() < 0:
            given = {n: table.column(n) for n in ("block", "ids", "least")}
        else:
            keys = [packed_keys.unpacked(x) for x in table.column("keys").to_pylist()]
            block = np.repeat(np.asarray(table.column("block")), [len(k) for k in keys])
            place = np.frombuffer(b"".join(table.column("places").to_pylist()), "<u2")
            key = np.concatenate(keys)
            order = np.argsort(key, kind="stable")
            ranked = key[order]
            head = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
            run = np.diff(np.append(head, len(order)))
            several = order[np.repeat(run > 1, run)]
            given = {"tile": hashing.signed(key[several]), "block": block[several], "place": place[several]}
        n = len(given["block"])
        return pa.table([pa.chunked_array([pa.array(given[c], types[c])]) if isinstance(given.get(c), np.ndarray) else given[c] if c in given else pa.nulls(n, types[c]) for c in names], names=names)

    sent = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").transform(arrow_map, deal, sent_type)
    held = store.written(sent.groupBy("part").applyInArrow(match, held_type))
    ids = held.where("ids is not null").select("block", F.posexplode(F.arrays_zip("ids", "least")).alias("place", "of")).select("block", "place", F.col("of.ids").alias("v"), F.col("of.least").alias("least"))
    # All tiles of a place meet in the join, so counting them there needs no shuffle of its own.
    met = F.count(F.lit(1)).over(Window.partitionBy("block", "place"))
    enough = held.where("ids is null").select("tile", "block", "place").join(ids, ["block", "place"]).withColumn("met", met).where("met >= least")
    enough = store.written(enough.select("tile", "v"))
    several = enough.groupBy("tile").agg(F.min("v").alias("a"), F.max("v").alias("b")).where("a < b").select("tile")
    return enough.join(several, "tile", "left_semi")


def may_link(percent: int) -> Column:
    """Whether sizes n, m and bitmaps b0 … and c0 … allow a link.

    A bit that one bitmap has and the other lacks stands for a shingle that only
    the first set has, so the counts of such bits bound both differences from
    below and the overlap from above.
    """
    extra = lambda x, y: sum(F.bit_count(F.col(f"{x}{i}").bitwiseAND(F.bitwise_not(f"{y}{i}"))) for i in range(BITMAP_WORDS))
    n, m = F.col("n"), F.col("m")
    overlap = F.least(n - extra("b", "c"), m - extra("c", "b"))
    return (100 * F.least(n, m) >= percent * F.greatest(n, m)) & (100 * overlap >= percent * (n + m - overlap))


def _verified(docs: DataFrame, pairs: DataFrame, rule: Rule) -> DataFrame:
    """The pairs (u, v) that link, by the exact intersection of the sorted shingles of both texts."""
    ids = store.broadcast_if_small(store.written(pairs.select(F.explode(F.array("u", "v")).alias("doc_id")).distinct()), most=BROADCAST_BYTES)
    texts = store.written(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(ids, "doc_id", "left_semi").groupBy("doc_id").agg(F.min("text").alias("text")))
    with_v = pairs.join(texts.select(F.col("doc_id").alias("v"), F.col("text").alias("v_text")), "v")
    both = with_v.join(texts.select(F.col("doc_id").alias("u"), F.col("text").alias("u_text")), "u").select("u", "v", "u_text", "v_text")
    percent = rule.percent

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_id, held = None, None
        for batch in batches:
            u, v = (batch.column(i).to_numpy() for i in (0, 1))
            first, second, ok = batch.column(2), batch.column(3), np.zeros(batch.num_rows, bool)
            for a, b, data, offsets in hashing.chunks(second):
                for i, found in enumerate(rule.sets(data, offsets), a):
                    if held_id != u[i]:  # pairs of one document follow each other
                        held = next(rule.sets(*hashing.column_bytes(first.slice(i, 1))))
                        held_id = u[i]
                    both = np.concatenate([held, found])
                    both.sort()
                    same = int(np.count_nonzero(both[1:] == both[:-1]))
                    ok[i] = same > 0 and 100 * same >= percent * (len(both) - same)
            yield pa.RecordBatch.from_arrays([pa.array(u[ok]), pa.array(v[ok])], names=["u", "v"])

    return store.written(both.transform(arrow_map, check, "u long, v long"))


def _labelled(in_tile: DataFrame, label: DataFrame) -> DataFrame:
    """in_tile with c, the component of each document so far."""
    joined = in_tile.join(label.select(F.col("id").alias("__id"), "component_id"), in_tile["v"] == F.col("__id"), "left")
    return joined.select(*in_tile.columns, F.coalesce("component_id", "v").alias("c"))


def jaccard_links(docs: DataFrame, rule: Rule | None = None) -> tuple[DataFrame, DataFrame]:
    """(members, component links): every document with its class, and links that connect all linked classes.

    members has doc_id, n_shingles and class_id, the least doc_id with that set.
    """
    rule = rule or Rule()
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    given, made = docs, store.written(signatures(docs, rule))
    # Repeated doc_ids, seldom many: one row of each goes on.
    repeated = store.written(made.where("doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1").select("doc_id"))
    again = not repeated.isEmpty()
    if again:
        repeated = store.broadcast_if_small(repeated, most=BROADCAST_BYTES)
        first = docs.join(repeated, "doc_id", "left_semi").groupBy("doc_id").agg(F.min("text").alias("text"))
        docs = store.written(docs.join(repeated, "doc_id", "left_anti").unionByName(first))
        made = store.written(signatures(docs, rule))
    classes = made.where("n > 0 and doc_id is not null").groupBy("k1", "k2").agg(F.min("doc_id").alias("class_id")).select(F.col("k1").alias("__k1"), F.col("k2").alias("__k2"), "class_id")
    same_set = (F.col("k1") == F.col("__k1")) & (F.col("k2") == F.col("__k2")) & (F.col("n") > 0)
    members = made.join(classes, same_set, "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("class_id", "doc_id")).alias("class_id"))
    members = store.written(members)

    # Only one document of each class goes on, and only tiles of several classes.
    extra = store.written(members.where("doc_id <> class_id or n_shingles = 0").select("doc_id").distinct())
    heads = docs.where("doc_id is not null").join(store.broadcast_if_small(extra, most=BROADCAST_BYTES), "doc_id", "left_anti")
    in_tile = store.written(shared_tiles(heads, rule, made.agg(F.sum("n_tiles")).first()[0] or 0))
    classes = made.join(in_tile.select(F.col("v").alias("doc_id")).distinct(), "doc_id", "left_semi")
    classes = store.written(classes.select(F.col("doc_id").alias("class_id"), "n", *_BITS))
    # A tile's lead is the document that shares most tiles with others: near copies of
    # one text are closer to that text than to each other.
    shares = in_tile.join(in_tile.groupBy("tile").agg(F.count(F.lit(1)).alias("k")), "tile").groupBy("v").agg(F.sum("k").alias("met"))
    in_tile = store.written(in_tile.join(shares, "v"))

    light = classes.select(F.col("class_id").alias("u"), "n", *_BITS)
    other = classes.select(F.col("class_id").alias("v"), F.col("n").alias("m"), *(F.col(b).alias(f"c{i}") for i, b in enumerate(_BITS)))

    def passing(pairs: DataFrame) -> DataFrame:
        sized = pairs.join(light, "u").join(other, "v")
        return sized.where(may_link(rule.percent)).select("u", "v")

    def stars(rows: DataFrame) -> DataFrame:
        """Each tile's lead with the tile's other documents."""
        leads = rows.groupBy("tile").agg(F.max_by("v", F.struct("met", -F.col("v"))).alias("lead"))
        pairs = rows.join(leads, "tile").where("v <> lead")
        return pairs.select(F.least("v", "lead").alias("u"), F.greatest("v", "lead").alias("v")).distinct()

    tried = store.written(stars(in_tile))
    links = _verified(docs, store.written(passing(tried)), rule)

    # What is left: pairs of one tile in different components.
    labelled = store.written(_labelled(in_tile, components(links)).drop("met"))
    open_tiles = labelled.groupBy("tile").agg(F.min("c").alias("a"), F.max("c").alias("b")).where("a < b").select("tile")
    rest = store.written(labelled.join(open_tiles, "tile", "left_semi"))
    rows = rest.groupBy("tile", "c").agg(F.count(F.lit(1)).alias("rows"))
    main = rows.groupBy("tile").agg(F.max_by("c", F.struct("rows", "c")).alias("main"), F.max("rows").alias("main_rows"))
    out = store.written(rest.join(main, "tile").where("c <> main or main_rows = 1"))
    # Documents outside a tile's main component are held against that component once,
    # however many tiles they share with it, and against each other in their tiles.
    # The bounds are part of the joins' conditions: only pairs that pass come out.
    one = rest.select(F.col("v").alias("u"), F.col("c").alias("uc")).distinct().join(light, "u")
    to_main = out.where("c <> main and main_rows > 1").select("v", F.col("main").alias("uc")).distinct().join(other, "v")
    left = out.select("tile", F.col("v").alias("u"), F.col("c").alias("uc")).join(light, "u")
    right = out.select("tile", "v", F.col("c").alias("vc")).join(other, "v")
    apart = (left["tile"] == right["tile"]) & (F.col("uc") != F.col("vc")) & (F.col("u") < F.col("v"))
    met = one.join(to_main, (one["uc"] == to_main["uc"]) & may_link(rule.percent)).select("u", "v").unionByName(left.join(right, apart & may_link(rule.percent)).select("u", "v"))
    more = met.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct().join(tried, ["u", "v"], "left_anti")
    more = store.written(more)
    if not more.isEmpty():
        links = links.unionByName(_verified(docs, more, rule))
    if again:
        members = members.where("doc_id is null").unionByName(given.where("doc_id is not null").select("doc_id").join(members, "doc_id").select(*members.columns))
    return members, links


def jaccard_groups(docs: DataFrame, words: int = 3, percent: int = 90) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every document."""
    members, links = jaccard_links(docs, Rule(words, percent))
    label = components(links)
    joined = members.join(label, members["class_id"] == label["id"], "left")
    return joined.select("doc_id", "n_shingles", F.coalesce("component_id", "class_id").alias("component_id"))


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_groups(store.table(spark, sf_dir, "documents"))


OP7_SQL = r"""
with recursive docs as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as words from documents
), shingles as (
  select distinct doc_id, case when len(words) < 3 then array_to_string(words, ' ') else array_to_string(list_slice(words, pos, pos + 2), ' ') end as s
  from (select doc_id, words, unnest(range(1, greatest(len(words) - 2, 1) + 1)) as pos from docs where len(words) > 0)
), sizes as (select doc_id, count(*)::bigint as n from shingles group by doc_id),
common as (
  select a.doc_id as u, b.doc_id as v, count(*) as both from shingles a join shingles b on a.s = b.s and a.doc_id < b.doc_id group by 1, 2
), links as (
  select u, v from common join sizes x on x.doc_id = u join sizes y on y.doc_id = v where 100 * "both" >= 90 * (x.n + y.n - "both")
), ways as (select u, v from links union all select v, u from links),
reach(doc_id, other) as (
  select doc_id, doc_id from docs union select r.doc_id, w.v from reach r join ways w on r.other = w.u
)
select d.doc_id, coalesce(n, 0)::bigint as n_shingles, least(d.doc_id, min(r.other)) as component_id
from docs d left join sizes on sizes.doc_id = d.doc_id left join reach r on r.doc_id = d.doc_id group by d.doc_id, n
"""
