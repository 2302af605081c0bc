"""Document fingerprints by Order MinHash, in DataFrame functions only.

The k-mers of a text are runs of ``k`` words with an occurrence number, so that
the second copy of a run is another element than the first.  Each component of the
fingerprint takes two elements that are minimal under two hash functions, puts
them in their order in the text and hashes the pair: it changes if the elements
change or swap, and so follows edit distance rather than set overlap.

Occurrence numbers come from one primitive sort per text of (hash, position)
packed in a long: equal hashes stand together in the order of positions.  The
elements are exploded, and the minima are plain aggregates with the position in
their low bits, combined before any shuffle.

Likeness of two fingerprints is the share of equal components.

Defined cases: a null text is empty; a text without words has one element of its
own, so empty texts are alike; fewer than ``k`` words are one element; positions
beyond 2**24 words count as the last; every row of the input has one row in the
result, repeated ones too; rows with equal doc_id follow each other in an order of
their texts (by hash, then by text), so that one doc_id that many rows share is
dealt over many tasks; with one document the next is itself; an empty table gives
an empty result; only doc_id and text are read; a null doc_id comes last in
descending order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from signpart.llm import store

K, COMPONENTS = 2, 32
_PLACE_BITS = 24
_PLACE = (1 << _PLACE_BITS) - 1
WHITE = r"[\x20\x09-\x0D]+"


def elements(text: Column, k: int = K) -> Column:
    """Longs of an occurrence-numbered k-mer's hash (high bits) and its position (low bits)."""
    words = F.split(F.btrim(text, F.lit(" \t\n\x0b\x0c\r")), WHITE)
    place = lambda i: F.least(i, F.lit(_PLACE)).cast("long")

    def packed(w: Column) -> Column:
        last = F.greatest(F.size(w) - F.lit(k), F.lit(0))
        kmer = lambda i: F.xxhash64(*(F.get(w, i + j) for j in range(k)))
        return F.transform(F.sequence(F.lit(0), last), lambda i: kmer(i).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(place(i)))

    one = F.transform(F.array(words), packed)[0]
    return _numbered(F.sort_array(one))


def _numbered(s: Column) -> Column:
    """Adds occurrence numbers to sorted (hash, position) longs: a first occurrence keeps its hash."""

    def number(a: Column) -> Column:
        high = lambda x: F.shiftright(x, _PLACE_BITS)
        starts = F.filter(F.sequence(F.lit(0), F.size(a) - 1), lambda i: (i == 0) | (high(F.get(a, i)) != high(F.get(a, i - 1))))

        def with_counts(st: Column) -> Column:
            sizes = F.transform(st, lambda x, i: F.coalesce(F.get(st, i + 1), F.size(a)) - x)
            counts = F.flatten(F.transform(sizes, lambda m: F.sequence(F.lit(0), m - 1)))
            renamed = F.zip_with(a, counts, lambda x, c: F.when(c == 0, x).otherwise(F.xxhash64(high(x), c).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(x.bitwiseAND(F.lit(_PLACE)))))
            return F.when(F.size(st) == F.size(a), a).otherwise(renamed)

        return F.transform(F.array(starts), with_counts)[0]

    return F.transform(F.array(s), number)[0]


def fingerprints(texts: DataFrame, key: list[str], facts: list[str] = (), components: int = COMPONENTS, k: int = K) -> DataFrame:
    """key columns, numeric ``facts`` and ``fingerprint``, an array of ints, of (key, text) rows; equal keys are one text."""
    rows = texts.select(*key, *facts, F.explode(elements(F.coalesce("text", F.lit("")), k)).alias("x"))
    element = F.shiftright("x", _PLACE_BITS)
    place = F.col("x").bitwiseAND(F.lit(_PLACE))
    ranked = [F.min(F.xxhash64(element, F.lit(j)).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(place)).alias(f"m{j}") for j in range(2 * components)]
    least = rows.groupBy(*key).agg(*(F.min(f).alias(f) for f in facts), *ranked)

    def component(j: int) -> Column:
        a, b = F.col(f"m{2 * j}"), F.col(f"m{2 * j + 1}")
        first = a.bitwiseAND(F.lit(_PLACE)) <= b.bitwiseAND(F.lit(_PLACE))
        ka, kb = F.shiftright(a, _PLACE_BITS), F.shiftright(b, _PLACE_BITS)
        return F.hash(F.when(first, ka).otherwise(kb), F.when(first, kb).otherwise(ka), first)

    return least.select(*key, *facts, F.array(*(component(j) for j in range(components))).alias("fingerprint"))


def as_text(fingerprint: Column) -> Column:
    return F.concat_ws("", F.transform(fingerprint, lambda c: F.lpad(F.hex(c.cast("long").bitwiseAND(F.lit(0xFFFFFFFF))), 8, "0")))


def likeness(a: Column, b: Column) -> Column:
    """Share of equal components."""
    same = F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda s, x: s + x)
    return same / F.size(a).cast("double")


def in_ring(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """(doc_id, text, next_id, next_text, at, next_at): the next document in descending order of doc_id; the first follows the last.

    Ranges of doc_id from approximate quantiles are the groups of one window each;
    the first row of every range closes the gap to the range before.  A doc_id that
    holds several quantiles, and a null one, is cut further by the text's hash.
    ``at`` numbers the rows, ``next_at`` is the number of the next row.
    """
    spark = docs.sparkSession
    clean = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    wanted = parts or 4 * store.shuffle_partitions(spark)
    quantiles = [int(b) for b in clean.select(F.col("doc_id").cast("double").alias("d")).stat.approxQuantile("d", [i / wanted for i in range(1, wanted)], 1 / (4 * wanted))]
    bounds, bits = sorted(set(quantiles)), max(1, wanted.bit_length())
    heavy = [b for b in bounds if quantiles.count(b) > 1]
    slice_ = F.shiftrightunsigned(F.xxhash64("text"), 64 - bits)
    # Number of bounds up to the doc_id, by a search tree of comparisons over at most ``wanted`` literals.
    base = F.when(F.col("doc_id").isNull(), F.lit(-1)).otherwise(_search(bounds, F.col("doc_id"), 0)).cast("long")
    sliced = F.col("doc_id").isNull() | F.col("doc_id").isin(heavy) if heavy else F.col("doc_id").isNull()
    ranged = clean.withColumn("slice", F.when(sliced, slice_).otherwise(F.lit(1 << bits)).cast("long")).withColumn("bucket", base * F.lit((1 << bits) + 1) + F.col("slice"))
    order = Window.partitionBy("bucket").orderBy(F.desc_nulls_last("doc_id"), F.desc("text"))
    # Plain columns: a struct would travel beside the text that it repeats.
    here = ranged.select("bucket", "doc_id", "text", F.lead("doc_id").over(order).alias("after_id"), F.lead("text").over(order).alias("after_text"), F.lead(F.lit(True)).over(order).alias("inner"), F.row_number().over(order).alias("place"))
    # One row for each range: its first document, and that of the range that follows it.
    top = ranged.groupBy("bucket").agg(F.max(F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id", "text")).alias("x")).select("bucket", F.struct("x.doc_id", "x.text").alias("first"))
    ids = [r[0] for r in top.select("bucket").orderBy(F.desc("bucket")).collect()]
    follows = spark.createDataFrame([(a, b) for a, b in zip(ids, [*ids[1:], *ids[:1]])], "bucket long, after long")
    after = follows.join(top.withColumnRenamed("bucket", "after"), "after").select(F.col("bucket").alias("from"), "after", "first")
    joined = here.join(after, (F.col("bucket") == F.col("from")) & F.col("inner").isNull(), "left")
    number = lambda bucket, place: F.col(bucket) * F.lit(1 << 40) + place
    return joined.select(
        "doc_id", "text", F.when(F.col("inner"), F.col("after_id")).otherwise(F.col("first.doc_id")).alias("next_id"), F.when(F.col("inner"), F.col("after_text")).otherwise(F.col("first.text")).alias("next_text"),
        number("bucket", F.col("place")).alias("at"), F.when(F.col("inner"), number("bucket", F.col("place") + 1)).otherwise(number("after", F.lit(1))).alias("next_at"),
    )


def _search(bounds: list[int], x: Column, base: int) -> Column:
    if not bounds:
        return F.lit(base)
    mid = len(bounds) // 2
    return F.when(x < bounds[mid], _search(bounds[:mid], x, base)).otherwise(_search(bounds[mid + 1 :], x, base + mid + 1))


def edited(text: Column, following: Column) -> Column:
    """The text with its last floor(n/3) code points replaced by the first as many of the following text."""
    cut = F.floor(F.length(text) / 3).cast("int")
    return F.concat(F.substring(text, F.lit(1), F.length(text) - cut), F.substring(following, F.lit(1), cut))


def document_fingerprints(docs: DataFrame, components: int = COMPONENTS, k: int = K) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likenesses."""
    ring = in_ring(docs).withColumn("edited", edited(F.col("text"), F.col("next_text")))
    texts = F.array(F.struct(F.lit(0).alias("which"), F.col("text").alias("text")), F.struct(F.lit(1).alias("which"), F.col("edited").alias("text")))
    # The digest travels as four longs, so that the aggregation stays one of fixed-width values.
    digest = F.sha2("edited", 256)
    quarters = [F.conv(F.substring(digest, 16 * i + 1, 16), 16, -10).cast("long").alias(f"d{i}") for i in range(4)]
    facts = ["doc_id", "n_chars", "next_at", *(f"d{i}" for i in range(4))]
    split = ring.select("at", "doc_id", "next_at", F.length("text").cast("long").alias("n_chars"), *quarters, F.explode(texts).alias("t"))
    rows = split.select("at", F.col("t.which").alias("which"), *facts, F.col("t.text").alias("text"))
    made = store.written(fingerprints(rows, ["at", "which"], facts, components, k))

    own = made.where("which = 0").select("at", "doc_id", "n_chars", "next_at", F.concat_ws("", *(F.lpad(F.hex(f"d{i}"), 16, "0") for i in range(4))).alias("digest"), F.col("fingerprint").alias("own"))
    changed = made.where("which = 1").select("at", F.col("fingerprint").alias("changed"))
    after = made.where("which = 0").select(F.col("at").alias("after_at"), F.col("fingerprint").alias("after"))
    joined = own.join(changed, "at").join(after, F.col("next_at") == F.col("after_at"))
    return joined.select(
        "doc_id", "n_chars", F.lower("digest").alias("edited_sha256"), as_text(F.col("own")).alias("fingerprint"), as_text(F.col("changed")).alias("edited_fingerprint"),
        likeness(F.col("own"), F.col("changed")).alias("near_edited"), likeness(F.col("own"), F.col("after")).alias("near_next"),
    )


def op1_order_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return document_fingerprints(store.table(spark, sf_dir, "documents"))
