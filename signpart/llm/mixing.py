"""Mixing sources to target weights.

Words are summed per source, targets are the weighted shares of the wanted total
with a ceiling of ``most_repeats`` times a source's own size, and every document
is emitted floor(rate) times plus once more with the fraction of the rate as its
probability.  The chance of a document is a hash of its doc_id and the seed, so
reruns agree.

The ceiling is found without a loop: a source is at its ceiling exactly if the
common level (target per weight) is at least its ceiling per weight.  In the order
of ceiling per weight, the level after filling the first k sources follows from
prefix sums, so one pass over the per-source table gives all targets.  That table
has one row per source; the documents are not sorted.

Defined cases: a null text has size 0; a null source is a source, last in order;
sources of size 0 have target 0; if all sources are at their ceilings the total
falls short of the wanted share; rows with equal doc_id share one chance; a null
doc_id is hashed like any other value; an empty table gives an empty result.
Columns of the input called ``size``, ``source_size``, ``target``, ``copies`` or
``taken`` are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from signpart.llm import store

WORD = r"[^\x20\x09-\x0D]+"
_ADDED = ("size", "source_size", "target", "copies", "taken")


def word_count(text) -> F.Column:
    """Number of words: the words become single marks, white space goes."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[float, ...], share: float, most_repeats: float) -> DataFrame:
    """(source, source_size, target) from (source, size); weights repeat over the sources in order, null last."""
    per_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    listed = per_source.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.row_number().over(by_name) - 1) % len(weights) + 1).cast("double"))
    ceiling = F.col("source_size") * F.lit(float(most_repeats))
    in_order = Window.orderBy("per_weight", F.col("source").asc_nulls_last())
    before = in_order.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    levels = (
        listed.withColumns({"ceiling": ceiling, "per_weight": ceiling / F.col("weight")})
        .withColumns({"wanted": F.sum("source_size").over(whole) * F.lit(float(share)), "all_weight": F.sum("weight").over(whole)})
        .withColumns({"filled": F.coalesce(F.sum("ceiling").over(before), F.lit(0.0)), "used_weight": F.coalesce(F.sum("weight").over(before), F.lit(0.0))})
        .withColumn("level", (F.col("wanted") - F.col("filled")) / (F.col("all_weight") - F.col("used_weight")))
        .withColumn("below", F.col("level") < F.col("per_weight"))
        .withColumn("common", F.min(F.when(F.col("below"), F.struct("per_weight", F.col("source").isNull().alias("last"), "source", "level"))).over(whole)["level"])
    )
    target = F.when(F.col("common").isNull() | (F.col("per_weight") <= F.col("common")), F.col("ceiling")).otherwise(F.col("common") * F.col("weight"))
    return levels.select("source", "source_size", target.alias("target"))


def mix_sources(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most_repeats: float = 2.0, seed: int = 17) -> DataFrame:
    """docs with size, source_size, target (of the source), copies and taken = copies * size.

    The per-source table is joined back; it has a row per distinct source only,
    and Spark chooses the join by its size.
    """
    kept = [c for c in docs.columns if c.lower() not in _ADDED]
    sized = docs.select(*kept, word_count(F.col("text")).alias("size"))
    (of_,) = store.free_names(sized, "of_source")
    targets = source_targets(sized.select("source", "size"), weights, share, most_repeats).withColumnRenamed("source", of_)
    joined = sized.join(targets, F.col("source").eqNullSafe(F.col(of_))).drop(of_)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    chance = F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") / F.lit(float(1 << 52))
    whole = F.floor(rate)
    copies = whole + F.when(chance < rate - whole, 1).otherwise(0)
    return joined.withColumn("copies", copies.cast("long")).withColumn("taken", F.col("copies") * F.col("size"))


def repeated(mixed: DataFrame, columns: list[str]) -> DataFrame:
    """Each document ``copies`` times."""
    (copy_,) = store.free_names(mixed, "copy")
    return mixed.where("copies > 0").withColumn(copy_, F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).select(*columns)


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = store.table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return mix_sources(docs).select("doc_id", "size", "source_size", "target", "taken")


OP3_SQL = r"""
with sized as (
  select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents
), per_source as (
  select source, sum(size)::bigint as source_size, (row_number() over (order by source nulls last) - 1) % 3 as place from sized group by source
), weighted as (
  select source, source_size, case place when 0 then 5.0::double when 1 then 2.0::double else 1.0::double end as weight, 2.0::double * source_size as ceiling from per_source
), prefixed as (
  select *, ceiling / weight as per_weight, sum(source_size) over ()::double * 1.5::double as wanted, sum(weight) over () as all_weight,
         coalesce(sum(ceiling) over w, 0.0::double) as filled, coalesce(sum(weight) over w, 0.0::double) as used_weight
  from weighted window w as (order by ceiling / weight, source nulls last rows between unbounded preceding and 1 preceding)
), levels as (
  select *, (wanted - filled) / (all_weight - used_weight) as level from prefixed
), chosen as (
  select *, (select min(level) from levels where level < per_weight and per_weight = (select min(per_weight) from levels where level < per_weight)) as common from levels
), targets as (
  select source, source_size, case when common is null or per_weight <= common then ceiling else common * weight end as target from chosen
)
select doc_id, size, source_size, target,
  (floor(case when source_size > 0 then target / source_size else 0.0::double end)::bigint
   + case when ('0x' || substr(md5('17:' || coalesce(doc_id::varchar, '')), 1, 13))::bigint::double / 4503599627370496.0::double
        < (case when source_size > 0 then target / source_size else 0.0::double end) - floor(case when source_size > 0 then target / source_size else 0.0::double end)
     then 1 else 0 end) * size as taken
from sized join targets on sized.source is not distinct from targets.source
"""
