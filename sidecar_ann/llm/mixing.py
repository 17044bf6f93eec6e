"""Mixing sources to target weights by capped water-filling; DataFrame functions only.

Sizes are numbers of words. Sources in code-point order (null last) weigh 1, 2, 3, 1, 2, 3, ...; together they share all
sizes. A source gets at most `epochs` times its own size: the level of the water is the share for one unit of weight at
which the capped sources give up exactly what the others take, found in closed form over the sources sorted by their cap
for one unit of weight (one row a source, never one a document).

Every document of a source is taken floor(target / size) times whole. What is left of the target is filled in the order
of a seeded hash by documents taken once more, and the one on the edge by as many of its words as are missing, so each
source meets its target to less than a word. Running sums go over ranges of the hash first, so a source that holds a
third of all rows is summed by many tasks.

Null and empty texts have size 0 and are taken 0 words. Rows of equal id and size are told apart by nothing and share
what they are taken. A source of size 0 has target 0. An empty table gives no rows. Further columns are ignored."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stage

EPOCHS = 3
SEED = "mix-1"
WORD = r"[^\x20\x09-\x0D]+"
#: Leading hex digits of the hash that make a range: 4096 ranges of each source.
RANGE_DIGITS = 3


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, epochs: int = EPOCHS) -> DataFrame:
    """source, source_size, weight, target: one row a source. Input: source, source_size."""
    whole = Window.partitionBy()
    by_cap = Window.partitionBy().orderBy(F.col("ratio").asc(), F.col("place").asc())
    named = sizes.withColumn("place", F.row_number().over(Window.partitionBy().orderBy(F.col("source").asc_nulls_last())))
    weighed = named.withColumn("weight", ((F.col("place") - 1) % 3 + 1).cast("long")).withColumn("cap", F.col("source_size") * epochs)
    shared = (
        weighed.withColumn("ratio", F.col("cap").cast("double") / F.col("weight"))
        .withColumn("total", F.sum("source_size").over(whole))
        .withColumn("rest", F.col("total") - (F.sum("cap").over(by_cap) - F.col("cap")))
        .withColumn("rest_weight", F.sum("weight").over(whole) - (F.sum("weight").over(by_cap) - F.col("weight")))
        .withColumn("level", F.col("rest").cast("double") / F.col("rest_weight"))
        # the first source, in this order, whose cap lies above the level sets it for all after it
        .withColumn("free", F.col("ratio") > F.col("level"))
        .withColumn("water", F.first(F.when(F.col("free"), F.col("level")), ignorenulls=True).over(by_cap.rowsBetween(Window.unboundedPreceding, 0)))
    )
    target = F.when(F.col("water").isNull(), F.col("cap").cast("double")).otherwise(F.col("water") * F.col("weight"))
    return shared.select("source", "source_size", "weight", target.alias("target"))


def mix_sizes(sized: DataFrame, epochs: int = EPOCHS, seed: str = SEED) -> DataFrame:
    """sized (doc_id, source, size and whatever else) with source_size, target and taken. Read twice."""
    names = sized.columns
    keyed = sized.withColumn("_key", F.md5(F.concat(F.lit(seed + ":"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))).withColumn("_range", F.substring("_key", 1, RANGE_DIGITS))
    by_range = keyed.groupBy("source", "_range").agg(F.sum("size").alias("_sum"))
    per_source = source_targets(by_range.groupBy("source").agg(F.sum("_sum").alias("source_size")), epochs)
    before = by_range.withColumn("_before", F.sum("_sum").over(Window.partitionBy("source").orderBy("_range").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_sum"))
    plan = before.alias("b").join(per_source.alias("s"), F.col("b.source").eqNullSafe(F.col("s.source"))).select("b.source", "b._range", "_before", "s.source_size", "s.target")
    k, p = keyed.alias("k"), plan.alias("p")
    joined = k.join(p, F.col("k.source").eqNullSafe(F.col("p.source")) & (F.col("k._range") == F.col("p._range"))).select("k.*", "p._before", F.col("p.source_size").alias("_ss"), F.col("p.target").alias("_tg"))
    upto = F.sum("size").over(Window.partitionBy("source", "_range").orderBy("_key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0))
    times = F.when(F.col("_ss") > 0, F.floor(F.col("_tg") / F.col("_ss"))).otherwise(0)
    left = F.floor(F.col("_tg")) - times * F.col("_ss")
    part = F.greatest(F.lit(0), F.least(F.col("size"), left - (F.col("_before") + F.col("_upto") - F.col("size"))))
    kept = [c for c in names if c not in ("source_size", "target", "taken")]
    return joined.withColumn("_upto", upto).select(*kept, F.col("_ss").alias("source_size"), F.col("_tg").alias("target"), (times * F.col("size") + part).cast("long").alias("taken"))


def repeat_documents(docs: DataFrame, epochs: int = EPOCHS, seed: str = SEED) -> DataFrame:
    """docs as the mix takes them: each row as often as it is taken whole, once more if at least half of it is taken
    besides. Rows without words are not taken. Columns keep their values, whatever their names."""
    own = docs.select("doc_id", "source", n_words(F.col("text")).alias("size"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"))
    mixed = mix_sizes(own, epochs, seed)
    times = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size")) + F.when(2 * (F.col("taken") % F.col("size")) >= F.col("size"), 1).otherwise(0)).otherwise(0)
    return mixed.select("_row", times.cast("int").alias("_n")).filter("_n > 0").select("_row", F.explode(F.sequence(F.lit(1), F.col("_n")))).select("_row.*")


def sized_documents(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "source", n_words(F.col("text")).alias("size"))


def mix(docs: DataFrame, epochs: int = EPOCHS, seed: str = SEED) -> DataFrame:
    return mix_sizes(stage(sized_documents(docs), "sizes"), epochs, seed)
