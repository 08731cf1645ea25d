"""Mixing sources to target weights, in DataFrame operations only.

Words are added up per source; a source's share follows its weight, but no more than ``most`` times
its own words, and what is above goes to the others by weight. That is a water level: sources in
order of (limit / weight) are filled up to their limits as long as the level of the rest is above.
Each document is then emitted floor(rate) times, and once more when a hash of its id is below the
rate's fraction; rate = target / words of the source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from flowregions.llm.common import cut

WEIGHTS, MOST, SEED = (5, 2, 1), 3, "mixture-1"
#: The rates of so many sources, those with the most documents, are broadcast (a few MB); the rest are joined by shuffle.
BROADCAST_SOURCES = 50_000


def words(text: Column) -> Column:
    r"""Number of words ``[^\x20\x09-\x0D]+``; null: 0."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def chance(ident: Column, seed: str) -> Column:
    """A number in [0, 1) from the id and the seed alone: the first 13 hex digits of an MD5."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(ident.cast("string"), F.lit("null")))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") / F.lit(float(16**13))


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """(source, source_size, documents, target) from (source, size) rows. Sources by code point, null last, take the weights in turn."""
    total = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("documents"))
    number = Window.orderBy(F.col("source").isNull(), "source")
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.pmod(F.row_number().over(number) - 1, F.lit(len(weights))) + 1).cast("int"))
    wide = "decimal(38,0)"
    rows = total.withColumn("w", weight.cast("long")).withColumn("cap", F.col("source_size") * most)
    ratio = F.col("cap").cast("double") / F.col("w")
    level = Window.orderBy(F.col("ratio"), F.col("source").isNull(), "source")
    rows = (
        rows.withColumn("ratio", ratio)
        .withColumn("left", F.sum("source_size").over(Window.partitionBy(F.lit(0))) - F.coalesce(F.sum("cap").over(level.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("behind", F.sum("w").over(level.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("full", F.col("left").cast(wide) * F.col("w").cast("decimal(18,0)") > F.col("cap").cast(wide) * F.col("behind").cast("decimal(18,0)"))
    )
    before = level.rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("left", F.first(F.when(~F.col("full"), F.col("left")), ignorenulls=True).over(before)).withColumn("behind", F.first(F.when(~F.col("full"), F.col("behind")), ignorenulls=True).over(before))
    share = F.when(F.col("left").isNull(), F.col("cap").cast("double")).otherwise(F.col("w") * F.col("left").cast("double") / F.col("behind"))
    return rows.select("source", "source_size", "documents", share.alias("target"))


def rates(docs: DataFrame, source_col: str = "source", text_col: str = "text", weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    sizes = docs.select(docs[source_col].cast("string").alias("source"), words(docs[text_col]).alias("size"))
    return cut(targets(sizes, weights, most))


def copies(docs: DataFrame, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", weights: tuple[int, ...] = WEIGHTS, most: int = MOST, seed: str = SEED, keep: tuple[str, ...] = ()) -> DataFrame:
    """The columns of ``keep`` as a struct ``row``, and (id, size, source_size, target, copies) of every document.

    Two scans: one adds up the words per source (partial sums, so a hot source is no hot key), one
    decides; with at most BROADCAST_SOURCES sources nothing of the documents is shuffled, and with more
    only documents of the sources with the fewest documents are, so a hot source never meets in one task.
    Null and empty texts have size 0; a source of only such has target 0 and takes nothing. Rows with one id
    (or without) decide alike, repeated rows stay repeated. Very long texts only add to a sum. An empty table
    gives no rows. Reruns agree. Other columns cannot clash: they travel in ``row``.
    """
    table = rates(docs, source_col, text_col, weights, most)
    size = words(docs[text_col])
    rows = docs.select(docs[id_col].alias("id"), docs[source_col].cast("string").alias("_of"), size.alias("size"), *([F.struct(*[docs[c] for c in keep]).alias("row")] if keep else []))
    rated = F.struct("source_size", "target")
    if table.count() <= BROADCAST_SOURCES:
        side = F.broadcast(table.select(F.col("source").alias("_source"), "source_size", "target"))
        joined = rows.join(side, F.col("_of").eqNullSafe(F.col("_source"))).drop("_of", "_source")
    else:
        ranked = cut(table.select("source", rated.alias("_rate"), (F.row_number().over(Window.orderBy(F.desc("documents"), F.col("source").isNull(), "source")) <= BROADCAST_SOURCES).alias("_large")))
        large = F.broadcast(ranked.filter("_large").select(F.col("source").alias("_source"), F.col("_rate").alias("_a")))
        rest = ranked.filter("not _large").select(F.col("source").alias("_small"), F.col("_rate").alias("_b"))
        # rows that are rated already get a key of their own, so they spread over the tasks of the shuffle
        salted = rows.withColumn("_salt", F.xxhash64("id", "size", F.monotonically_increasing_id()))
        some = salted.join(large, F.col("_of").eqNullSafe(F.col("_source")), "left").drop("_source")
        some = some.withColumn("_key", F.when(F.col("_a").isNull(), F.col("_of")).otherwise(F.concat(F.lit("\u0000"), F.col("_salt").cast("string"))))
        joined = some.join(rest, F.col("_key").eqNullSafe(F.col("_small")), "left").withColumn("_rate", F.coalesce("_a", "_b"))
        joined = joined.withColumn("source_size", F.col("_rate.source_size")).withColumn("target", F.col("_rate.target")).drop("_of", "_salt", "_key", "_small", "_a", "_b", "_rate")
    rate = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(most)))).otherwise(0.0)
    joined = joined.withColumn("rate", rate)
    extra = (chance(F.col("id"), seed) < F.col("rate") - F.floor("rate")).cast("long")
    return joined.withColumn("copies", F.floor("rate") + extra).drop("rate")


def plan(docs: DataFrame, id_col: str = "doc_id", **how) -> DataFrame:
    """(id, size, source_size, target, taken): taken counts the words that the mix takes, repeats included."""
    rows = copies(docs, id_col, **how)
    return rows.select(F.col("id").alias(id_col), "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def mix(docs: DataFrame, id_col: str = "doc_id", **how) -> DataFrame:
    """The mixed corpus: each document as often as it is taken, with all its columns."""
    rows = copies(docs, id_col, keep=tuple(docs.columns), **how)
    return rows.withColumn("_copy", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int")))).select("row.*")
