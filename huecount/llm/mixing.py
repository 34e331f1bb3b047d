"""Mixing sources to target weights by capped water-filling. DataFrame functions only.

Every source has a weight. The words of the mix are as many as those of all documents together; a
source gets its weight's share of them, but never more than ``max_epochs`` times its own words. What a
clamped source cannot take goes to the others in proportion to their weights, again and again until no
source is above its cap. Sorting sources by cap/weight turns that loop into one pass: with the sources
before k clamped, the level is (total - clamped caps) / (weights from k on), and the first source whose
share at that level fits under its cap ends the clamping.

The orderings over sources run in one task, which holds a row a source: sources may be many, but not as many as
documents.

A source then repeats each document floor(target / source words) times, and a seeded prefix of its
documents once more. The prefix follows the md5 of seed and doc_id, and ends at the document where the
words reach the rest of the target. Finding that document takes sums over 4096 ranges of the order and a
sort of one of them; a last pass compares each document with its source's end and shuffles nothing.

Defined results: a null text has size 0; a null source is a source of its own, last in order; a source
without words has target 0; rows of one source that repeat a doc_id are taken alike; an empty table gives an empty result; other columns pass through ``mix``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from huecount.llm.common import cut, hash_hex, n_words

MAX_EPOCHS = 3
WEIGHT_CYCLE = (5, 2, 1)
SEED = "mix-1"
#: The seeded order is cut into this many ranges; one range of one source is sorted by one task.
RANGE_HEX_DIGITS = 3


def source_targets(sizes: DataFrame, weight_cycle=WEIGHT_CYCLE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """sizes(source, source_size) -> source, source_size, weight, target. One row per source, so the
    orderings here are over the list of sources, not over documents."""
    by_name = W.orderBy(F.col("source").asc_nulls_last())
    turn = (F.row_number().over(by_name) - 1) % len(weight_cycle)
    weight = F.element_at(F.array(*[F.lit(int(w)) for w in weight_cycle]), (turn + 1).cast("int")).cast("long")
    cap = F.col("source_size") * max_epochs
    by_ratio = W.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    everything = W.partitionBy()
    ranked = (
        sizes.withColumn("weight", weight)
        .withColumn("cap", cap)
        .withColumn("total", F.sum("source_size").over(everything))
        .withColumn("caps_before", F.coalesce(F.sum("cap").over(by_ratio.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("weights_left", F.sum("weight").over(by_ratio.rowsBetween(0, W.unboundedFollowing)))
        .withColumn("place", F.row_number().over(by_ratio))
    )
    fits = (F.col("total") - F.col("caps_before")) * F.col("weight") <= F.col("cap") * F.col("weights_left")
    first = F.min(F.when(fits, F.col("place"))).over(everything)
    at = lambda name: F.max(F.when(F.col("place") == F.col("first"), F.col(name))).over(everything)
    levelled = ranked.withColumn("first", first).withColumn("rest", at("total") - at("caps_before")).withColumn("left", at("weights_left"))
    target = F.when(F.col("place") < F.col("first"), F.col("cap").cast("double")).otherwise(
        (F.col("rest") * F.col("weight")).cast("double") / F.col("left")
    )
    return levelled.select("source", "source_size", "weight", F.coalesce(target, F.lit(0.0)).alias("target"))


def _ordered(docs: DataFrame, seed: str) -> DataFrame:
    order = hash_hex(seed, F.col("doc_id"))
    return docs.withColumn("mix_order", order).withColumn("mix_range", F.substring("mix_order", 1, RANGE_HEX_DIGITS))


def source_plan(sized: DataFrame, weight_cycle=WEIGHT_CYCLE, max_epochs: int = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """sized(doc_id, source, size) -> one row per source: m_source, source_size, target, whole, upto. A
    document is taken ``whole`` times, and once more if its place in the seeded order is not past ``upto``."""
    sized = _ordered(sized, seed)
    per_range = cut(sized.groupBy("source", "mix_range").agg(F.sum("size").alias("range_size")), "mix-ranges")
    targets = source_targets(per_range.groupBy("source").agg(F.sum("range_size").alias("source_size")), weight_cycle, max_epochs)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    targets = targets.withColumn("whole", whole).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size"))
    targets = cut(targets.withColumnRenamed("source", "m_source"), "mix-targets")
    same = F.col("source").eqNullSafe(F.col("m_source"))
    before = F.sum("range_size").over(W.partitionBy("source").orderBy("mix_range")) - F.col("range_size")
    ends = (
        per_range.withColumn("before", before)
        .join(targets, same)
        .where(F.col("before") + F.col("range_size") > F.col("rest"))
        .groupBy("m_source")
        .agg(F.min(F.struct("mix_range", "before", "rest")).alias("end"))
        .select("m_source", "end.*")
    )
    ends = cut(ends.withColumnRenamed("mix_range", "end_range"), "mix-ends")
    # Only the range in which a source's rest ends has to be sorted: one of 4096.
    running = F.sum("size").over(W.partitionBy("source").orderBy("mix_order"))
    last = (
        sized.join(ends, same & (F.col("mix_range") == F.col("end_range")))
        .groupBy("source", "mix_order", "before", "rest")
        .agg(F.sum("size").alias("size"))
        .withColumn("upto", F.col("before") + running - F.col("size") / 2)
        .where("upto <= rest")
        .groupBy(F.col("source").alias("l_source"))
        .agg(F.max("mix_order").alias("last"))
    )
    ends = ends.withColumnRenamed("m_source", "e_source").select("e_source", "end_range")
    # Without a rest nothing is taken once more, not even a text without words: no document passes max_epochs.
    upto = F.when(F.col("rest") > 0, F.coalesce("last", "end_range", F.lit(""))).otherwise("")
    full = targets.join(ends, F.col("m_source").eqNullSafe(F.col("e_source")), "left").join(last, F.col("m_source").eqNullSafe(F.col("l_source")), "left")
    return cut(full.select("m_source", "source_size", "target", "whole", upto.alias("upto")), "mix-plan")


def _reps(docs: DataFrame, plan: DataFrame, seed: str) -> DataFrame:
    more = (F.col("mix_order") <= F.col("upto")).cast("long")
    return _ordered(docs, seed).join(plan, F.col("source").eqNullSafe(F.col("m_source"))).withColumn("reps", F.col("whole") + more)


def mix_plan(docs: DataFrame, size: Column | None = None, weight_cycle=WEIGHT_CYCLE, max_epochs: int = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """doc_id, source, size, source_size, target, reps, taken of each document; texts stay where they are."""
    sized = cut(docs.select("doc_id", "source", (n_words(F.col("text")) if size is None else size).cast("long").alias("size")), "mix-sizes")
    plan = source_plan(sized, weight_cycle, max_epochs, seed)
    return _reps(sized, plan, seed).select("doc_id", "source", "size", "source_size", "target", "reps", (F.col("reps") * F.col("size")).alias("taken"))


def mix(docs: DataFrame, size: Column | None = None, weight_cycle=WEIGHT_CYCLE, max_epochs: int = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """The mix itself: every document as often as it is taken, with its own columns."""
    sized = cut(docs.select("doc_id", "source", (n_words(F.col("text")) if size is None else size).cast("long").alias("size")), "mix-sizes")
    plan = source_plan(sized, weight_cycle, max_epochs, seed)
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("mix_row")
    taken = _reps(docs.select(row, "doc_id", "source"), plan, seed).where("reps > 0")
    repeated = taken.select("mix_row", F.explode(F.sequence(F.lit(1), F.col("reps").cast("int"))).alias("copy"))
    return repeated.select(*[F.col("mix_row").getField(c).alias(c) for c in docs.columns])


def op3_mixing(docs: DataFrame) -> DataFrame:
    return mix_plan(docs).select("doc_id", "size", "source_size", "target", "taken", "source", "reps")


SQL = r"""
WITH sized AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         md5('mix-1|' || coalesce(doc_id::VARCHAR, '~')) AS o FROM documents),
src AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
w AS (SELECT *, [5, 2, 1][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::BIGINT AS weight FROM src),
r AS (SELECT *, 3 * source_size AS cap, (sum(source_size) OVER ())::BIGINT AS total,
        coalesce(sum(3 * source_size) OVER (ORDER BY 3 * source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS caps_before,
        (sum(weight) OVER (ORDER BY 3 * source_size / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::BIGINT AS weights_left,
        row_number() OVER (ORDER BY 3 * source_size / weight, source NULLS LAST) AS place FROM w),
lvl AS (SELECT total - caps_before AS rest, weights_left, place AS first FROM r
        WHERE (total - caps_before) * weight <= cap * weights_left ORDER BY place LIMIT 1),
t AS (SELECT source, source_size, CASE WHEN place < first THEN cap::DOUBLE ELSE (lvl.rest * weight)::DOUBLE / lvl.weights_left END AS target FROM r, lvl),
f AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM t),
p AS (SELECT s.doc_id, s.source, s.size, f.source_size, f.target, f.whole,
        sum(s.size) OVER (PARTITION BY s.source ORDER BY s.o) - sum(s.size) OVER (PARTITION BY s.source, s.o) / 2 <= f.target - f.whole * f.source_size AND f.target - f.whole * f.source_size > 0 AS more
      FROM sized s JOIN f ON s.source IS NOT DISTINCT FROM f.source)
SELECT doc_id, size, source_size, target, ((whole + more::BIGINT) * size)::BIGINT AS taken, source, (whole + more::BIGINT)::BIGINT AS reps FROM p
"""
