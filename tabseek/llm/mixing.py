"""Mixing sources to target weights by repetition rates.

A document's size is its number of words. Sources get targets in proportion to
their weights, held at ``max_rate`` times their own size; what a held source
can't take goes to the others by weight, until none is above. The levels at
which sources are held follow from one pass over the sources in the order of
``max_rate * size / weight``: nothing iterates. Each document is then taken
floor(rate) times, plus once more if its draw, a hash of its id in [0, 1), falls
below the fraction.

The draws of a source may be turned in a circle without changing any document's
chance. Of ``TURNS`` turns each source gets the one whose taken words come
nearest its target, found from sums by source and interval of draws: one small
table, made in the pass that adds the sizes up. So a source misses its target by
a document or so, not by the spread of independent draws.

Defined cases: a null text has size 0; the null source is a source of its own,
last in order; a source of size 0 has target 0 and rate 0; rows of one doc_id
get one draw; an empty table gives no rows; a long text is one document, however
much of its source it is. ``mix`` replaces columns of the names that it adds;
``emit`` keeps all columns as they are, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from .store import free_prefix, materialise

WORD = r"[^\x20\x09-\x0D]+"
#: Intervals of draws that sizes are added up by, and turns of the draws that are tried.
INTERVALS, TURNS = 4096, 64


def draw(doc_id: Column, seed: int) -> Column:
    """A number in [0, 1) from a portable hash of the id."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(doc_id.cast("string"), F.lit("null"))))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") / F.lit(float(1 << 52))


def source_targets(sizes: DataFrame, cycle: int = 3, max_rate: float = 3.0) -> DataFrame:
    """(source, source_size) to (source, source_size, target, rate); one row per source.

    Weights are 1 .. ``cycle`` over the sources in code-point order, repeating.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    by_level = Window.orderBy("level", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    ranked = sizes.withColumn("weight", ((F.row_number().over(by_name) - 1) % cycle + 1).cast("double")).withColumn("level", max_rate * F.col("source_size") / F.col("weight"))
    # the water level if all sources before this one are held
    held = ranked.select(
        "*",
        ((F.sum("source_size").over(everything) - max_rate * F.coalesce(F.sum("source_size").over(by_level), F.lit(0))) / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(by_level), F.lit(0.0)))).alias("water"),
    )
    level = F.min(F.when(F.col("water") <= F.col("level"), F.col("water"))).over(everything)
    first = F.min(F.when(F.col("water") <= F.col("level"), F.struct("level", "water"))).over(everything)["water"]
    target = F.least(max_rate * F.col("source_size"), F.coalesce(first, level, F.lit(0.0)) * F.col("weight"))
    return held.select("source", "source_size", target.alias("target")).withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))


def sums_by_draw(docs: DataFrame, size: Column, seed: int) -> DataFrame:
    """(source, interval, part): words by source and interval of draws, in shared storage; at most ``INTERVALS`` rows a source."""
    drawn = docs.select("source", size.alias("size"), F.floor(draw(F.col("doc_id"), seed) * INTERVALS).cast("int").alias("interval"))
    return materialise(drawn.groupBy("source", "interval").agg(F.sum("size").alias("part")), "mixing-sums")


def best_turns(sums: DataFrame, targets: DataFrame) -> DataFrame:
    """``targets`` (source, source_size, target, rate) with ``turn``: the turn of draws whose taken words come nearest the target."""
    fraction = F.col("rate") - F.floor("rate")
    known = targets.select("*", fraction.alias("fraction"), F.floor(fraction * INTERVALS).cast("int").alias("whole")).withColumnRenamed("source", "_source")
    rows = sums.join(known.select("_source", "whole"), F.col("source").eqNullSafe(F.col("_source"))).withColumn("turn", F.explode(F.sequence(F.lit(0), F.lit(TURNS - 1))))
    at = F.pmod(F.col("interval") - F.col("turn") * (INTERVALS // TURNS), F.lit(INTERVALS))
    # the interval that the fraction ends in counts by half, so all are counted twice
    twice = F.sum(F.col("part") * F.when(at < F.col("whole"), 2).when(at == F.col("whole"), 1).otherwise(0))
    taken = rows.groupBy(F.col("_source").alias("_by"), "turn").agg(twice.alias("twice"))
    joined = known.join(taken, F.col("_source").eqNullSafe(F.col("_by")))
    off = F.abs(F.col("twice") - 2 * F.col("fraction") * F.col("source_size"))
    best = joined.groupBy(F.col("_source").alias("source"), "source_size", "target", "rate").agg(F.min(F.struct(off.alias("off"), "turn")).alias("best"))
    return best.select("source", "source_size", "target", "rate", F.col("best.turn").alias("turn"))


def _taken(docs: DataFrame, prefix: str, seed: int, cycle: int, max_rate: float) -> DataFrame:
    """``docs`` with size, source_size, target and copies under ``prefix``.

    The per-source table is joined by source. It is far smaller than ``docs`` but
    grows with the number of sources, so its broadcast is left to the planner,
    which knows its size; beyond the limit the hot source's partition is split.
    """
    # the sizes of a text are needed twice; counting words again costs less than shuffling texts
    size = F.regexp_count(F.coalesce(F.col("text"), F.lit("")), F.lit(WORD)).cast("long")
    sums = sums_by_draw(docs, size, seed)
    targets = source_targets(sums.groupBy("source").agg(F.sum("part").alias("source_size")), cycle, max_rate)
    turned = best_turns(sums, targets)
    own = docs.withColumn(f"{prefix}size", size)
    joined = own.join(turned.select(*[F.col(c).alias(prefix + c) for c in turned.columns]), F.col("source").eqNullSafe(F.col(f"{prefix}source")), "left")
    rate, shift = F.coalesce(F.col(f"{prefix}rate"), F.lit(0.0)), F.coalesce(F.col(f"{prefix}turn"), F.lit(0)) / F.lit(float(TURNS))
    at = draw(F.col("doc_id"), seed) - shift
    extra = (F.when(at < 0, at + 1).otherwise(at) < rate - F.floor(rate)).cast("long")
    copies = F.when(F.col(f"{prefix}size") > 0, F.floor(rate) + extra).otherwise(0).cast("long")
    return joined.withColumn(f"{prefix}copies", copies).drop(f"{prefix}source", f"{prefix}rate", f"{prefix}turn")


_ADDED = ("size", "source_size", "target", "copies")


def mix(docs: DataFrame, seed: int = 17, cycle: int = 3, max_rate: float = 3.0) -> DataFrame:
    """``docs`` (doc_id, text, source, ...) with size, source_size, target and copies."""
    docs = docs.drop(*_ADDED)
    prefix = free_prefix(docs.columns)
    out = _taken(docs, prefix, seed, cycle, max_rate)
    return out.select(*docs.columns, *[F.col(prefix + c).alias(c) for c in _ADDED])


def report(docs: DataFrame, **options) -> DataFrame:
    """Per document: doc_id, size, source_size, target, taken."""
    return mix(docs.select("doc_id", "text", "source"), **options).select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def emit(docs: DataFrame, seed: int = 17, cycle: int = 3, max_rate: float = 3.0) -> DataFrame:
    """The mixed corpus: each document's row ``copies`` times, in the columns of ``docs``.

    A document without words takes part in no target and is kept once.
    """
    prefix = free_prefix(docs.columns)
    mixed = _taken(docs, prefix, seed, cycle, max_rate)
    times = F.when(F.col(f"{prefix}size") > 0, F.col(f"{prefix}copies")).otherwise(1)
    return mixed.withColumn(f"{prefix}copy", F.explode(F.array_repeat(F.lit(0), times.cast("int")))).select(*docs.columns)


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         CAST('0x' || md5('17:' || coalesce(CAST(doc_id AS VARCHAR), 'null'))[1:13] AS BIGINT) / 4503599627370496.0::DOUBLE AS u
  FROM documents),
sums AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
weighed AS (SELECT *, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS DOUBLE) AS weight FROM sums),
levels AS (SELECT *, 3.0::DOUBLE * source_size / weight AS level FROM weighed),
waters AS (
  SELECT *, (CAST(sum(source_size) OVER () AS DOUBLE) - 3.0::DOUBLE * coalesce(CAST(sum(source_size) OVER before AS BIGINT), 0))
         / (sum(weight) OVER () - coalesce(sum(weight) OVER before, 0)) AS water
  FROM levels WINDOW before AS (ORDER BY level, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
found AS (SELECT arg_min(water, level) AS water FROM waters WHERE water <= level),
targets AS (
  SELECT source, source_size, least(3.0::DOUBLE * source_size, coalesce(found.water, 0) * weight) AS target
  FROM waters LEFT JOIN found ON true),
rates AS (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0 END AS rate FROM targets),
parts AS (SELECT source, CAST(floor(u * 4096) AS BIGINT) AS i, sum(size) AS part FROM sized GROUP BY ALL),
tried AS (
  SELECT rates.source, turn, any_value(rate - floor(rate)) AS fraction, any_value(source_size) AS source_size,
         CAST(sum(part * CASE WHEN (i - turn * 64 + 4096) % 4096 < CAST(floor((rate - floor(rate)) * 4096) AS BIGINT) THEN 2
                              WHEN (i - turn * 64 + 4096) % 4096 = CAST(floor((rate - floor(rate)) * 4096) AS BIGINT) THEN 1 ELSE 0 END) AS BIGINT) AS twice
  FROM parts JOIN rates ON parts.source IS NOT DISTINCT FROM rates.source, range(64) AS t(turn) GROUP BY rates.source, turn),
turns AS (SELECT source, first(turn ORDER BY abs(twice - 2 * fraction * source_size), turn) AS turn FROM tried GROUP BY source),
drawn AS (
  SELECT doc_id, size, source_size, target, rate, u - turn / 64.0::DOUBLE AS place
  FROM sized JOIN rates ON sized.source IS NOT DISTINCT FROM rates.source JOIN turns ON sized.source IS NOT DISTINCT FROM turns.source)
SELECT doc_id, size, source_size, target,
       size * CAST(floor(rate) + CASE WHEN (CASE WHEN place < 0 THEN place + 1 ELSE place END) < rate - floor(rate) THEN 1 ELSE 0 END AS BIGINT) AS taken
FROM drawn
"""
