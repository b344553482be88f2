"""Mixing of sources to target weights by whole repetitions and one drawn copy.

Words are added up per source; targets share ``budget`` of all words by weight and
stop at ``most`` times a source's words, the excess going to the others by weight. A
source's rate is its target over its words. A document is taken floor(rate) times,
and once more if its draw, a hash of seed and id, falls under the rate's fraction: a
Bernoulli copy with that probability. So a source's words meet its target in
expectation, with a standard deviation of sqrt(f (1 - f) * sum of squared sizes).

Plan: one pass reads sizes and draws, one partial aggregate adds sizes up per source,
and the table of sources goes to the rows by broadcast (checked by its number of
rows; beyond that by a join that adaptive execution can split).

Defined results: null text has size 0; a null source is a source, the last in
order; rows that repeat an id share its draw; without words all targets are 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .durable import stored

BUDGET, MOST, WEIGHTS, SEED, BROADCAST_SOURCES = 1.5, 2, (3, 1, 2), "mix-1", 50_000
_BITS = 48


def word_count(text: Column) -> Column:
    """Number of runs of bytes other than 0x20 and 0x09-0x0D (null: 0)."""
    spaced = F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", "     ")
    return F.size(F.array_remove(F.split(spaced, " +"), "")).cast("long")


def draw(key: Column, seed: str = SEED) -> Column:
    """48 hash-seeded bits of an id, as a whole number."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(seed + ":"), F.coalesce(key.cast("string"), F.lit("null"))).cast("binary")), 1, 12), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, most: int = MOST) -> DataFrame:
    """source_key, source_size, target for a table (source_key, source, size). Sources
    are a catalogue: their list alone is ordered in one task."""
    totals = stored(sizes.groupBy("source_key", "source").agg(F.sum("size").alias("source_size")), "sources")
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int"))
    table = stored(totals.withColumn("weight", weight), "weights")
    whole = budget * (table.agg(F.sum("source_size")).first()[0] or 0)
    level, seen = 0.0, None
    while True:  # each round caps more sources or is the last
        capped = F.lit(most) * F.col("source_size") < F.lit(level) * F.col("weight")
        full, n, free = table.agg(F.coalesce(F.sum(F.when(capped, F.col("source_size"))), F.lit(0)), F.count_if(capped), F.sum(F.when(~capped, F.col("weight")))).first()
        if n == seen or not free:
            break
        level, seen = (whole - most * full) / free, n
    return table.select("source_key", "source_size", F.least(F.lit(float(most)) * F.col("source_size"), F.lit(level) * F.col("weight")).alias("target"))


def copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", carry=(), seed: str = SEED, **shares) -> DataFrame:
    """id, size, source_size, target, copies for every row, and the struct ``carried`` of the columns ``carry``."""
    source = F.col(source_col).cast("string")
    # Draws and sizes are taken from the text once; texts travel only if carried.
    rows = docs.select(
        F.col(id_col).alias("id"), word_count(F.col(text_col).cast("string")).alias("size"), F.when(source.isNull(), "n").otherwise(F.concat(F.lit("s"), source)).alias("source_key"),
        source.alias("source"), draw(F.col(id_col), seed).alias("u"), *(F.struct(*carry).alias("carried") for _ in carry[:1]),
    )
    rows = stored(rows, "drawn")
    targets = stored(source_targets(rows.select("source_key", "source", "size"), **shares), "targets")
    # One row a source: a hot source's rows stay where they are, unless there are very many sources.
    small = F.broadcast if targets.count() <= BROADCAST_SOURCES else (lambda df: df)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    targets = targets.withColumn("rate", rate).withColumn("whole", F.floor("rate").cast("int"))
    drawn = F.col("u") < (F.col("rate") - F.col("whole")) * F.lit(float(1 << _BITS))
    return rows.join(small(targets), "source_key").select(
        F.col("id").alias(id_col), "size", "source_size", "target", (F.col("whole") + drawn.cast("int")).alias("copies"), *(["carried"] if carry else [])
    )


def mix(docs: DataFrame, **shares) -> DataFrame:
    """The mixed corpus: each row of ``docs``, with its columns, as often as it is taken."""
    names = docs.columns
    packed = docs.select(F.col("doc_id").alias("mix_id"), F.col("text").alias("mix_text"), F.col("source").alias("mix_source"), *names)
    out = copies(packed, "mix_id", "mix_text", "mix_source", carry=tuple(names), **shares)
    return out.where("copies > 0").select("carried", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("carried.*")
