"""Mixing sources to target weights.

Sizes are summed per source; sources in code-point order (null last) weigh ``pattern[0], pattern[1], ...``,
repeating, and share the whole. A source's target stops at ``most`` times its size, and what it
can't take is shared again by weight: the level at which this settles is found in closed form from the sources
sorted by size over weight. A document is then emitted floor(rate) times, and once more if its hash-seeded
uniform number lies below the rate's fraction. The seed of each source is the one, of ``seeds`` stated ones, whose
total comes nearest to the target. Every seed gives each document the fraction as its chance; the choice among seeds ties the documents of a source
together, so the fraction is the chance before the choice, not after it.

Null texts have size 0. Sources may be null or empty; null is a source of its own. Equal rows draw
the same number and are taken alike. A source of size 0 has target 0. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import shared


def _uniform(seed: Column, id_col: Column) -> Column:
    """A number in [0, 1) from the first 32 bits of an MD5 of seed and id."""
    digest = F.md5(F.concat(seed, F.lit(":"), F.coalesce(id_col.cast("string"), F.lit("null"))))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def source_targets(sources: DataFrame, pattern: tuple[int, ...], most: int) -> DataFrame:
    """``sources``: (source, source_size), one row per source. Adds weight and target.

    Level c solves sum(min(most * size, c * weight)) = sum(size): sorted by size over weight, the first k sources are
    full, and c is what is left over the weight that is left.
    """
    every = Window.partitionBy()
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, pattern)), ((F.row_number().over(order) - 1) % len(pattern) + 1).cast("int")).cast("double")
    ranked = sources.withColumn("weight", weight).withColumn("total", F.sum("source_size").over(every))
    by_fill = Window.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = by_fill.rowsBetween(Window.unboundedPreceding, -1)
    left = F.col("total") - most * F.coalesce(F.sum("source_size").over(before), F.lit(0))
    weight_left = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    level = ranked.withColumn("level", left / weight_left).withColumn("full", F.col("level") * F.col("weight") >= most * F.col("source_size"))
    # the levels of later sources are lower, so the largest is that of the first open one
    first_open = F.max(F.when(~F.col("full"), F.col("level"))).over(every)
    return level.withColumn("target", F.when(F.col("full"), (most * F.col("source_size")).cast("double")).otherwise(first_open * F.col("weight"))).select("source", "source_size", "weight", "target")


def _copies(id_col: Column) -> Column:
    """Copies of a row that carries its source's floor, fraction and seed."""
    again = _uniform(F.col("seed").cast("string"), id_col) < F.col("fraction")
    return (F.col("floor") + F.when(again, 1).otherwise(0)).cast("long")


def mixing_rates(sizes: DataFrame, *, pattern: tuple[int, ...] = (1, 2, 3), most: int = 3, seeds: int = 32) -> DataFrame:
    """``sizes``: (id, source, size). One row per source: (source, source_size, weight, target, floor, fraction, seed)."""
    targets = source_targets(sizes.groupBy("source").agg(F.sum("size").alias("source_size")), pattern, most)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    targets = shared.materialize(targets.withColumn("floor", F.floor(rate)).withColumn("fraction", rate - F.floor(rate)), "mix-targets")
    joined = sizes.join(targets.select(F.col("source").alias("of"), "fraction"), F.col("source").eqNullSafe(F.col("of"))).drop("of")
    extra = [F.sum(F.when(_uniform(F.lit(str(s)), F.col("id")) < F.col("fraction"), F.col("size")).otherwise(0)).alias(f"extra_{s}") for s in range(seeds)]
    tried = joined.groupBy(F.col("source").alias("of")).agg(*extra)
    miss = lambda s: F.abs(F.col(f"extra_{s}") + F.col("floor") * F.col("source_size") - F.col("target"))
    best = F.array_min(F.array(*[F.struct(miss(s).alias("miss"), F.lit(s).alias("seed")) for s in range(seeds)]))["seed"]
    return shared.materialize(targets.join(tried, F.col("source").eqNullSafe(F.col("of"))).select(targets["*"], best.alias("seed")), "mix-rates")


def mixing_plan(documents: DataFrame, *, size: Column, id_col: str = "doc_id", source_col: str = "source", **options) -> DataFrame:
    """One row per document: (``id_col``, source, size, source_size, target, copies).

    (id, source, size) is written once; joined is only the table of sources, and sums per source are sums of
    partial sums, so a hot source makes no hot task.
    """
    sizes = shared.materialize(documents.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), size.cast("long").alias("size")), "mix-sizes")
    rates = mixing_rates(sizes, **options).withColumnRenamed("source", "of")
    joined = sizes.join(rates, F.col("source").eqNullSafe(F.col("of")))
    return joined.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", _copies(F.col("id")).alias("copies"))


def mix(documents: DataFrame, *, size: Column, id_col: str = "doc_id", source_col: str = "source", **options) -> DataFrame:
    """The mix itself: each row as often as its copies say, with the columns of ``documents``. Texts aren't shuffled."""
    sizes = shared.materialize(documents.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), size.cast("long").alias("size")), "mix-sizes")
    rates = mixing_rates(sizes, **options).select(F.struct(F.col("source").alias("of"), "floor", "fraction", "seed").alias("__mix"))
    joined = documents.join(rates, documents[source_col].eqNullSafe(F.col("__mix.of")))
    again = _uniform(F.col("__mix.seed").cast("string"), documents[id_col]) < F.col("__mix.fraction")
    copies = (F.col("__mix.floor") + F.when(again, 1).otherwise(0)).cast("int")
    return joined.withColumn("__copy", F.explode(F.array_repeat(F.lit(1), copies))).drop("__copy", "__mix")
