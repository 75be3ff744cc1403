"""Mixing sources to target weights with a time-varying curriculum. DataFrame functions only.

Targets: a share of all words is dealt out by weight, no source above ``most`` times its size, the excess reshared by
weight until none is above. Curriculum: each source's rate over training time u in [0, 1] is its target times a linear
schedule ``1 + slope * (2u - 1)``; its integral is the source's cumulative word demand, whose inverse turns a cumulative
word count into a training position. Documents of a source are laid out in hash order, repeated as often as the target
asks; the last pass stops in the document where the target is met.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import word_count


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = (3.0, 1.0, 2.0), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """``sizes(source, source_size)`` (one row a source) -> plus ``weight, target``.

    Sources take the weights in turn, ordered by code point with null last. At the end of resharing the uncapped
    sources get ``weight * level`` with one common level: sources are ordered by the level at which they reach their
    cap, and the level is found by running sums, with no loop.
    """
    everything = Window.partitionBy(F.lit(0))
    place = F.row_number().over(everything.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))) - 1
    w = F.element_at(F.array(*map(F.lit, weights)), (place % len(weights) + 1).cast("int"))
    rows = sizes.select("source", "source_size", w.alias("weight"), (most * F.col("source_size")).alias("cap"))
    order = Window.partitionBy(F.lit(0)).orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), F.col("source").cast("binary"))
    rows = rows.withColumns({
        "__total": share * F.sum("source_size").over(everything),
        "__capped": F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)),
        "__open": F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)),
    })
    level = (F.col("__total") - F.col("__capped")) / F.col("__open")
    rows = rows.withColumn("__level", level).withColumn("__fits", F.col("__level") * F.col("weight") <= F.col("cap"))
    # the first source that stays below its cap fixes the level of all that follow
    rows = rows.withColumn("__at", F.min(F.when(F.col("__fits"), F.struct(F.col("cap") / F.col("weight"), F.col("__level")))).over(everything)["__level"])
    return rows.select("source", "source_size", "weight", F.coalesce(F.least("cap", F.col("weight") * F.col("__at")), F.col("cap")).alias("target"))


def position(words: Column, target: Column, slope: Column) -> Column:
    """Training time in [0, 1] at which a source's integrated schedule has asked for so many words."""
    q = F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.coalesce(F.try_divide(words, target), F.lit(0.0))))
    # u + slope (u^2 - u) = q
    root = F.sqrt((1 - slope) * (1 - slope) + 4 * slope * q)
    return F.least(F.lit(1.0), 2 * q / ((1 - slope) + root))


def mix(docs: DataFrame, weights: tuple[float, ...] = (3.0, 1.0, 2.0), share: float = 1.5, most: float = 2.0, slopes: tuple[float, ...] = (0.5, -0.5, 0.0), buckets: int = 4096, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns plus source, size, source_size, target, taken, position, last_position (training times of the first and last word taken; null if none is).

    Null texts have size 0 and take nothing; null sources are one source; repeated rows (same id and size) count each,
    in an arbitrary but harmless order among themselves; an empty table gives an empty one; a kept column called like an
    output raises (``source`` comes once). Prefix sums run in two
    levels: ranges of a hash (60 bits of the digest of id and text, so that any SQL engine finds the same layout) deal
    each source into ``buckets``, so a source with a third of all rows is never one group.
    """
    if clash := {k.lower() for k in keep} & {"size", "source_size", "target", "taken", "position", "last_position"}:
        raise ValueError(f"kept columns and outputs share names: {sorted(clash)}")
    digest = F.md5(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), F.coalesce(F.col("text"), F.lit(""))).cast("binary"))
    named = F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("")).alias("__k")  # a source's key, never null
    others = [k for k in keep if k.lower() not in ("source",)]
    rows = docs.select(*others, "source", named, word_count(F.col("text")).alias("__size"), F.conv(F.substring(digest, 1, 15), 16, 10).cast("long").alias("__h"))
    rows = rows.withColumn("__b", F.shiftright("__h", 60 - (buckets - 1).bit_length()))
    by_bucket = rows.groupBy("source", "__k", "__b").agg(F.sum("__size").alias("__in"))
    sizes = by_bucket.groupBy("source").agg(F.sum("__in").alias("source_size"))
    targets = source_targets(sizes, weights, share, most)
    targets = targets.withColumn("__place", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.col("source").isNull(), F.col("source").cast("binary"))) - 1)
    slope = F.element_at(F.array(*map(F.lit, slopes)), (F.col("__place") % len(slopes) + 1).cast("int"))
    before = F.sum("__in").over(Window.partitionBy("__k").orderBy("__b").rowsBetween(Window.unboundedPreceding, -1))
    offsets = by_bucket.select(F.col("source").alias("__s"), "__k", "__b", F.coalesce(before, F.lit(0)).alias("__before"))
    t = targets.select(F.col("source").alias("__t"), F.col("source_size").alias("__source_size"), F.col("target").alias("__target"), slope.alias("__slope"))
    offsets = offsets.join(t, F.col("__s").eqNullSafe(F.col("__t"))).drop("__s", "__t")
    inside = F.sum("__size").over(Window.partitionBy("__k", "__b").orderBy("__h", "__size").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("__size")
    # the window has dealt the rows out by the keys of this join: texts in ``keep`` move once
    rows = rows.withColumn("__inside", inside).join(offsets, ["__k", "__b"])
    at = F.col("__before") + F.col("__inside")
    goal = F.floor("__target")
    full = F.when(F.col("__source_size") > 0, F.least(F.lit(int(most)), F.expr("cast(floor(__target) as bigint) div greatest(__source_size, 1)"))).otherwise(0)
    rest = F.greatest(F.lit(0), goal - full * F.col("__source_size"))
    last = F.greatest(F.lit(0), F.least(F.col("__size"), rest - at))
    rows = rows.withColumns({"__at": at, "__full": full, "__last": last})
    taken = (F.col("__full") * F.col("__size") + F.col("__last")).cast("long")
    end = F.when(F.col("__last") > 0, F.col("__full") * F.col("__source_size") + F.col("__at") + F.col("__last")).otherwise((F.col("__full") - 1) * F.col("__source_size") + F.col("__at") + F.col("__size"))
    any_taken = taken > 0
    return rows.select(
        *others, "source", F.col("__size").alias("size"), F.col("__source_size").alias("source_size"), F.col("__target").alias("target"), taken.alias("taken"),
        F.when(any_taken, position(F.col("__at"), F.col("__target"), F.col("__slope"))).alias("position"),
        F.when(any_taken, position(end, F.col("__target"), F.col("__slope"))).alias("last_position"),
    )


def ordered(mixed: DataFrame, by: str = "position") -> DataFrame:
    """Documents range-sorted by training position, those not taken last: partitions and rows within them follow training order."""
    return mixed.orderBy(F.col(by).asc_nulls_last(), "doc_id")
