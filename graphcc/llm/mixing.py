"""Mixing sources to target weights along a time-varying curriculum (DataFrame functions only).

Targets: sources share all words by weight; none may exceed ``cap`` times its own size,
and the excess goes to the others by weight until none is above. Ordering sources by the
level at which they saturate turns that into prefix sums over the (small) source table.

Training positions: a source's weight changes linearly over a schedule's time t in [0, 1], as
w(t) = d * (1 + slope * (2t - 1)), d its target. The integrated demand is D(t) = d * (t + slope * (t*t - t));
a copy whose words begin at cumulative demand c belongs to the t with D(t) = c, a quadratic's root. Its
position is the part of all words due by then, t + drift * (t*t - t), drift being the mean slope weighted by
target: so equal spans of positions hold equal words, a source has the share w(t) / (sum of all w(t)) of them, and all
targets are met at position 1. Documents are then range-sorted by position.

Which documents a source takes: all of them floor(f) times, f = target / size, and once more
those first in a fixed pseudo-random order until the target is met within one document.
Cumulative sizes come from hash strata: per-stratum sums, then a running sum inside each
stratum, so that a source with a third of all rows is still spread over all tasks.

Null text has size 0; a null source is a source of its own, sorted last. Repeated rows are
mixed one by one; extra columns are ignored. Documents of size 0 are taken with 0 words. The table of sources, one
row each, is sorted in one task; it is broadcast only where the planner finds it small.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphcc.llm.tables import n_words
from graphcc.session import keep

#: Fixed values of the contract: weights of the sources in order, repeating.
WEIGHTS, CAP = (5, 2, 1), 3.0
STRATA_HEX = 3


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: float = CAP) -> DataFrame:
    """``(source, source_size, target)`` from per-source sizes; one row a source."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    level = Window.orderBy("ratio", "rank")
    after = level.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    before = level.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    ranked = sizes.withColumn("rank", F.row_number().over(by_name)).withColumn(
        "weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.col("rank") - 1, F.lit(len(weights))) + 1).cast("int"))
    )
    filled = (
        ranked.withColumn("ratio", cap * F.col("source_size") / F.col("weight"))
        .withColumn("rest", F.sum("source_size").over(everything) - cap * F.coalesce(F.sum("source_size").over(before), F.lit(0)))
        .withColumn("level", F.col("rest") / F.sum("weight").over(after))
    )
    # Saturated sources come first by ratio; the first level not above its own ratio holds for all others.
    first = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "rank", "level"))).over(everything)
    return filled.withColumn("water", first.getField("level")).select(
        "source", "source_size", F.least(F.col("weight") * F.coalesce(F.col("water"), F.lit(0.0)), cap * F.col("source_size")).alias("target"), F.col("rank").alias("source_rank")
    )


def _strata(sized: DataFrame) -> DataFrame:
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")).cast("binary"))
    return sized.withColumn("order_key", key).withColumn("stratum", F.substring("order_key", 1, STRATA_HEX))


def sizes_of(docs: DataFrame) -> DataFrame:
    """``(doc_id, source, size)``: words of each whole text."""
    return docs.select("doc_id", "source", n_words(F.col("text")).alias("size"))


def plan(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: float = CAP, slopes: tuple[float, ...] = (-0.5, 0.0, 0.5), also: tuple[str, ...] = ()) -> DataFrame:
    """Each document of ``(doc_id, source, size)`` with its target, words taken, copies and first position.

    ``slopes`` are cycled over the sources in order: -0.5 starts strong and fades, 0.5 grows. Columns
    in ``also`` break ties and are returned.
    """
    rows = _strata(sized)
    per = rows.groupBy("source", "stratum").agg(F.sum("size").alias("stratum_size"))
    base = per.withColumn("base", F.sum("stratum_size").over(Window.partitionBy("source").orderBy("stratum")) - F.col("stratum_size"))
    goal = targets(per.groupBy("source").agg(F.sum("stratum_size").alias("source_size")), weights, cap)
    slope = F.element_at(F.array(*[F.lit(float(s)) for s in slopes]), (F.pmod(F.col("source_rank") - 1, F.lit(len(slopes))) + 1).cast("int"))
    drift = F.coalesce(F.sum(F.col("target") * F.col("slope")).over(Window.partitionBy()) / F.sum("target").over(Window.partitionBy()), F.lit(0.0))
    goal = goal.withColumn("slope", slope).withColumn("drift", drift)
    where = base.join(goal, base["source"].eqNullSafe(goal["source"])).select(base["source"].alias("s"), base["stratum"].alias("k"), "base", "source_size", "target", "slope", "drift")
    running = Window.partitionBy("source", "stratum").orderBy("order_key", "size", *also).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    inside = rows.withColumn("run", F.sum("size").over(running) - F.col("size"))
    joined = inside.join(where, F.col("source").eqNullSafe(F.col("s")) & (F.col("stratum") == F.col("k"))).withColumn("before", F.col("base") + F.col("run"))
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    # A document gets the further copy if the remainder of the target reaches past its middle; never above the cap.
    extra = F.col("before") + F.col("size") / 2 < F.col("target") - F.col("whole") * F.col("source_size")
    copies = F.least(F.col("whole") + F.when(extra, 1).otherwise(0), F.lit(int(cap)))
    out = joined.withColumn("whole", whole).withColumn("copies", copies.cast("long")).withColumn("taken", F.col("copies") * F.col("size"))
    return out.withColumn("position", position(F.col("before"), F.col("target"), F.col("slope"), F.col("drift"))).select(
        "doc_id", "source", "size", "source_size", "target", "taken", "copies", "before", "slope", "drift", "position", *also
    )


def position(demand, target, slope, drift):
    """The part of all words due when the integrated schedule of a source reaches ``demand``."""
    t = due(demand, target, slope)
    return t + drift * (t * t - t)


def due(demand, target, slope):
    """The time t in [0, 1] at which the integrated schedule of a source reaches ``demand``."""
    share = F.when(target > 0, F.least(demand / target, F.lit(1.0))).otherwise(F.lit(0.0))
    b = 1 - slope
    root = 2 * share / (b + F.sqrt(b * b + 4 * slope * share))  # of slope*t*t + b*t = share, stable for slope near 0
    return F.when(share > 0, F.least(root, F.lit(1.0))).otherwise(F.lit(0.0))


def mix(docs: DataFrame, **options) -> DataFrame:
    """Documents in training order, each as often as it is taken: all columns of ``docs`` (no others).

    Words are counted in one pass over the texts. The texts move twice: to their places, then to their ranges.
    """
    cols = docs.columns
    key = F.monotonically_increasing_id()
    rows = docs.withColumn("__row", key)
    counted = keep(rows.select("__row", "doc_id", "source", n_words(F.col("text")).alias("size"), F.spark_partition_id().alias("split")), "sizes")
    planned = plan(counted, also=("__row",), **options).where("copies > 0").select("__row", "source_size", "target", "copies", "before", "slope", "drift")
    again = F.explode(F.sequence(F.lit(0), F.col("copies").cast("int") - 1))
    placed = planned.withColumn("__copy", again).withColumn("__position", position(F.col("before") + F.col("__copy") * F.col("source_size"), F.col("target"), F.col("slope"), F.col("drift")))
    # Ranges are cut without the texts: row numbers are range-sorted, and the texts go straight to their range.
    # As many ranges as the input has splits: the planner, seeing only small rows, would make far too few for the texts.
    ranges = (counted.agg(F.max("split").alias("m")).first().m or 0) + 1
    placed = placed.select("__row", "__position", "__copy").repartitionByRange(ranges, "__position", "__row", "__copy").withColumn("__range", F.spark_partition_id())
    placed = keep(placed, "placed")
    ranges = (placed.agg(F.max("__range").alias("m")).first().m or 0) + 1
    return rows.join(placed, "__row").repartitionById(ranges, "__range").sortWithinPartitions("__position", "__row", "__copy").select(*cols)
