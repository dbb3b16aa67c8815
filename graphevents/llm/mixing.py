"""Mixing sources to target weights by Pareto order sampling, on DataFrame functions only.

A source whose target is r times its size gives floor(r) whole copies of every document for certain. What is left,
the share f = r - floor(r), is an unequal-probability sample of fixed size: each document gets an inclusion chance
p = min(1, c * weight), by default in proportion to its words, with c set so that the expected words are f times the source's words.
Documents whose chance would exceed 1 are certain, and what they leave is shared by the others. A document is ranked by
(u / (1 - u)) / (p / (1 - p)) for a random u made from a hash of its id, and documents are taken in that order while
the words fit. The last gap is closed by the one document further down the order whose size comes nearest to it, so a source misses its target by at most half of its largest document.

Scale: weights and ranks fall into bins; sums by (source, bin) are combined before the shuffle and tell from which weight on
documents are certain and in which bin of ranks a source's cut lies. That bin is divided again until it holds few rows, and only
those are ever ordered. Tables of a row a source are broadcast up to ``SMALL`` sources and joined beyond; their order by
name and by room is one task's work over as many rows as there are sources.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import document, stored, table, word_count

#: Weights by the rank of a source's name.
CYCLE = (3, 1, 2)
#: Bins of a pass, the rows of a cut bin that are ordered in one task, sources up to which their tables are broadcast.
BINS, ORDERED, SMALL = 512, 50_000, 100_000


def uniform(*columns, seed: str) -> F.Column:
    """A number in (0, 1) from a hash of ``columns``; the same in every run and in every SQL engine that has md5."""
    text = F.concat_ws("|", F.lit(seed), *[F.coalesce(F.col(c).cast("string"), F.lit("null")) for c in columns])
    return (F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("double") + 0.5) / F.lit(281474976710656.0)


def targets(sources: DataFrame, share: float, most: float) -> DataFrame:
    """``source, source_size, weight`` -> also ``target``: ``share`` of all sizes by weight, where no target exceeds ``most``
    times its source's size and the excess goes to the others by weight. Filling by level gives the end of that resharing at
    once: sources are full in the order of size / weight."""
    by_room = Window.orderBy(F.col("source_size") / F.col("weight"), F.col("weight"), F.col("source").asc_nulls_last())
    before, after = by_room.rowsBetween(Window.unboundedPreceding, -1), by_room.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy()
    levels = (
        sources.withColumn("full_before", F.coalesce(F.sum("source_size").over(before), F.lit(0)))
        .withColumn("weight_after", F.sum("weight").over(after))
        .withColumn("everything", F.sum("source_size").over(everything))
        .withColumn("level", (share * F.col("everything") - most * F.col("full_before")) / F.col("weight_after"))
        .withColumn("fits", F.col("level") * F.col("weight") <= most * F.col("source_size"))
        .withColumn("place", F.row_number().over(by_room))
        .withColumn("first", F.min(F.when(F.col("fits"), F.struct("place", "level"))).over(everything))
    )
    level = F.col("place") >= F.col("first.place")
    own = F.when(level, F.col("first.level") * F.col("weight")).otherwise(most * F.col("source_size"))
    return levels.withColumn("target", own.cast("double")).select("source", "source_size", "weight", "target")


def cyclic_weights(sources: DataFrame, cycle: tuple[int, ...] = CYCLE) -> DataFrame:
    """Sources by code point, null last, weigh ``cycle`` repeating. The table has a row a source."""
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    pick = F.element_at(F.array(*[F.lit(w) for w in cycle]), (rank % len(cycle)).cast("int") + 1)
    return sources.withColumn("weight", pick)


def weight_bin(w) -> F.Column:
    """Bins of a weight, finer for small ones; the square root is the same in every engine."""
    return F.floor(4.0 * F.sqrt(w)).cast("long")


def certain(brief: DataFrame, plan: DataFrame) -> DataFrame:
    """``source, size, w`` and ``source, rest`` -> s, c, from_bin: documents of weight bins above ``from_bin`` are taken for certain, the
    others have the chance c * w, and all together are expected to have ``rest`` words."""
    bins = brief.groupBy("source", weight_bin(F.col("w")).alias("wb")).agg(F.sum("size").alias("words"), F.sum(F.col("size") * F.col("w")).alias("mass"), F.max("w").alias("top"))
    bins = bins.join(plan.select(F.col("source").alias("s"), "rest"), F.col("source").eqNullSafe(F.col("s")))
    down = Window.partitionBy("s").orderBy(F.desc("wb"))
    above = F.coalesce(F.sum("words").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    below = F.sum("mass").over(down.rowsBetween(0, Window.unboundedFollowing))
    levels = bins.withColumn("c", F.greatest(F.lit(0.0), (F.col("rest") - above) / F.nullif(below, F.lit(0.0))))
    fits = levels.filter(F.col("c") * F.col("top") < 1.0)
    return fits.groupBy("s").agg(F.max(F.struct("wb", "c")).alias("m")).select("s", F.col("m.c").alias("c"), F.col("m.wb").alias("from_bin"))


def mixed_rows(docs: DataFrame, keep: list, *, share: float = 1.5, most: float = 2.0, cycle: tuple[int, ...] = CYCLE, seed: str = "mix", weight: F.Column | None = None, small: bool = False) -> DataFrame:
    """``keep`` (columns of ``docs``, aliased) with size, source_size, target, copies, taken of every row.

    ``weight``: a column of numbers above 0 that the inclusion chances are in proportion to; None takes the number of words.
    Null text has size 0; a null source is a source of its own; rows that are equal in all of id and text tie and are
    ordered by their size only, which leaves the result the same. An empty table gives an empty result. ``docs`` is read
    by ``source``, ``doc_id`` and ``text``; all else goes through ``keep`` untouched. ``small``: ``keep`` is small beside
    the text, so it is stored with the sizes and the text is read once; otherwise the text is read twice and never moved.
    """
    sized = docs.select(
        F.struct(*keep).alias("row"),
        F.col("source").alias("source"),
        F.col("doc_id").alias("id"),
        word_count(F.col("text")).alias("size"),
        uniform("doc_id", seed=seed).alias("u"),
        (F.lit(None) if weight is None else weight).cast("double").alias("w"),
    ).withColumn("w", F.coalesce("w", F.col("size").cast("double")))
    sized = stored(sized) if small else sized
    brief = sized.select("source", "id", "size", "u", "w")
    brief = brief if small else stored(brief)
    per_source = brief.groupBy("source").agg(F.sum("size").alias("source_size"))
    plan = targets(cyclic_weights(per_source, cycle), share, most)
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    plan = plan.select(
        "source", "source_size", "target",
        F.floor(ratio).alias("whole"),
        (F.col("target") - F.floor(ratio) * F.col("source_size")).alias("rest"),
    )
    plan = stored(plan)  # a row a source
    sources = plan.count()
    if sources == 0:
        return sized.select("row.*", "size", F.lit(0).cast("long").alias("source_size"), F.lit(0.0).alias("target"), F.lit(0).cast("long").alias("copies"), F.lit(0).cast("long").alias("taken"))
    light = F.broadcast if sources <= SMALL else lambda df: df
    plan = stored(plan.join(certain(brief, plan), F.col("source").eqNullSafe(F.col("s")), "left").drop("s"))

    def ranked(rows: DataFrame) -> DataFrame:
        out = rows.join(light(plan.withColumnRenamed("source", "s")), F.col("source").eqNullSafe(F.col("s"))).drop("s")
        sure = weight_bin(F.col("w")) > F.col("from_bin")
        chance = F.least(F.lit(1.0 - 1e-9), F.greatest(F.lit(1e-9), F.when(sure, 1.0).otherwise(F.coalesce(F.col("c") * F.col("w"), F.lit(0.0)))))
        odds = F.col("u") / (1.0 - F.col("u")) * ((1.0 - chance) / chance)
        return out.withColumn("q", odds / (1.0 + odds))

    r = ranked(brief)
    # The stretch of ranks that holds a source's cut, and the words before it: from all ranks down to one of few rows.
    cuts = plan.select(F.col("source").alias("s"), F.lit(0.0).alias("lo"), F.lit(1.0 + 1e-9).alias("hi"), F.lit(0).cast("long").alias("before"))
    while True:
        here = r.join(light(cuts), F.col("source").eqNullSafe(F.col("s"))).filter((F.col("q") >= F.col("lo")) & (F.col("q") < F.col("hi")))
        step = (F.col("hi") - F.col("lo")) / BINS
        bins = here.withColumn("bin", F.least(F.lit(BINS - 1), F.floor((F.col("q") - F.col("lo")) / step)).cast("int"))
        bins = bins.groupBy("source", "bin").agg(F.sum("size").alias("words"), F.count("*").alias("rows"), F.first("rest").alias("rest"), F.first("before").alias("before"), F.min("q").alias("first"), F.max("q").alias("last"))
        up_to = Window.partitionBy("source").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
        bins = bins.withColumn("upto", F.col("before") + F.sum("words").over(up_to))
        # The first bin in which the words no longer fit; everything before it is taken.
        over = bins.filter(F.col("upto") > F.col("rest")).groupBy("source").agg(F.min(F.struct("bin", (F.col("upto") - F.col("words")).alias("before"), "first", "last", "rows")).alias("c"))
        cuts = stored(over.select(F.col("source").alias("s"), F.col("c.first").alias("lo"), F.col("c.last").alias("last"), F.col("c.before").alias("before"), F.col("c.rows").alias("rows")))
        many = cuts.filter((F.col("rows") > ORDERED) & (F.col("last") > F.col("lo")))
        if many.isEmpty():  # or nothing but ties is left
            break
        cuts = cuts.select("s", "lo", (F.col("last") * (1.0 + 1e-15) + 1e-300).alias("hi"), "before")
    inside = r.join(light(cuts), F.col("source").eqNullSafe(F.col("s"))).filter((F.col("q") >= F.col("lo")) & (F.col("q") <= F.col("last")))
    run = Window.partitionBy("source").orderBy("q", "id", "size").rowsBetween(Window.unboundedPreceding, 0)
    inside = inside.withColumn("sofar", F.col("before") + F.sum("size").over(run))
    first_out = inside.filter(F.col("sofar") > F.col("rest")).groupBy("source").agg(F.min(F.struct("q", "id", "size", "sofar")).alias("f"))
    first_out = stored(first_out.select(F.col("source").alias("s"), F.col("f.q").alias("cut_q"), F.col("f.id").alias("cut_id"), F.col("f.size").alias("cut_size"), (F.col("f.sofar") - F.col("f.size")).alias("filled")))
    order = F.struct("q", "id", "size")
    edge = F.struct(F.col("cut_q").alias("q"), F.col("cut_id").alias("id"), F.col("cut_size").alias("size"))
    gap = F.col("rest") - F.col("filled")
    later = r.join(light(first_out), F.col("source").eqNullSafe(F.col("s"))).filter((order >= edge) & (F.col("size") > 0))
    # One document, the nearest to the gap; taking it must come nearer to the target than leaving the gap open.
    closing = later.filter(F.abs(gap - F.col("size")) < gap).groupBy("source").agg(F.min(F.struct(F.abs(gap - F.col("size")).alias("miss"), "q", "id", "size")).alias("f"))
    closing = stored(closing.select(F.col("source").alias("s2"), F.col("f.q").alias("last_q"), F.col("f.id").alias("last_id"), F.col("f.size").alias("last_size")))

    out = ranked(sized)
    out = out.join(light(first_out), F.col("source").eqNullSafe(F.col("s")), "left")
    out = out.join(light(closing), F.col("source").eqNullSafe(F.col("s2")), "left")
    before_cut = F.col("s").isNull() & F.col("cut_q").isNull() | (order < edge)
    last = F.coalesce((F.col("q") == F.col("last_q")) & F.col("id").eqNullSafe(F.col("last_id")) & (F.col("size") == F.col("last_size")), F.lit(False))
    drawn = F.when((F.col("rest") > 0) & (before_cut | last), 1).otherwise(0)
    out = out.withColumn("copies", (F.col("whole") + drawn).cast("long"))
    return out.select("row.*", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mix(spark, docs: DataFrame) -> DataFrame:
    """One row a document: doc_id, size, source_size, target, taken."""
    return mixed_rows(docs, [F.col("doc_id").alias("doc_id")], small=True).select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mixture itself: every row of ``docs`` as often as it is taken, with the columns of ``docs``."""
    packed = mixed_rows(docs, [document(docs)], **options)
    again = packed.filter(F.col("copies") > 0).select("document", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("copy"))
    return again.select("document.*")


def op1(spark, sf_dir: str) -> DataFrame:
    """The mix of all ``documents``, chances in proportion to words; nulls, ties and empty tables as in ``mixed_rows``."""
    return mix(spark, table(spark, sf_dir, "documents"))
