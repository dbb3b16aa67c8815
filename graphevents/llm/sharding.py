"""Sharding into parts of near equal size by sampled splitters.

Records are ordered by a digest of their text, then id, so copies of a text lie side by side and everything else is in random
order. A size-weighted sample of keys gives quantile boundaries that cut this order into many small ranges; an exact sum per
range shows where each range begins in the whole order, ranges that turn out overfull are subdivided at further sampled keys, and a
running sum inside each range then gives every record its exact place.

Equal texts share a shard. Groups of them (or single records) heavier than a twentieth of a shard, of which there are at most 20 for
each shard, are dealt out first, the heaviest to the emptiest shard; the room that is left is filled up to one level, in the order of
the other records, a group of copies going where its middle byte falls. Only a group heavier than a whole shard is
divided, into whole shards and a rest.

The result depends on the order alone, never on the sample: boundaries only decide which task does the work.
"""

from __future__ import annotations

import bisect

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored, table

SHARDS = 24
#: Rows that one range is meant to hold, sampled keys a range, and the most ranges (bounds what is broadcast: 64 bytes a range).
RANGE_ROWS, OVERSAMPLE, MOST_RANGES = 50_000, 8, 100_000
#: Bytes a record costs besides its text.
OVERHEAD = 8


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32 and the ordering key of every record. Null text counts as empty."""
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select(
        "doc_id", (F.octet_length(raw) + OVERHEAD).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"), F.md5(raw).alias("digest")
    ).withColumn("key", F.concat_ws(" ", "digest", F.lpad(F.coalesce(F.conv(F.hex("doc_id"), 16, 10), F.lit("")), 20, "0")))


def splitters(rows: DataFrame, ranges: int) -> list[str]:
    """Quantile boundaries of a size-weighted sample of keys; fixed by the rows, so reruns agree. The chance of a row is
    proportional to its size, so the sample has about ``ranges`` x OVERSAMPLE keys."""
    total = rows.agg(F.sum("size").alias("bytes")).first()["bytes"] or 0
    if not total or ranges < 2:
        return []
    u = F.pmod(F.xxhash64(F.lit("split"), "key"), F.lit(1 << 30)) / float(1 << 30)
    sample = rows.filter(u < F.col("size") * (ranges * OVERSAMPLE / total)).select("key").distinct()
    keys = sorted(r["key"] for r in sample.collect())
    return sorted({keys[len(keys) * i // ranges] for i in range(1, ranges)}) if keys else []


def placed(rows: DataFrame, bounds: list[str]) -> DataFrame:
    """``rows`` with the number of the range that holds their key."""
    spark = rows.sparkSession
    if not bounds:
        return rows.withColumn("part", F.lit(0).cast("long"))
    # Two levels of bounded arrays: a coarse one, then the one of the coarse range; each is searched by counting smaller bounds.
    step = max(1, int(len(bounds) ** 0.5))
    coarse = bounds[::step]
    smaller = lambda array: F.size(F.filter(array, lambda b: b <= F.col("key")))
    fine = spark.createDataFrame([(i, bounds[i * step : (i + 1) * step]) for i in range(len(coarse))], "c int, fine array<string>")
    out = rows.withColumn("c", smaller(F.array(*[F.lit(b) for b in coarse])) - 1)
    out = out.join(F.broadcast(fine), "c", "left")
    return out.withColumn("part", F.when(F.col("c") < 0, F.lit(0)).otherwise(F.col("c") * step + smaller(F.col("fine"))).cast("long")).drop("c", "fine")


def dealt(heavy: list[tuple[str, int]], total: int, shards: int) -> tuple[dict[tuple[str, int], int], list[float]]:
    """(digest, weight) of the heavy groups -> the shard of each (digest, part of a group), and the place among the other records, by
    bytes, up to which each shard is filled."""
    fair = max(1.0, total / shards)
    parts = [(min(fair, weight - k * fair), digest, k) for digest, weight in heavy for k in range(pieces_of(weight, fair))]
    load, of = [0.0] * shards, {}
    for weight, digest, k in sorted(parts, key=lambda x: (-x[0], x[1:])):
        at = min(range(shards), key=lambda s: (load[s], s))
        load[at] += weight
        of[digest, k] = at
    # The level that the other records fill all shards to.
    room, level = total - sum(load), 0.0
    for k, low in enumerate(sorted(load), 1):
        if room + sum(sorted(load)[:k]) >= k * low:
            level = (room + sum(sorted(load)[:k])) / k
    upto, at = [], 0.0
    for have in load:
        at += max(0.0, level - have)
        upto.append(at)
    return of, upto


def pieces_of(weight: int, fair: float) -> int:
    """Parts of a group: one, unless it is heavier than a shard."""
    return max(1, int(-(-weight // fair)))


def sharded(docs: DataFrame, *, shards: int = SHARDS, range_rows: int = RANGE_ROWS) -> DataFrame:
    """One row a record: doc_id, size, text_crc32, law, shard, slot, grown_shard (null under this law).

    An empty table gives an empty result. Null ids come first among copies of a text. Rows equal in id and text take adjoining
    slots in either order, which is the same result. Extra columns are ignored; size and crc are those of the UTF-8 text.
    """
    spark = docs.sparkSession
    rows = stored(keyed(docs))  # a few dozen bytes a record; the text is read once
    n, total = rows.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    ranges = max(min(MOST_RANGES, n // range_rows + 1), min(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), n // 50 + 1))
    bounds = splitters(rows, ranges)
    for _ in range(3):
        held = placed(rows, bounds).groupBy("part").agg(F.count("*").alias("n"), F.sum("size").alias("bytes")).collect()
        over = [r["part"] for r in held if r["n"] > 2 * range_rows and r["bytes"] > 2 * total / ranges]
        if not over:
            break
        inner = splitters(placed(rows, bounds).filter(F.col("part").isin(over)).drop("part"), 4 * len(over))
        bounds = sorted({*bounds, *inner})
    rows = placed(rows, bounds)

    # Groups of copies by range, then whole: a hot group is many rows of few ranges.
    fair = max(1.0, total / shards)
    by_part = rows.groupBy("digest", "part").agg(F.count("*").alias("k"), F.sum("size").alias("bytes"))
    groups = stored(by_part.groupBy("digest").agg(F.sum("k").alias("k"), F.sum("bytes").alias("weight")).filter((F.col("k") > 1) | (F.col("weight") > fair / 20)))
    heavy = sorted((r["digest"], r["weight"]) for r in groups.filter(F.col("weight") > fair / 20).collect())  # 20 a shard at most
    of, upto = dealt(heavy, total, shards)
    spread = spark.createDataFrame([(d, w, [of[d, k] for k in range(pieces_of(w, fair))]) for d, w in heavy], "heavy string, whole long, shards array<int>")
    rows = rows.join(F.broadcast(spread), F.col("digest") == F.col("heavy"), "left").withColumn("light", F.when(F.col("heavy").isNull(), F.col("size")).otherwise(0))

    sums = sorted((r["part"], r["bytes"], r["light"]) for r in rows.groupBy("part").agg(F.sum("size").alias("bytes"), F.sum("light").alias("light")).collect())
    begin, at, light_at = [], 0, 0
    for part, size, light in sums:
        begin.append((part, at, light_at))
        at, light_at = at + size, light_at + light
    rows = rows.join(F.broadcast(spark.createDataFrame(begin, "part long, begin long, light_begin long")), "part")
    run = Window.partitionBy("part").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("upto", F.col("begin") + F.sum("size").over(run)).withColumn("light_upto", F.col("light_begin") + F.sum("light").over(run))
    rows = stored(rows)
    first = rows.groupBy("digest", "part").agg(F.min(F.col("upto") - F.col("size")).alias("first"), F.min(F.col("light_upto") - F.col("light")).alias("light_first"))
    first = first.join(groups.filter("k > 1"), "digest")
    head = first.groupBy("digest").agg(F.min("first").alias("first"), F.min("light_first").alias("light_first"))
    first = first.select("digest", "part", "weight").join(head, "digest").select(F.col("digest").alias("d"), F.col("part").alias("p"), "weight", "first", "light_first")
    rows = rows.join(first, (F.col("digest") == F.col("d")) & (F.col("part") == F.col("p")), "left")
    middle = F.coalesce(F.col("light_first") + F.col("weight") / 2, F.col("light_upto") - F.col("light") / 2)
    filled = F.size(F.filter(F.array(*[F.lit(float(x)) for x in upto]), lambda x: x <= middle))
    piece = F.floor((F.col("upto") - F.col("size") / 2 - F.coalesce("first", F.col("upto") - F.col("size"))) / F.lit(fair))
    own = F.element_at("shards", (F.least(F.size("shards") - 1, piece) + 1).cast("int"))
    rows = rows.withColumn("shard", F.when(F.col("heavy").isNotNull(), own).otherwise(F.least(F.lit(shards - 1), filled)).cast("int"))
    rows = stored(rows.select("doc_id", "size", "text_crc32", "key", "part", "shard"))

    counts = sorted((r["shard"], r["part"], r["n"]) for r in rows.groupBy("shard", "part").agg(F.count("*").alias("n")).collect())
    offsets, last, at = [], None, 0
    for shard, part, k in counts:
        at = 0 if shard != last else at
        offsets.append((shard, part, at))
        last, at = shard, at + k
    offset = spark.createDataFrame(offsets, "shard int, part long, offset long")
    order = Window.partitionBy("part", "shard").orderBy("key")
    out = rows.join(F.broadcast(offset), ["shard", "part"]).withColumn("slot", (F.row_number().over(order) - 1 + F.col("offset")).cast("long"))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def written(docs: DataFrame, path: str, *, shards: int = SHARDS) -> None:
    """The records themselves, in a directory a shard, each ordered by slot."""
    place = sharded(docs, shards=shards).select(F.col("doc_id").alias("id"), "shard", "slot", F.col("text_crc32").alias("crc"))
    rows = docs.join(place.distinct(), F.col("doc_id").eqNullSafe(F.col("id")) & (F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")) == F.col("crc")))
    rows.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").drop("id", "crc").write.partitionBy("shard").mode("overwrite").parquet(path)


def range_of(key: str, bounds: list[str]) -> int:
    """The range of one key, for tests."""
    return bisect.bisect_right(bounds, key)


def op8(spark, sf_dir: str) -> DataFrame:
    """All ``documents`` in 24 shards under the law ``bytes``; odd rows as in ``sharded``."""
    return sharded(table(spark, sf_dir, "documents"))
