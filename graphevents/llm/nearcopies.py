"""Near duplicates by order MinHash, verified by banded alignment.

A text is the sequence of its five-word stretches, each labelled with how often it occurred before. For each of ``SKETCHES`` random
orders the ``KEPT`` least labelled stretches are taken and put back in text order; their names make one key. Two texts
share a key the likelier the smaller their word edit distance, since both which stretches are least and their order must agree.
Texts that share a key are candidates; a pair is linked when 1 - distance / longer length >= 0.8 for the word edit distance, which
a bit-parallel alignment computes within a band.

Classes need only links that connect, so a bucket is never expanded to its pairs:

1. The bucket's text with most company leads it and is aligned with every other one (as many pairs as rows). Buckets whose texts
   are in one component by now are done.
2. In the others, pairs of different components are held against a lower bound of their distance (lengths and word
   histograms) inside tiles of bounded size. A tile returns a spanning forest of the pairs that are left, never the pairs; its
   components are families. All pairs of a bucket that may be linked and are not yet in one component are in one family.
3. A family's texts meet in tiles, where pairs of different components are aligned, the likeliest first; a tile returns a
   spanning forest of links. Tiles of one and the same component never meet.

So every pair of texts that share a bucket is linked, ruled out, or has both ends in one component already.

Scale: a text leaves its row once, if it has company, into a table bucketed by text id, which later joins read without moving it. Rows
made are in proportion to bucket rows, but for groups beyond a tile, whose rows are repeated once for each other tile: texts of a
family that are neither linked nor ruled out by histograms must all be aligned, whatever the form.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import components
from .common import bucketed, discard, free_shuffles, mixed, slices, stored, table, word_hashes
from .substrings import prefix_names, stretch_names

K, SKETCHES, KEPT, THRESHOLD = 5, 64, 2, 0.8
BINS = 256
#: Texts with company that are broadcast at most: some 60 bytes each.
FEW = 100_000
#: Texts of one tile, when histograms and when whole texts are compared; rows and words that small groups are packed to.
TILE, TEXT_TILE, PACK_ROWS, PACK_WORDS = 4096, 128, 8192, 200_000


def sketched(hashes: np.ndarray, offsets: np.ndarray, k: int = K, sketches: int = SKETCHES, seed: int = 11) -> list[np.ndarray]:
    """The keys of each text. A text of fewer than ``k`` words is one stretch, a text without words has no key."""
    sizes = np.diff(offsets)
    stretches = np.where(sizes == 0, 0, np.maximum(sizes - k + 1, 1))
    at = np.concatenate([[0], np.cumsum(stretches)])
    doc = np.repeat(np.arange(len(sizes)), stretches)
    start = offsets[:-1][doc] + np.arange(at[-1]) - at[:-1][doc]
    name = stretch_names(prefix_names(hashes), start, np.minimum(start + k, offsets[1:][doc]))
    own = name ^ mixed(doc.astype(np.uint64))
    order = np.argsort(own, kind="stable")
    sorted_own = own[order]
    fresh = np.concatenate([[True], sorted_own[1:] != sorted_own[:-1]]) if len(order) else np.zeros(0, bool)
    group = np.flatnonzero(fresh)
    before = np.zeros(len(order), np.int64)
    before[order] = np.arange(len(order)) - np.repeat(group, np.diff(np.concatenate([group, [len(order)]])))
    label = mixed(name ^ mixed((before + 1).astype(np.uint64)))
    factors = np.random.Generator(np.random.PCG64(seed)).integers(1, 1 << 63, sketches, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    salt = mixed(np.arange(sketches).astype(np.uint64) + np.uint64(seed))
    out = []
    none = np.uint64(0xFFFFFFFFFFFFFFFF)
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        if a == b:
            out.append(np.zeros(0, np.uint64))
            continue
        names, labels = name[a:b], label[a:b]
        keys = []
        step = max(1, (1 << 18) // (b - a))  # bounds the table of ranks for very long texts
        for s in range(0, sketches, step):
            rank = labels[None] * factors[s : s + step, None]
            rows, least = np.arange(len(rank)), []
            for _ in range(min(KEPT, b - a)):
                least.append(rank.argmin(axis=1))
                rank[rows, least[-1]] = none
            key = salt[s : s + step]
            for places in np.sort(np.stack(least), axis=0):
                key = mixed(key * np.uint64(3) + names[places])
            keys.append(key)
        out.append(np.concatenate(keys))
    return out


def edit_distance(a: list, b: list, most: int) -> int:
    """The word edit distance of two sequences if it is at most ``most``, else ``most + 1``.

    Common ends are cut off. Then columns of the distance matrix are kept as bits of two numbers (where it rises and falls
    from row to row), a band of ``2 * most + 1`` rows wide that moves down with the diagonal.
    """
    if abs(len(a) - len(b)) > most:
        return most + 1
    i, n = 0, min(len(a), len(b))
    while i < n and a[i] == b[i]:
        i += 1
    j = 0
    while j < n - i and a[-1 - j] == b[-1 - j]:
        j += 1
    a, b = a[i : len(a) - j], b[i : len(b) - j]
    if len(a) > len(b):
        a, b = b, a
    if not a:
        return len(b)
    n, m = len(b), len(a)
    most = min(most, n)
    where: dict = {}
    for p, w in enumerate(b):
        where[w] = where.get(w, 0) | (1 << p)
    if 2 * most + 1 >= n:
        # The band covers the matrix: all rows at once.
        full, last = (1 << n) - 1, 1 << (n - 1)
        up, down, score = full, 0, n
        for j, w in enumerate(a):
            eq = where.get(w, 0)
            diagonal = ((((eq & up) + up) ^ up) | eq | down) & full
            rise = down | (full & ~(diagonal | up))
            fall = diagonal & up
            score += bool(rise & last) - bool(fall & last)
            if score - (m - 1 - j) > most:
                return most + 1
            rise = ((rise << 1) | 1) & full
            up = ((fall << 1) & full) | (full & ~(diagonal | rise))
            down = rise & diagonal
        return score if score <= most else most + 1
    # Row r of column j is bit r - j + most; b runs down, a runs right. Along the top diagonal of the band the score is followed.
    width = 2 * most + 1
    full, lead = (1 << width) - 1, 1 << (width - 1)
    up, down = full ^ ((1 << most) - 1), 0
    score = most  # the score of row j + most in column j, then moved along the last row
    for j, w in enumerate(a):
        shift = j - most
        eq = where.get(w, 0)
        eq = ((eq >> shift) if shift >= 0 else (eq << -shift)) & full
        diagonal = ((((eq & up) + up) ^ up) | eq | down) & full
        rise = down | (full & ~(diagonal | up))
        fall = diagonal & up
        row = j + most  # the row (from 0) that the band's last bit stands for
        if row < n:
            score += 0 if diagonal & lead else 1
        else:
            bit = 1 << (n - 1 - j + most)
            score += bool(rise & bit) - bool(fall & bit)
        up = (fall | (full & ~((diagonal >> 1) | rise))) & full
        down = (diagonal >> 1) & rise
    return score if score <= most else most + 1


def features(docs: DataFrame) -> DataFrame:
    """``doc, digest, raw`` -> doc, digest, n (words), keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "raw"):
            hashes, offsets = word_hashes(b.column("raw").to_pylist())
            keys = sketched(hashes, offsets)
            places = np.concatenate([[0], np.cumsum([len(x) for x in keys])]).astype(np.int32)
            flat = np.concatenate(keys).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("doc"), b.column("digest"), pa.array(np.diff(offsets)), pa.ListArray.from_arrays(places, flat)], ["doc", "digest", "n", "keys"])

    return docs.mapInArrow(run, "doc long, digest string, n long, keys array<long>")


def counts(hashes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """How many words of each text fall in each of 256 classes by hash, 255 at most."""
    n = len(offsets) - 1
    doc = np.repeat(np.arange(n), np.diff(offsets))
    found = np.bincount(doc * BINS + (hashes >> np.uint64(56)).astype(np.int64), minlength=n * BINS)
    return np.minimum(found, 255).astype(np.uint8).reshape(n, BINS)


def with_bins(texts: DataFrame) -> DataFrame:
    """``id, n, raw`` with bins, the word histogram."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "raw"):
            bins = counts(*word_hashes(b.column("raw").to_pylist()))
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("n"), pa.array([x.tobytes() for x in bins], pa.binary()), b.column("raw")], ["id", "n", "bins", "raw"])

    return texts.select("id", "n", "raw").mapInArrow(run, "id long, n long, bins binary, raw binary")


def histograms(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, BINS)


def apart(one: np.ndarray, others: np.ndarray) -> np.ndarray:
    """A lower bound of the word edit distance of ``one`` (one row, or a row for each) and ``others``: one edit changes a histogram by 2 at most, and cutting counts off only lowers it."""
    return (np.maximum(one, others) - np.minimum(one, others)).sum(axis=1, dtype=np.int32) / 2


def met(rows: DataFrame, size: int, packs: int) -> DataFrame:
    """``grp, id, comp, ...`` -> also g, lo, hi, tile: any two rows of a group with different comp share a (g, lo, hi).

    Groups of up to ``size`` rows are packed whole into ``packs`` packs. Larger ones are cut into tiles of about ``size`` rows, a large
    component of the group into tiles of its own; a row goes to every pair that its tile forms, but for two of one component.
    """
    blocks = rows.groupBy("grp", "comp").agg(F.count("*").alias("k"))
    whole = blocks.groupBy("grp").agg(F.sum("k").alias("all"), F.sum(F.when(F.col("k") <= size, F.col("k"))).alias("rest"))
    large = whole.filter(F.col("all") > size).select("grp", F.ceil(F.coalesce("rest", F.lit(0)) / size).cast("long").alias("shared"))
    own = blocks.join(large, "grp").select("grp", "comp", F.when(F.col("k") > size, F.ceil(F.col("k") / size).cast("long")).alias("own"), "shared")
    small = rows.join(large.select("grp"), "grp", "left_anti").withColumns({"g": F.pmod(F.xxhash64("grp"), F.lit(packs)), "lo": F.lit(0).cast("long"), "hi": F.lit(0).cast("long"), "tile": F.lit(0).cast("long")})
    if large.isEmpty():
        return small
    name = lambda part, block: F.xxhash64("grp", block, part)
    upto = lambda k: F.explode(F.sequence(F.lit(0).cast("long"), F.col(k) - 1)).alias("part")
    shared = large.filter("shared > 0").select("grp", F.lit(None).cast("long").alias("block"), upto("shared"))
    tiles = shared.union(own.filter("own is not null").select("grp", F.col("comp").alias("block"), upto("own")))
    tiles = tiles.select("grp", F.col("block").alias("other_block"), name(F.col("part"), F.col("block")).alias("other"))
    block = F.when(F.col("own").isNotNull(), F.col("comp"))
    cut = rows.join(own, ["grp", "comp"]).withColumn("block", block)
    cut = cut.withColumn("tile", name(F.pmod(F.xxhash64(F.when(F.col("own").isNotNull(), F.col("id")).otherwise(F.col("comp"))), F.coalesce("own", "shared")), F.col("block")))
    pairs = cut.join(tiles, "grp").filter(F.col("block").isNull() | ~F.col("block").eqNullSafe(F.col("other_block")))
    pairs = pairs.withColumns({"g": F.col("grp"), "lo": F.least("tile", "other"), "hi": F.greatest("tile", "other")})
    return small.unionByName(pairs.select(*small.columns))


class Forest:
    """Union-find over a few numbered things."""

    def __init__(self, start: np.ndarray) -> None:
        _, first, self.of = np.unique(start, return_index=True, return_inverse=True)
        self.of = first[self.of]

    def join(self, i: int, j: int) -> None:
        self.of[self.of == self.of[j]] = self.of[i]


def in_groups(group: pa.Table) -> Iterator[tuple[np.ndarray, list[tuple[int, np.ndarray]]]]:
    """The rows of each group in a pack or tile pair, and for each of its rows the later ones that it meets."""
    grp, tile = group.column("grp").to_numpy(), group.column("tile").to_numpy()
    lo, hi = group.column("lo")[0].as_py(), group.column("hi")[0].as_py()
    order = np.lexsort((group.column("id").to_numpy(), grp))
    for rows in np.split(order, np.flatnonzero(np.diff(grp[order])) + 1):
        if lo == hi:
            yield rows, [(i, np.arange(i + 1, len(rows))) for i in range(len(rows) - 1)]
        else:
            left, right = np.flatnonzero(tile[rows] == lo), np.flatnonzero(tile[rows] == hi)
            yield rows, [(i, right) for i in left.tolist()]


def families(rows: DataFrame, far: float) -> DataFrame:
    """``grp, id, n, comp, bins`` -> ``a, b``: a spanning forest of the pairs of different components that lengths and histograms leave."""

    def run(group: pa.Table) -> pa.Table:
        ids, n, comp = (group.column(c).to_numpy() for c in ("id", "n", "comp"))
        bins, out = histograms(group.column("bins")), ([], [])
        for rows, meets in in_groups(group):
            mine, lengths, of, trees = ids[rows], n[rows], comp[rows], Forest(np.arange(len(rows)))
            for i, later in meets:
                limit = far * np.maximum(lengths[i], lengths[later]) + 1e-9
                j = later[(of[later] != of[i]) & (trees.of[later] != trees.of[i]) & (np.abs(lengths[later] - lengths[i]) <= limit)]
                if not len(j):
                    continue
                j = j[apart(bins[rows[i]], bins[rows[j]]) <= far * np.maximum(lengths[i], lengths[j]) + 1e-9]
                for x in j.tolist():
                    if trees.of[x] != trees.of[i]:
                        trees.join(i, x)
                        out[0].append(mine[i])
                        out[1].append(mine[x])
        return pa.table({"a": pa.array(out[0], pa.int64()), "b": pa.array(out[1], pa.int64())})

    columns = ["g", "lo", "hi", "grp", "tile", "id", "n", "comp", "bins"]
    return rows.select(*columns).groupBy("g", "lo", "hi").applyInArrow(run, "a long, b long")


def aligned(rows: DataFrame, far: float) -> DataFrame:
    """``grp, id, n, comp, raw`` -> ``a, b``: links between texts of different components, as many as connect what they connect."""

    def run(group: pa.Table) -> pa.Table:
        ids, n, comp = (group.column(c).to_numpy() for c in ("id", "n", "comp"))
        raw, out = group.column("raw").to_pylist(), ([], [])
        bins, numbers = counts(*word_hashes(raw)), {}
        for rows, meets in in_groups(group):
            texts = [None] * len(rows)

            def words(i: int) -> list[int]:
                if texts[i] is None:
                    texts[i] = [numbers.setdefault(w, len(numbers)) for w in raw[rows[i]].split()]
                return texts[i]

            lengths, trees = n[rows], Forest(comp[rows])
            for i, later in meets:
                j = later[(trees.of[later] != trees.of[i]) & (np.abs(lengths[later] - lengths[i]) <= far * np.maximum(lengths[i], lengths[later]) + 1e-9)]
                if not len(j):
                    continue
                least = apart(bins[rows[i]], bins[rows[j]])
                likely = np.argsort(least, kind="stable")
                for x, bound in zip(j[likely].tolist(), least[likely].tolist(), strict=True):
                    most = int(far * max(lengths[i], lengths[x]) + 1e-9)
                    if bound <= most and trees.of[x] != trees.of[i] and edit_distance(words(i), words(x), most) <= most:
                        trees.join(i, x)
                        out[0].append(ids[rows[i]])
                        out[1].append(ids[rows[x]])
        return pa.table({"a": pa.array(out[0], pa.int64()), "b": pa.array(out[1], pa.int64())})

    columns = ["g", "lo", "hi", "grp", "tile", "id", "n", "comp", "raw"]
    return rows.select(*columns).groupBy("g", "lo", "hi").applyInArrow(run, "a long, b long")


def compared(pairs: DataFrame, texts: DataFrame, far: float, most: int = 200) -> DataFrame:
    """``a, b`` -> a, b, na, nb, d for the pairs whose word edit distance d is within ``far`` of the longer length.

    First by lengths and word histograms, which one edit changes by at most 2, then by alignment. ``texts`` is bucketed by id, so pairs
    go to the texts. A text with very many pairs is repeated once for every ``most`` of them and they are dealt out by a hash.
    """
    parts = pairs.groupBy("a").agg(F.ceil(F.count("*") / most).cast("int").alias("parts"))
    dealt = pairs.join(parts, "a").withColumn("salt", F.pmod(F.xxhash64("b"), F.col("parts")).cast("int"))
    dealt = stored(dealt.select("a", "b", "salt"))
    salts = dealt.select("a", "salt").distinct()

    def joined(rows: DataFrame, salts: DataFrame, columns: tuple[str, ...]) -> DataFrame:
        side = lambda x: texts.select(F.col("id").alias(x), *[F.col(c).alias(c + x) for c in columns])
        return rows.join(side("b"), "b").join(salts.join(side("a"), "a"), ["a", "salt"])

    def bounds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            least = apart(histograms(b.column("binsa")), histograms(b.column("binsb")))
            keep = pa.array(least <= far * np.maximum(b.column("na").to_numpy(), b.column("nb").to_numpy()) + 1e-9)
            yield pa.RecordBatch.from_arrays([b.column(c).filter(keep) for c in ("a", "b", "salt")], ["a", "b", "salt"])

    likely = joined(dealt, salts, ("n", "bins")).filter(F.abs(F.col("na") - F.col("nb")) <= far * F.greatest("na", "nb") + 1e-9)
    likely = stored(likely.select("a", "b", "salt", "na", "nb", "binsa", "binsb").mapInArrow(bounds, "a long, b long, salt int"))

    def align(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "rawb"):
            left, last, got = None, None, []
            for x, y in zip(b.column("rawa").to_pylist(), b.column("rawb").to_pylist(), strict=True):
                if x != last:
                    left, last = x.split(), x
                right = y.split()
                most = int(far * max(len(left), len(right)) + 1e-9)
                d = edit_distance(left, right, most)
                got.append(d if d <= most else None)
            keep = pa.array([d is not None for d in got], pa.bool_())
            cols = [b.column(c).filter(keep) for c in ("a", "b", "na", "nb")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array([d for d in got if d is not None], pa.int64())], ["a", "b", "na", "nb", "d"])

    both = joined(likely, likely.select("a", "salt").distinct(), ("n", "raw"))
    out = stored(both.select("a", "b", "na", "nb", "rawa", "rawb").mapInArrow(align, "a long, b long, na long, nb long, d long"))
    discard(dealt, likely)
    return out


def led(rows: DataFrame) -> DataFrame:
    """``key, id, doc, k`` (rows of the key) -> ``a, b``: every text of a bucket with the bucket's leader.

    The leader has most company over all its buckets: texts with few edits of their own keep most least stretches of their kind
    and so are close to the others.
    """
    weight = rows.groupBy("id").agg(F.sum("k").alias("w"))
    rows = rows.select("key", "id", "doc").join(weight, "id")
    lead = rows.groupBy("key").agg(F.min(F.struct((-F.col("w")).alias("w"), "doc", F.col("id").alias("a"))).alias("m")).select("key", "m.a")
    both = rows.join(lead, "key").filter("id <> a")
    return both.select(F.least("a", "id").alias("a"), F.greatest("a", "id").alias("b")).distinct()


def named(ids: DataFrame, found: DataFrame, column: str) -> DataFrame:
    """``ids`` with ``column``: the component of ``id`` in ``found`` (node, component), the id itself where it has none."""
    return ids.join(found.withColumnRenamed("node", "id"), "id", "left").withColumn(column, F.coalesce("component", "id")).drop("component")


def banded(rows: DataFrame, threshold: float) -> DataFrame:
    """``key, id, n, comp`` -> also band: any two rows of a bucket with several components whose lengths allow a link share one, and a band
    has several components.

    A bucket that a tile holds, or that spans at most two classes of length, is one band, in which each row is once; a larger one is
    divided by length: each row is in its own class and the next.
    """
    band = lambda n: F.floor(F.log(n.cast("double")) / F.log(F.lit(1.0 / threshold)) + 1e-9).cast("long")
    several = rows.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y"), F.min("n").alias("short"), F.max("n").alias("long"), F.count("*").alias("k")).filter("x < y")
    wide = (F.col("k") > TILE) & (band(F.col("long")) - band(F.col("short")) > 1)
    rows = stored(rows.join(several.select("key", wide.alias("wide")), "key"))
    own = band(F.col("n"))
    whole, cut = rows.filter("not wide").select("key", "id", "n", "comp", F.lit(0).cast("long").alias("band")), rows.filter("wide")
    if cut.isEmpty():
        return whole
    cut = stored(cut.select("key", "id", "n", "comp", F.explode(F.array(own, own + 1)).alias("band")))
    open_ = cut.groupBy("key", "band").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).filter("x < y").select("key", "band")
    return whole.unionByName(cut.join(open_, ["key", "band"], "left_semi"))


def linked(rows: DataFrame, texts: DataFrame, same: DataFrame, threshold: float) -> DataFrame:
    """``key, id, n, k`` -> ``node, component`` of the texts (ids) that share buckets; ``same`` (src, dst) are linked beforehand."""
    far = 1.0 - threshold
    first = compared(stored(led(rows)), texts, far)
    found = stored(components(first.select(F.col("a").alias("src"), F.col("b").alias("dst")).union(same)))
    open_ = banded(named(rows.select("key", "id", "n"), found, "comp"), threshold)
    open_ = stored(open_.select(F.xxhash64("key", "band").alias("grp"), "id", "n", "comp"))
    packs = 1 + open_.count() // PACK_ROWS
    left = stored(families(met(open_.join(texts.select("id", "bins"), "id"), TILE, packs), far))
    own = stored(components(left.select(F.col("a").alias("src"), F.col("b").alias("dst"))))
    inside = own.select(F.col("node").alias("id"), F.col("component").alias("grp")).join(texts.select("id", "n"), "id")
    inside = stored(named(inside, found, "comp"))
    packs = 1 + int(inside.agg(F.sum("n")).first()[0] or 0) // PACK_WORDS
    more = stored(aligned(met(inside, TEXT_TILE, packs).join(texts.select("id", "raw"), "id"), far))
    # Links of the second step join components of the first.
    ends = named(named(more.withColumnRenamed("a", "id"), found, "src").drop("id").withColumnRenamed("b", "id"), found, "dst").drop("id")
    joined = stored(components(ends.select("src", "dst")))
    out = found.withColumnRenamed("component", "id").join(joined.withColumnRenamed("node", "id"), "id", "left").select("node", F.coalesce("component", "id").alias("component"))
    alone = joined.join(found.select("node"), "node", "left_anti")
    discard(first, open_, left, own, inside, more)
    return stored(out.union(alone))


def classes(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row a document: doc_id, class_id (the least doc_id of its class), kept (doc_id = class_id), n_words.

    Equal texts are one text; a text without words (null, empty, blanks) is in no class but its own. Rows that share a doc_id
    count as one document, whose classes are joined. A null doc_id is in no class, with a null class_id, and is kept. Ties and repeated
    rows do not matter. Extra columns are ignored, an empty table gives an empty result. ``doc_id`` is an integer.
    """
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc"), F.md5(raw).alias("digest"), raw.alias("raw"))
    got = features(rows).filter("n > 0 and doc is not null")
    # A text is known by a number of its own from here on, the same in all that reads the stored table.
    reps = got.groupBy("digest").agg(F.min("doc").alias("doc"), *[F.first(c).alias(c) for c in ("n", "keys")])
    reps = stored(reps.withColumn("id", F.monotonically_increasing_id()))
    free_shuffles(docs.sparkSession)
    open_ = reps.select(F.explode("keys").alias("key"), "id", "doc", "n")
    many = open_.groupBy("key").agg(F.count("*").alias("k")).filter("k > 1")
    company = stored(open_.join(many, "key"))
    free_shuffles(docs.sparkSession)
    members = stored(rows.select("doc", "digest").join(reps.select("digest", "id", "n"), "digest", "left").select("doc", "id", F.coalesce("n", F.lit(0)).cast("long").alias("n")))
    # Several texts under one doc_id are one document, so they are linked.
    of_text = members.filter("id is not null and doc is not null").select("doc", "id").distinct()
    least = of_text.groupBy("doc").agg(F.min("id").alias("src"), F.max("id").alias("y")).filter("src < y").select("doc", "src")
    same = of_text.join(least, "doc").filter("src < id").select("src", F.col("id").alias("dst"))
    own = reps.select(F.col("doc").alias("d"), F.col("digest").alias("g"), "id", "n").join(company.select("id").distinct(), "id", "left_semi")
    own = stored(own)
    # Few texts with company travel to the rows; many meet them by a shuffle.
    own = F.broadcast(own) if own.count() <= FEW else own
    with bucketed(with_bins(rows.join(own, (F.col("doc") == F.col("d")) & (F.col("digest") == F.col("g"))).dropDuplicates(["id"])), "id") as texts:
        found = linked(company, texts, same, threshold)
    of_doc = of_text.join(found, F.col("id") == F.col("node"), "left").groupBy("doc").agg(F.min(F.coalesce("component", "id")).alias("component"))
    heads = of_doc.groupBy("component").agg(F.min("doc").alias("class_id"))
    joined = of_doc.join(heads, "component").select(F.col("doc").alias("i"), "class_id")
    out = members.select("doc", "n").join(joined, F.col("doc") == F.col("i"), "left")
    class_id = F.coalesce("class_id", "doc")
    return out.select(F.col("doc").alias("doc_id"), class_id.alias("class_id"), F.coalesce(F.col("doc") == class_id, F.lit(True)).alias("kept"), F.col("n").alias("n_words"))


def distinct_documents(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row of ``docs`` a class: that with the least doc_id, and of rows that share it the one whose text has the least digest.
    Rows without an id stay, and so do texts without words, each under its own id. Columns may have any names."""
    kept = classes(docs, threshold).filter("kept and doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("rows")).select(F.col("doc_id").alias("kept_id"), "rows")
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("document"), F.col("doc_id").cast("long").alias("own_id"))
    mine = packed.join(kept, F.col("own_id") == F.col("kept_id"))
    once = mine.filter("rows = 1").select("document")
    again = mine.filter("rows > 1").groupBy("own_id").agg(F.min_by("document", F.struct(F.md5(F.coalesce(F.col("document.text"), F.lit(""))), F.to_json("document"))).alias("document")).select("document")
    return once.union(again).union(packed.filter("own_id is null").select("document")).select("document.*")


def op10(spark, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents"))
